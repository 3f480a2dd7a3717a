"""The JVM kernels against the Python ones, unit by unit."""

import random

import pytest

from repeatfold.kernels import baselines, gated, jvm, reach, suffix, tree
from repeatfold.model import FOLDED, GRAMMAR, LZ77, STEP_LOG
from repeatfold.operators import checks, fold
from repeatfold.workloads.methods import FIXTURES


def texts():
    rng = random.Random(5)
    out = [v[0] for v in FIXTURES.values()] + ["", "a", "aa", "ab" * 40, "a" * 90, "äöü𝒳𝒳äöü𝒳" * 3]
    for _ in range(400):
        sigma = rng.choice([1, 2, 3, 5, 20])
        out.append("".join(chr(97 + rng.randrange(sigma)) for _ in range(rng.randint(0, 160))))
    words = ["".join(rng.choice("abcdefgh") for _ in range(rng.randint(2, 9))) for _ in range(60)]
    return [*out, *(" ".join(rng.choice(words) for _ in range(rng.randint(50, 900))) for _ in range(12))]


@pytest.fixture(scope="module")
def units(spark):
    return spark.createDataFrame(list(enumerate(texts())), "id int, text string").repartition(4).cache()



def by_id(units, what, fields, engine, **options):
    out = {}
    for r in jvm.rows(units, ["id"], "text", fields, what, engine, **options).collect():
        out.setdefault(r[0], []).append(r)
    return out


ENGINES = [
    ("reach", {}), ("reach", {"tie": "lex"}), ("reach", {"min_len": 4, "terminator": True}), ("reach", {"max_steps": 3}), ("reach", {"mode": "simple", "order": "ends_first"}), ("reach", {"mode": "simple", "order": "scan"}),
    ("reach", {"mode": "simple", "order": "hash"}), ("tree", {}), ("tree", {"tie": "lex"}), ("tree", {"min_len": 3}), ("gated", {}), ("gated", {"alpha": 0, "beta": 2}), ("gated", {"alpha": 4, "beta": 3, "rescan": True}),
]


@pytest.mark.parametrize(("engine", "options"), ENGINES)
def test_folds(units, engine, options):
    folds = by_id(units, "fold", FOLDED, engine, null_row=True, **options)
    logs = by_id(units, "log", STEP_LOG, engine, **options)
    checked = by_id(units, "checked", checks.CHECKED, engine, **options)
    run = {"reach": reach, "tree": tree, "gated": gated}[engine].run
    for k, text in enumerate(texts()):
        codes = [ord(c) for c in text]
        f = run(codes, *suffix.order_of(codes), **options)
        r = folds[k][0]
        assert (r["n"], r["residual"], [tuple(x) for x in r["factors"]], r["kinds"], r["steps"]) == (f.n, f.residual, f.factors, f.kinds, sum(s.accepted for s in f.steps))
        rows = [fold.step_row(s) for s in f.steps]
        assert [tuple(x)[1:10] + tuple(x)[11:] for x in logs.get(k, [])] == [x[:9] + x[10:] for x in rows]
        assert [x["sort_work"] for x in logs.get(k, [])] == pytest.approx([x[9] for x in rows])
        assert tuple(checked[k][0])[1:4] == (f.n, True, True)
        if engine == "gated" or (options.get("min_len", 2) == 2 and "max_steps" not in options):
            assert checked[k][0]["final"]


@pytest.mark.parametrize("engine", ["reach", "tree", "brute"])
def test_final_is_tested_at_every_least_length(spark, engine):
    """a fold that stops early leaves repeats of ``min_len`` literals; one that does not leaves none, but shorter ones."""
    rows = ["abcdXabcdYefghZefgh", "abcdXabcdYefgZefg", "aaaaaaaaaa", "abcabcabcXabd", "abXab", "", "a", *(t for t in texts() if len(t) < 60)]
    df = spark.createDataFrame(list(enumerate(rows)), "id int, text string").repartition(2)
    left = lambda residual, w: [x for x in (tuple(residual[i : i + w]) for i in range(len(residual) - w + 1)) if min(x) >= 0]
    for least in (1, 3, 4, 7):
        width = max(2, least) if engine == "tree" else least
        for most in (0, 1, None):
            options = {"engine": engine, "min_len": least, **({} if most is None else {"max_steps": most})}
            found = {r["id"]: r["final"] for r in checks.folded(df, ["id"], **options).collect()}
            want = {r["id"]: len(set(x := left(r["residual"], width))) == len(x) for r in fold.fold(df, ["id"], **options).collect()}
            assert found == want and all(found.values()) == (most is None)


def test_factors_and_grammars(units):
    lz = by_id(units, "lz77", LZ77, "lz77")
    grammars = {e: by_id(units, "grammar", GRAMMAR, e, null_row=True) for e in ("longest", "pairs")}
    ruled = {e: by_id(units, "ruled", checks.CHECKED, e) for e in ("longest", "pairs")}
    for k, text in enumerate(texts()):
        codes = [ord(c) for c in text]
        order = suffix.order_of(codes)
        want = [(-1 if r["src"] is None else r["src"] - 1, r["len"], -1 if r["literal"] is None else r["literal"]) for r in lz.get(k, [])]
        assert want == baselines.lz77(codes, *order)
        for e, (rules, start) in {"longest": baselines.longest_grammar(codes, *order), "pairs": baselines.pair_grammar(codes)}.items():
            assert (grammars[e][k][0]["rules"], grammars[e][k][0]["start"]) == (rules, start)
            assert tuple(ruled[e][k][0])[1:] == (len(codes), True, True, True)


def test_null_units_and_integers(spark):
    df = spark.createDataFrame([(1, [1, 2, 1, 2, 0x110005]), (2, None), (3, [])], "id int, codes array<int>")
    rows = {r["id"]: r for r in fold.fold(df, ["id"], "codes").collect()}
    assert rows[1]["residual"] == [1, 2, -2, 0x110005] and rows[2]["residual"] is None and rows[3]["n"] == 0
    assert fold.fold(df, ["id"], "codes", log=True).count() == 1 and checks.folded(df, ["id"], "codes").count() == 2


def test_step_totals_are_those_of_the_log(units):
    from repeatfold.operators import measures

    names = [c.split()[0] for c in fold.TOTALS.split(", ") if c != "n bigint"]
    want = {r["id"]: [r[c] for c in names] for r in measures.step_stats(fold.fold(units, ["id"], engine="tree", log=True), ["id"]).collect()}
    found = {r["id"]: [r[c] for c in names] for r in fold.step_totals(units, ["id"]).collect()}
    assert found.keys() == want.keys()
    for k in want:
        assert found[k] == [pytest.approx(x) if isinstance(x, float) else x for x in want[k]]
    assert "Exchange" not in fold.step_totals(units, ["id"])._jdf.queryExecution().executedPlan().toString().split("InMemoryRelation")[0]


def test_distinct_folds_move_sizes_only(units):
    from repeatfold.plans import planner

    both = units.union(units.selectExpr("id + 10000", "text")).union(units.selectExpr("-1", "cast(null as string)").limit(1))
    found = planner.fold_distinct(both, ["id"], only_sizes=True)
    assert sorted(map(tuple, found.collect()), key=repr) == sorted(map(tuple, fold.sizes(fold.fold(both, ["id"])).select(found.columns).collect()), key=repr)
    assert "residual#" not in found._jdf.queryExecution().optimizedPlan().toString()


def test_pairs_left_in_a_residual(spark):
    df = spark.createDataFrame([(1, [1, 2, -2, 1, 2, 1, 2, 3]), (2, None), (3, [])], "id int, residual array<int>")
    assert {r["id"]: r["violations"] for r in fold.irreducible(df).collect()} == {1: 2, 2: 0, 3: 0}


def test_factors_of_a_unit_stay_together(spark):
    from repeatfold.operators.baselines import lz77_texts, lz77_units

    df = spark.createDataFrame([(1, "abababxab𝒳𝒳𝒳"), (2, None), (3, "")], "id int, text string")
    back = lz77_texts(lz77_units(df, ["id"]))
    assert sorted(map(tuple, back.collect())) == [(1, "abababxab𝒳𝒳𝒳"), (2, None), (3, "")]
    assert "Exchange" not in back._jdf.queryExecution().executedPlan().toString()


def test_windows_tell_strings_apart(spark):
    from repeatfold.operators.repeats import windows

    rows = texts()
    df = spark.createDataFrame(list(enumerate(rows)), "id int, text string")
    for width in (1, 3, 48):
        found = windows(df, ["id"], width).collect()
        want = {(k, t[i : i + width]) for k, t in enumerate(rows) for i in range(len(t) - width + 1)}
        assert len(found) == len(want) and len({(r["a"], r["b"]) for r in found}) == len({x for _, x in want})


def test_stream_histograms_give_the_bits_of_whole_outputs(spark):
    from repeatfold.operators import baselines as b
    from repeatfold.operators import measures

    docs = spark.createDataFrame([(k, "ab"[k % 2], t) for k, t in enumerate(texts()[:120])], "id int, lang string, text string").repartition(3)
    ids, key = ["id", "lang"], ["lang"]
    whole = {
        "fold": measures.fold_streams(fold.fold(docs, ids), key), "simple": measures.fold_streams(fold.fold_simple(docs, ids), key), "gated": measures.fold_streams(fold.fold_gated(docs, ids), key),
        "longest": measures.grammar_streams(b.grammar_longest(docs, ids), key), "pairs": measures.grammar_streams(b.grammar_pairs(docs, ids), key), "lz77": measures.lz77_streams(b.lz77(docs, ids), key),
    }
    for name, streams in whole.items():
        want = {tuple(r)[:2]: tuple(r)[2:] for r in measures.histogram_bits(streams, [*key, "stream"], "x").select("lang", "stream", "n", "bits").collect()}
        found = {tuple(r)[:2]: tuple(r)[2:] for r in measures.stream_bits(measures.stream_counts(docs, key, name), key).collect()}
        assert found == {k: pytest.approx(v) for k, v in want.items()}
    counts = measures.stream_counts(docs, key, "fold", joined=True)
    for code in ("entropy", "huffman", "fixed"):
        cols = ["lang", "n_residual", "n_kinds", "n_factors", "bit_residual", "bit_kinds", "bit_factors", "alpha", "beta", "total_bits"]
        want = sorted(map(tuple, measures.bit_costs(fold.fold(docs, ids), key, code).select(cols).collect()))
        found = sorted(map(tuple, measures.stream_costs(counts, docs.select("lang").distinct(), key, code).select(cols).collect()))
        assert [r[0] for r in found] == [r[0] for r in want] and [r[1:] for r in found] == [pytest.approx(r[1:]) for r in want]


def test_families_and_fixtures_read_their_tables(spark):
    from conftest import SF
    from pyspark.sql import functions as F

    from repeatfold.sources import tables
    from repeatfold.workloads import methods

    orders, customers = (methods.load_table(spark, SF, t).count() for t in ("orders", "customer"))
    assert methods.hand_fixtures(spark, SF).agg(F.sum("customers")).first()[0] == customers
    for rows, times in ((methods.family_fold(spark, SF), 1), (methods.gate_failure_grid(spark, SF), 3), (methods.gate_failure_two_blocks(spark, SF), 3)):
        assert rows.agg(F.sum("n_orders")).first()[0] == times * orders
    pairs = spark.createDataFrame([(1, 1), (8, 3), (79, 30)], "r long, s long")
    for blocks, make in ((1, tables.adversarial_text), (2, tables.adversarial_text2)):
        for r in tables.adversarial_units(pairs, blocks).collect():
            assert r["codes"] == [ord(c) for c in make(r["r"], r["s"])]


def test_methods_share_a_pass_and_histograms_leave_in_parts(spark):
    """one scan for all methods; what a task hands on early, or for a null key, is counted in full."""
    from pyspark.sql import functions as F

    from repeatfold.operators import measures
    from repeatfold.workloads import methods

    rows = [(k, None if k % 3 == 2 else "ab"[k % 3], None if k % 40 == 7 else t) for k, t in enumerate(texts()[-90:])]
    docs = spark.createDataFrame([*rows, (1000, "only null", None)], "id int, lang string, text string").repartition(3)
    names = list(measures.STREAMS)
    cols = ["lang", "method", "stream", "x", "n"]
    whole = sorted(map(tuple, measures.method_counts(docs, ["lang"], names).select(cols).collect()), key=repr)
    assert sorted(map(tuple, measures.method_counts(docs, ["lang"], names, limit=50).select(cols).collect()), key=repr) == whole
    parts = [measures.stream_counts(docs, ["lang"], m).withColumn("method", F.lit(m)).select(cols).collect() for m in names]
    assert sorted((tuple(r) for p in parts for r in p), key=repr) == whole
    found = {r["lang"]: r for r in methods.ratios(docs, ["lang"]).collect()}
    assert found.keys() == {None, "a", "b", "only null"} and all(found[k]["fold_bits"] > 0 and found[k]["input_bits"] > 0 for k in (None, "a", "b"))
    assert (found["only null"]["n_units"], found["only null"]["fold"], found["only null"]["input_bits"]) == (0, None, None)


def test_gate_without_refusals_takes_the_same_copies(units):
    for options in ({}, {"alpha": 0, "beta": 2}, {"alpha": 4, "beta": 3.5, "rescan": True}, {"alpha": 0, "beta": 5, "gate_type1": "always"}):
        both = [by_id(units, "fold", FOLDED, "gated", **options, **more) for more in ({}, {"refused": False})]
        assert both[0] == both[1]


def test_ratios_of_labelled_documents_scan_texts_twice(spark):
    """one pass for gzip and sizes, one for all methods."""
    from conftest import SF

    from repeatfold.workloads import methods

    rows = methods.ratio_by_quality(spark, SF)
    plan = rows._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("MapPartitions") == 1 and plan.count("ArrowEvalPython") == 1
    labelled = methods.load_table(spark, SF, "documents").join(methods.load_table(spark, SF, "labels"), "doc_id").where("text is not null")
    assert sum(r["n_units"] for r in rows.collect()) == labelled.count()


def test_labelled_texts_are_dealt_out_at_any_size_of_labels(spark, tmp_path):
    """the same join whether labels could be broadcast or not, without a sort of texts; ids that are null, missing or stand twice are joined as SQL does."""
    from pyspark.sql import functions as F

    from repeatfold.workloads import methods

    docs = [(None if k % 17 == 3 else k // 2, None if k % 13 == 5 else t) for k, t in enumerate(texts()[:60])]
    labels = [(None if k % 9 == 4 else k % 25, None if k % 7 == 2 else k % 2, k % 3) for k in range(40)]
    spark.createDataFrame(docs, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    both = methods.load_table(spark, str(tmp_path), "documents").join(F.broadcast(methods.load_table(spark, str(tmp_path), "labels")), "doc_id")
    want, before, found = sorted(methods.ratios(both, ["quality", "toxic"]).collect(), key=repr), spark.conf.get("spark.sql.autoBroadcastJoinThreshold"), []
    try:
        for most in ("-1", "100m"):
            spark.conf.set("spark.sql.autoBroadcastJoinThreshold", most)
            rows = methods.ratio_by_quality(spark, str(tmp_path))
            plan = [x for x in rows._jdf.queryExecution().executedPlan().toString().splitlines() if "[doc_id#" in x]
            found.append((sum("ShuffledHashJoin" in x for x in plan), any("BroadcastHashJoin" in x or "Sort" in x for x in plan)))
            assert sorted(rows.collect(), key=repr) == want
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
    assert found == [(2, False)] * 2 and len(want) == 9


def test_texts_of_a_key_are_gathered_as_they_are(spark):
    """a unit of many texts holds no object for each symbol, and is the same unit."""
    from repeatfold.sources import tables
    from repeatfold.workloads import methods

    rows = [(k, None if k % 5 == 4 else "ab"[k % 2], None if k % 11 == 3 else t) for k, t in enumerate(texts()[:90])]
    docs = spark.createDataFrame([*rows, (-1, "b", ""), (-2, "c", "𝒳a𝒳a")], "doc_id int, source string, text string").repartition(4)
    units, whole = (make(docs, ["source"], ["doc_id"]) for make in (tables.grouped_texts, tables.grouped_units))
    found, want = fold.fold_sizes(units, ["source"], "texts", ended=True), fold.fold_sizes(whole, ["source"], "codes")
    assert sorted(map(tuple, found.collect()), key=repr) == sorted(map(tuple, want.collect()), key=repr) and want.count() == 4
    assert all(r["lossless"] and r["balanced"] and r["final"] for r in checks.folded(units, ["source"], "texts", ended=True).collect())
    from conftest import SF

    for name in ("fold_by_source", "checked_fold_sources"):
        assert "split(" not in methods.QUERIES[name](spark, SF)._jdf.queryExecution().optimizedPlan().toString()
