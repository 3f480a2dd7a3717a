"""Corpus mode against the kernels on small units."""

from repeatfold.kernels import reach, suffix
from repeatfold.plans import corpus


def test_rounds_equal_the_sequential_fold(spark):
    units = {1: "abcabcaabcdabcacabc", 2: "aabaaPaabaabaaabaaQ", 3: "xyzzyxyzzy", 4: "q"}
    places = spark.createDataFrame([(u, i + 1, ord(c)) for u, t in units.items() for i, c in enumerate(t)], "unit long, pos long, code int")
    want = []
    for u, t in units.items():
        c = [ord(x) for x in t]
        for s in reach.steps_of(len(c), *suffix.order_of(c)):
            want += [(u, s.len, s.first + 1, p + 1, k) for p, k in s.picks]
    assert sorted(map(tuple, corpus.fold_steps(places).collect())) == sorted(want)


def test_no_repeat(spark):
    places = spark.createDataFrame([(1, 1, 97), (1, 2, 98)], "unit long, pos long, code int")
    assert corpus.fold_steps(places).count() == 0
    assert corpus.fold_steps(places.where("pos < 0")).count() == 0


def test_documents_grouped_by_source(spark):
    from repeatfold.sources.tables import grouped_units

    rows = [(1, "a", "abcabca"), (3, "a", "bcabcq"), (2, "a", ""), (4, "b", "xyzzy"), (5, "b", "xyzzy"), (6, None, "aaaa"), (7, "b", None)]
    docs = spark.createDataFrame(rows, "doc_id long, source string, text string").repartition(3)
    places, names = corpus.grouped_positions(docs, ["source"], ["doc_id"])
    name = {r["unit"]: r["source"] for r in names.collect()}
    want, codes = [], {r["source"]: r["codes"] for r in grouped_units(docs, ["source"], ["doc_id"]).collect()}
    got = {s: [] for s in codes}
    for r in places.orderBy("unit", "pos").collect():
        got[name[r["unit"]]].append(r["code"])
    assert got == codes
    for s, c in codes.items():
        want += [(s or "", x.len, x.first + 1, p + 1, k) for x in reach.steps_of(len(c), *suffix.order_of(c)) for p, k in x.picks]
    assert sorted((name[r["unit"]] or "", r["len"], r["first"], r["pos"], r["kind"]) for r in corpus.fold_steps(places).collect()) == sorted(want)
