"""Edge cases of the frame operators, sources and sinks."""

from pyspark.sql import functions as F

from repeatfold.functions.columns import gate, unfold_text
from repeatfold.operators import baselines, fold, measures, repeats
from repeatfold.plans import planner
from repeatfold.sources import folded_source, tables

ODD = [(1, "ab#$ab#$ab"), (2, None), (3, ""), (4, "a"), (5, "naïve😀naïve😀"), (6, "abcabc"), (6, "abcabc"), (7, "a" * 300)]


def odd(spark):
    return spark.createDataFrame(ODD, "id long, text string").repartition(4)


def test_round_trip_of_odd_units(spark):
    for f in (fold.fold(odd(spark), ["id"]), fold.fold_simple(odd(spark), ["id"]), fold.fold_gated(odd(spark), ["id"], alpha=0, beta=2), fold.fold(odd(spark), ["id"], engine="tree", terminator=True)):
        assert sorted(map(tuple, fold.unfold(f).collect()), key=str) == sorted(ODD, key=str)
        text = f.select("id", unfold_text(F.col("residual"), F.col("factors"), F.col("kinds")).alias("text"))
        assert sorted(map(tuple, text.collect()), key=str) == sorted(ODD, key=str)


def test_empty_frames(spark):
    none = odd(spark).where("id < 0")
    assert fold.fold(none, ["id"]).count() == 0 and fold.fold(none, ["id"], log=True).count() == 0
    assert repeats.suffix_rows(none, ["id"]).count() == 0 and baselines.lz77(none, ["id"]).count() == 0


def test_other_symbols(spark):
    df = spark.createDataFrame([(1, bytearray(b"\x00\x01\x00\x01"), [5, 6, 5, 6], ["x", "y", "x", "y"])], "id int, b binary, i array<int>, s array<string>")
    sizes = [fold.sizes(fold.fold(df, ["id"], c)).first()["residual_len"] for c in ("b", "i", "s")]
    assert sizes == [3, 3, 3]


def test_distinct_units_give_all_rows(spark):
    a = planner.fold_distinct(odd(spark), ["id"]).select("id", "n", "steps")
    b = fold.fold(odd(spark), ["id"]).select("id", "n", "steps")
    assert sorted(map(str, a.collect())) == sorted(map(str, b.collect()))


def test_measures(spark):
    f = fold.fold(odd(spark), ["id"])
    assert measures.lossless(odd(spark).dropDuplicates(), fold.unfold(f).dropDuplicates(), ["id"]).first()["wrong"] == 0
    for code in ("entropy", "huffman", "fixed"):
        r = measures.bit_costs(f.withColumn("g", F.lit(1)), ["g"], code).first()
        assert r["alpha"] > 0 and r["beta"] > 1 and r["total_bits"] > 0
    h = measures.histogram_bits(spark.createDataFrame([(c,) for c in "aabc"], "c string"), [], "c").first()
    assert h["bits"] == 1.5
    assert abs(measures.slope([(2**k, 3.0 * 2**k) for k in range(5)]) - 1) < 1e-9


def test_gate_column(spark):
    row = spark.range(1).select(gate(F.lit(81), F.lit(30), 30, 80).alias("a"), gate(F.lit(81), F.lit(29), 30, 80).alias("b"), gate(F.lit(90), F.lit(0), 30, 80).alias("c"), gate(F.lit(2), F.lit(0), 0, 2).alias("d")).first()
    assert tuple(row) == (True, False, False, True)


def test_sinks_and_sources(spark, tmp_path):
    f = fold.fold(odd(spark).where("id <> 6").withColumnRenamed("id", "unit_id"), ["unit_id"])
    tables.write_folded(f, f"{tmp_path}/p")
    assert tables.read_folded(spark, f"{tmp_path}/p", "unit_id bigint").exceptAll(f).count() == 0
    spark.dataSource.register(folded_source.FoldedSource)
    f.write.format("folded").mode("overwrite").save(f"{tmp_path}/f")
    assert spark.read.format("folded").load(f"{tmp_path}/f").exceptAll(f).count() == 0
    tables.write_json(f, f"{tmp_path}/j")
    assert tables.load_json(spark, f"{tmp_path}/j", "unit_id bigint, n bigint").count() == 6
    (tmp_path / "t.txt").write_text("abab\nxyxy\n")
    assert tables.load_text(spark, f"{tmp_path}/t.txt").count() == 2 and tables.load_text(spark, f"{tmp_path}/t.txt", whole=True).count() == 1


def test_tree_export(spark):
    t = repeats.suffix_tree(spark.createDataFrame([(1, "abcabcaabcdabcacabc$")], "id int, text string"), ["id"])
    inner = {r["depth"] for r in t.where("leaf_id is null and parent >= 0").collect()}
    assert inner == {1, 2, 3, 4} and t.where("leaf_id is not null").count() == 21
