"""Sources and sinks: the given tables, other formats, generated families, folded units."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from repeatfold.model import FOLDED


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One given table. Filters and columns reach the Parquet scan, since nothing stands between."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load_text(spark: SparkSession, path: str, whole: bool = False) -> DataFrame:
    """Units ``(unit_id, text)`` from text files: a line each, or with ``whole`` a file each."""
    return spark.read.text(path, wholetext=whole).select(F.xxhash64(F.input_file_name(), "value").alias("unit_id"), F.col("value").alias("text"))


def load_json(spark: SparkSession, path: str, schema: str) -> DataFrame:
    return spark.read.schema(schema).json(path)


def load_csv(spark: SparkSession, path: str, schema: str) -> DataFrame:
    return spark.read.schema(schema).csv(path, header=True)


def grouped_units(df: DataFrame, key_cols: Sequence[str], order_cols: Sequence[str], text_col: str = "text") -> DataFrame:
    """One unit a key: ``key, codes array<int>``, its texts in order, each ended by a terminator of its own (codes beyond all characters).

    A unit is folded by one task, so a key's texts must fit a worker; larger keys belong to the corpus mode.
    """
    code = F.transform(F.split(F.col("_t"), ""), lambda c: _code_point(c))
    row = df.withColumn("_t", F.col(text_col)).where("_t is not null").select(*key_cols, F.struct(*order_cols, F.when(F.col("_t") == "", F.array().cast("array<int>")).otherwise(code).alias("c")).alias("r"))
    parts = row.groupBy(*key_cols).agg(F.array_sort(F.collect_list("r")).alias("rs"))
    ended = F.transform(F.col("rs"), lambda r, k: F.concat(r["c"], F.array(k + 0x110000)))
    return parts.select(*key_cols, F.flatten(ended).alias("codes"))


def grouped_texts(df: DataFrame, key_cols: Sequence[str], order_cols: Sequence[str], text_col: str = "text") -> DataFrame:
    """``key, texts array<string>``: the units of ``grouped_units`` before their texts become codes, for kernels with ``ended``.

    A text of the row takes its own bytes, not an object for each symbol; the bound on a key's texts is the same.
    """
    rows = df.where(F.col(text_col).isNotNull()).groupBy(*key_cols).agg(F.array_sort(F.collect_list(F.struct(*order_cols, F.col(text_col).alias("_t")))).alias("r"))
    return rows.select(*key_cols, F.transform("r", lambda x: x["_t"]).alias("texts"))


def _code_point(c):
    return F.ascii(c).cast("int")  # the first character's code point


def symbol_units(df: DataFrame, key_cols: Sequence[str], order_cols: Sequence[str], symbol_col: str) -> DataFrame:
    """One unit a key: ``key, symbols array<string>`` in order (an event sequence, a run of flags)."""
    rows = df.where(F.col(symbol_col).isNotNull()).groupBy(*key_cols).agg(F.array_sort(F.collect_list(F.struct(*order_cols, F.col(symbol_col).alias("_s")))).alias("r"))
    return rows.select(*key_cols, F.transform("r", lambda x: x["_s"]).alias("symbols"))


def sign_units(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """``id, text``: the signs of a vector's components as 0 and 1."""
    return vectors.select(id_col, F.array_join(F.transform(vector_col, lambda x: F.when(x < 0, "0").otherwise("1")), "").alias("text"))


def adversarial_text(r: int, s: int) -> str:
    """A letter, r distinct fresh letters and the letter again, s + 1 times, each with a separator of its own; and an end letter."""
    middle = "".join(chr(0x4E00 + k) for k in range(r))
    return "".join(f"a{middle}a{chr(0x3000 + 0x100 + k)}" for k in range(s + 1)) + "$"


def adversarial_text2(r: int, s: int) -> str:
    """The family with a second block: another middle and other separators."""
    other = "".join(chr(0x6E00 + k) for k in range(r))
    return adversarial_text(r, s)[:-1] + "".join(f"a{other}a{chr(0x3000 + 0x800 + k)}" for k in range(s + 1)) + "$"


def adversarial_df(spark: SparkSession, grid: Sequence[tuple[int, int]], blocks: int = 1) -> DataFrame:
    make = adversarial_text if blocks == 1 else adversarial_text2
    return spark.createDataFrame([(r, s, make(r, s)) for r, s in grid], "r int, s int, text string")


def adversarial_units(pairs: DataFrame, blocks: int = 1) -> DataFrame:
    """``pairs`` (with ``r, s``) beside ``codes``: the symbols of ``adversarial_text`` (or of ``adversarial_text2``)."""

    def block(middle: int, separator: int):
        one = lambda k: F.concat(F.array(F.lit(97)), F.transform(F.sequence(F.lit(0), (F.col("r") - 1).cast("int")), lambda j: j + middle), F.array(F.lit(97), k + separator))
        return F.flatten(F.transform(F.sequence(F.lit(0), F.col("s").cast("int")), one))

    parts = [block(0x4E00, 0x3100), *([block(0x6E00, 0x3800)] if blocks == 2 else [])]
    return pairs.withColumn("codes", F.concat(*parts, F.array(F.lit(ord("$")))))


def write_folded(folded: DataFrame, path: str, partition_by: Sequence[str] = ()) -> None:
    """Triples as Parquet, one column a component, so a reader of one takes that one only."""
    folded.write.mode("overwrite").partitionBy(*partition_by).parquet(path)


def read_folded(spark: SparkSession, path: str, ids: str) -> DataFrame:
    return spark.read.schema(f"{ids}, {FOLDED}").parquet(path)


def write_json(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").json(path)
