"""Frame-level rewrites around a fold: equal units once, balance by length, and the way back to all rows."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def distinct_units(df: DataFrame, text_col: str = "text") -> DataFrame:
    """``text_key, text``: each distinct text once. The key is 128 bits of the text's hashes; groups of copies combine before the shuffle."""
    key = F.concat_ws("-", F.hex(F.xxhash64(text_col)), F.md5(F.col(text_col).cast("binary")))
    return df.where(F.col(text_col).isNotNull()).select(key.alias("text_key"), F.col(text_col).alias("text")).dropDuplicates(["text_key"])


def balance(df: DataFrame, partitions: int, text_col: str = "text") -> DataFrame:
    """Units dealt by size: rows are ranked within their size class by a hash, and each class is spread over all partitions, so that no
    partition gets most of the long units."""
    size = F.floor(F.log2(F.greatest(F.length(text_col), F.lit(1))))
    return df.repartition(partitions, F.pmod(F.xxhash64(text_col) + size, F.lit(partitions)))


def spread(df: DataFrame) -> DataFrame:
    """A scan of few, small files dealt out to all cores: folding costs far more than moving a text. Larger scans stay where they are."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(3 * cores) if df.rdd.getNumPartitions() < cores else df


def rejoin(df: DataFrame, done: DataFrame, text_col: str = "text") -> DataFrame:
    """``df`` without its text beside the results of its distinct texts."""
    key = F.concat_ws("-", F.hex(F.xxhash64(text_col)), F.md5(F.col(text_col).cast("binary")))
    return df.withColumn("text_key", F.when(F.col(text_col).isNotNull(), key)).drop(text_col).join(done, "text_key", "left").drop("text_key")


def fold_distinct(df: DataFrame, id_cols: Sequence[str], text_col: str = "text", only_sizes: bool = False, **options) -> DataFrame:
    """``fold`` over distinct texts only: copies cost a hash and a join instead of a fold. With ``only_sizes`` the triples' sizes, and no triple is moved."""
    from repeatfold.operators.fold import fold, fold_sizes

    units = distinct_units(df, text_col)
    done = (fold_sizes if only_sizes else fold)(units, ["text_key"], "text", **options)
    return rejoin(df.select(*id_cols, text_col), done, text_col)
