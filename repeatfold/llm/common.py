"""Loading, cutting lineage and connected components, shared by the operators of this subpackage."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from repeatfold.plans.lineage import cut, drop_cut, shared_dir

__all__ = ["components", "cut", "drop_cut", "fresh", "row_key", "shared_dir", "spread_out", "table"]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def fresh(df: DataFrame, *names: str) -> list[str]:
    """``names`` changed, if need be, into ones that ``df`` has no column of."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out


def row_key(id_: Column, text: Column) -> tuple[Column, Column]:
    """Two numbers that name a row by its id (of any type; null too) and its text; rows alike in both have the same fate."""
    return F.xxhash64(id_.isNull(), id_.cast("string")), F.xxhash64(text)


def spread_out(df: DataFrame, *keys: str) -> DataFrame:
    """Dealt by ``keys`` into as many partitions as the session's shuffles have, in a way that stages may not coalesce."""
    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return df.repartition(n, *keys)


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Connected components of ``edges (a, b)``, nodes of any one orderable type: one row ``(node, component)`` for each node of an edge.

    The component is its smallest node. Alternating large and small stars; each round is written to the shared folder, and only a count
    and a checksum reach the driver. The least neighbours are a written table too, so that the join with them has two shuffled sides and
    adaptive execution may split the centre of a giant component. Nulls and self-loops are dropped; no edges give no rows.
    """
    e = cut(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct())
    state = None
    for _ in range(max_rounds):
        now = e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now[0] == 0 or now == state:
            break
        state = now
        both = e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = cut(both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        near = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(near, "u").select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("x"))
        last, e = e, cut(small.select(F.greatest("x.u", "x.v").alias("u"), F.least("x.u", "x.v").alias("v")).where("u <> v").distinct())
        drop_cut(last)
        drop_cut(least)
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return e.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("component")).union(e.select("v", "v").distinct())
