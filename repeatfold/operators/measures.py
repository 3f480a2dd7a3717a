"""Cost and accuracy measures of folds and baselines: one aggregation over one row a unit or step each."""

from __future__ import annotations

import heapq
import math
from collections.abc import Sequence

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType


def entropy_of(counts: Column) -> Column:
    """Zero-order bits a symbol of a histogram given as an array of counts."""
    total = F.aggregate(counts, F.lit(0.0), lambda a, x: a + x)
    return F.aggregate(counts, F.lit(0.0), lambda a, x: a - (x / total) * F.log2(x / total))


@F.pandas_udf(DoubleType())
def huffman_mean(counts: pd.Series) -> pd.Series:
    """Mean code length of a Huffman code for each histogram; one symbol takes one bit."""

    def one(c) -> float:
        heap = sorted(float(x) for x in c)
        total, bits = sum(heap), 0.0
        if len(heap) == 1:
            return 1.0
        heapq.heapify(heap)
        while len(heap) > 1:
            x = heapq.heappop(heap) + heapq.heappop(heap)
            bits += x
            heapq.heappush(heap, x)
        return bits / total if total else 0.0

    return counts.map(one)


def histogram_bits(symbols: DataFrame, keys: Sequence[str], symbol: str, code: str = "entropy") -> DataFrame:
    """``keys, n, distinct, bits``: symbols of each key (rows), and mean bits under the code: entropy, huffman or fixed."""
    counts = symbols.groupBy(*keys, symbol).agg(F.count("*").alias("_count")).groupBy(*keys).agg(F.sum("_count").alias("n"), F.count("*").alias("distinct"), F.array_sort(F.collect_list(F.col("_count").cast("double"))).alias("cs"))
    bits = {"entropy": entropy_of(F.col("cs")), "huffman": huffman_mean(F.col("cs")), "fixed": F.ceil(F.log2(F.greatest(F.col("distinct"), F.lit(2)))).cast("double")}[code]
    return counts.select(*keys, "n", "distinct", bits.alias("bits"))


def bit_costs(folded: DataFrame, keys: Sequence[str], code: str = "entropy") -> DataFrame:
    """Per key: counts and mean bits of residual, kinds and factors, ``alpha``, ``beta`` and ``total_bits``.

    The gate's parameters follow from what a replaced copy of length len saves and costs: s * (len - 1) residual symbols against s kinds and
    one factor, all in units of a residual symbol.
    """
    parts = {
        "residual": folded.select(*keys, F.explode(F.transform("residual", lambda c: c.cast("string"))).alias("x")),
        "kinds": folded.select(*keys, F.explode(F.transform("kinds", lambda k: F.least(k, F.lit(3)).cast("string"))).alias("x")),
        "factors": folded.select(*keys, F.explode("factors").alias("f")).select(*keys, F.concat_ws(",", "f.a", "f.len").alias("x")),
    }
    out = folded.select(*keys).distinct()
    for name, rows in parts.items():
        h = histogram_bits(rows, keys, "x", code).select(*keys, F.col("n").alias(f"n_{name}"), F.col("bits").alias(f"bit_{name}"))
        out = out.join(h, list(keys), "left").fillna(0, [f"n_{name}", f"bit_{name}"])
    return _with_gate(out)


def estimate_gate(folded: DataFrame, keys: Sequence[str] = ()) -> DataFrame:
    """Break-even ``alpha, beta`` per key from an ungated run."""
    if not keys:
        folded, keys = folded.withColumn("all", F.lit("all")), ["all"]
    return bit_costs(folded, keys).select(*keys, "alpha", "beta")


def type_counts(log: DataFrame, keys: Sequence[str] = ()) -> DataFrame:
    """Occurrences by kind over the steps of each key."""
    return log.groupBy(*keys).agg(*(F.sum(c).cast("long").alias(c) for c in ("n1", "n2", "n3", "n4")))


def step_stats(log: DataFrame, id_cols: Sequence[str]) -> DataFrame:
    """Per unit: steps, whether lengths ever grow, and the charges that the bounds speak of."""
    s = log.groupBy(*id_cols).agg(
        F.count("*").alias("steps"), F.array_sort(F.collect_list(F.struct("k", "len"))).alias("lens"), F.sum("d").cast("long").alias("sum_d"), F.sum("sort_work").alias("sort_work"),
        F.sum("edges").alias("edges"), F.sum("nodes_new").alias("nodes_new"), F.sum("bucket_ops").alias("bucket_ops"), F.sum("select_work").alias("select_work"), F.sum(F.col("q") * (F.col("len") - 1)).cast("long").alias("saved"),
        F.max(F.when((F.col("q") < 1) & F.col("accepted"), 1).otherwise(0)).cast("long").alias("idle_steps"), F.sum(F.col("q") * F.col("len")).cast("long").alias("taken"),
    )
    grow = F.exists(F.sequence(F.lit(1), F.greatest(F.size("lens") - 1, F.lit(1))), lambda k: F.get(F.col("lens"), k)["len"] > F.get(F.col("lens"), k - 1)["len"])
    return s.withColumn("grows", F.coalesce(grow, F.lit(False))).drop("lens")


def compare_selection(df: DataFrame, id_cols: Sequence[str], text_col: str = "text", pick: str = "ends_first") -> DataFrame:
    """For each step of a simple fold: copies of kind 3 beside those that left-greedy would take of the same string: ``k, greedy, simple``."""
    from repeatfold.kernels import reach
    from repeatfold.kernels.typing import end_bound, left_greedy
    from repeatfold.operators.units import map_units

    def work(codes, sa, lcp):
        for s in reach.steps_of(len(codes), sa, lcp, mode="simple", order=pick):
            starts = sorted(s.starts)
            greedy = len(left_greedy(starts, s.len, end_bound(starts, s.len)[1]))
            if greedy > 1:
                yield s.k, greedy, sum(k > 1 for _, k in s.picks)

    return map_units(df, id_cols, text_col, "k int, greedy int, simple int", work)


def lossless(source: DataFrame, decoded: DataFrame, id_cols: Sequence[str], text_col: str = "text") -> DataFrame:
    """``units, wrong``: decoded units that are not the source's."""
    both = source.select(*id_cols, F.col(text_col).alias("_a")).join(decoded.select(*id_cols, F.col(text_col).alias("_b")), list(id_cols), "full")
    return both.agg(F.count("*").alias("units"), F.sum((~F.col("_a").eqNullSafe(F.col("_b"))).cast("long")).alias("wrong"))


def refusals(log: DataFrame, id_cols: Sequence[str]) -> DataFrame:
    """Per unit: candidates refused by the gate and the symbols they would have saved."""
    lost = F.when(~F.col("accepted"), F.size("picks") * (F.col("len") - 1)).otherwise(0)
    return log.groupBy(*id_cols).agg(F.sum((~F.col("accepted")).cast("long")).alias("refused"), F.sum(lost).cast("long").alias("lost"))


def slope(points: Sequence[tuple[float, float]]) -> float:
    """Least-squares slope of log time on log n."""
    x, y = [math.log(p) for p, _ in points], [math.log(max(t, 1e-9)) for _, t in points]
    mx, my = sum(x) / len(x), sum(y) / len(y)
    return sum((a - mx) * (b - my) for a, b in zip(x, y, strict=True)) / sum((a - mx) ** 2 for a in x)


def growth(rows: DataFrame, keys: Sequence[str], n: str, value: str) -> DataFrame:
    """``keys, slope``: least-squares slope of log ``value`` on log ``n``."""
    x, y = F.log(F.col(n).cast("double")), F.log(F.greatest(F.col(value).cast("double"), F.lit(1e-9)))
    return rows.groupBy(*keys).agg(F.regr_slope(y, x).alias("slope"))


def kernel_growth(units: DataFrame, id_cols: Sequence[str], engine: str, text_col: str = "text", **options) -> DataFrame:
    """``ids, n, work, cells`` of each unit's fold: what the steps touched, and the most cells of working arrays held."""
    from repeatfold.operators.fold import runner
    from repeatfold.operators.units import map_units

    run = runner(engine, options)

    def work(codes, sa, lcp):
        f = run(codes, sa, lcp)
        yield len(codes), len(codes) + sum(len(s.starts) + s.edges + s.nodes_new + s.bucket_ops + s.select_work for s in f.steps), f.cells

    return map_units(units, id_cols, text_col, "n bigint, work bigint, cells bigint", work)


def method_bits(streams: DataFrame, keys: Sequence[str], code: str = "entropy") -> DataFrame:
    """``keys, bits``: all symbols of a method's output under one code for each of its streams (``keys, stream, x``), streams added up."""
    h = histogram_bits(streams, [*keys, "stream"], "x", code)
    return h.groupBy(*keys).agg(F.sum(F.col("n") * F.col("bits")).alias("bits"))


def _stream(df: DataFrame, keys: Sequence[str], name: str, symbols: Column) -> DataFrame:
    return df.select(*keys, F.lit(name).alias("stream"), F.explode(F.transform(symbols, lambda x: x.cast("string"))).alias("x"))


def fold_streams(folded: DataFrame, keys: Sequence[str]) -> DataFrame:
    """Residual, kinds, pointers and lengths of triples."""
    f = F.col("factors")
    parts = {"residual": F.col("residual"), "kinds": F.transform("kinds", lambda k: F.least(k, F.lit(3))), "pointers": f["a"], "lengths": f["len"]}
    return _union([_stream(folded, keys, name, symbols) for name, symbols in parts.items()])


def lz77_streams(factors: DataFrame, keys: Sequence[str]) -> DataFrame:
    """Whether a factor is a literal, literals, distances and lengths of factor rows."""
    flags = factors.select(*keys, F.lit("flags").alias("stream"), F.col("src").isNull().cast("string").alias("x"))
    literals = factors.where("src is null").select(*keys, F.lit("literals").alias("stream"), F.col("literal").cast("string").alias("x"))
    copies = factors.where("src is not null")
    return _union([flags, literals, *(copies.select(*keys, F.lit(n).alias("stream"), c.cast("string").alias("x")) for n, c in (("distances", F.col("pos") - F.col("src")), ("lengths", F.col("len"))))])


def grammar_streams(grammar: DataFrame, keys: Sequence[str]) -> DataFrame:
    """Start sequences and rule bodies, each body with its length."""
    bodies = F.map_values("rules")
    return _union([_stream(grammar, keys, "symbols", F.concat("start", F.flatten(bodies))), _stream(grammar, keys, "lengths", F.transform(bodies, F.size))])


def _union(frames: Sequence[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.union(f)
    return out


#: Each method's engine and options for ``stream_counts``.
STREAMS = {
    "fold": ("reach", {}), "simple": ("reach", {"mode": "simple"}), "gated": ("gated", {"refused": False}), "longest": ("longest", {}), "pairs": ("pairs", {}), "lz77": ("lz77", {}), "chars": ("chars", {}),
}


def stream_counts(df: DataFrame, keys: Sequence[str], method: str, text_col: str = "text", joined: bool = False) -> DataFrame:
    """``keys, stream, x, n``: symbols of the streams of a method's output over all units of a key; see ``method_counts``."""
    return method_counts(df, keys, [method], text_col, joined).drop("method")


def method_counts(df: DataFrame, keys: Sequence[str], methods: Sequence[str], text_col: str = "text", joined: bool = False, limit: int = 0) -> DataFrame:
    """``keys, method, stream, x, n``: the same of several methods, which share one order of each unit's suffixes. A task's own histograms leave
    the JVM, not the outputs.

    Streams are those of ``fold_streams``, ``grammar_streams`` and ``lz77_streams`` (chars: the text itself); with ``joined`` pointers and lengths
    are one stream of pairs, ``factors``.
    """
    from repeatfold.kernels import jvm

    rows = jvm.histograms(df, keys, text_col, {m: (STREAMS[m][0], STREAMS[m][1] | {"joined": joined}) for m in methods}, limit)
    return rows.groupBy(*keys, "method", "stream", "x").agg(F.sum("k").alias("n"))


@F.pandas_udf(DoubleType())
def huffman_of_runs(runs: pd.Series) -> pd.Series:
    """``huffman_mean`` of histograms given as (count, number of symbols that have it)."""

    def one(pairs) -> float:
        heap = [(float(p["c"]), int(p["m"])) for p in pairs]
        total, bits = sum(c * m for c, m in heap), 0.0
        if len(heap) == 1 and heap[0][1] == 1:
            return 1.0
        heapq.heapify(heap)
        while heap:
            c, m = heapq.heappop(heap)
            if m > 1:
                bits += 2 * c * (m // 2)
                heapq.heappush(heap, (2 * c, m // 2))
                if m % 2:
                    heapq.heappush(heap, (c, 1))
            elif heap:
                d, k = heapq.heappop(heap)
                bits += c + d
                if k > 1:
                    heapq.heappush(heap, (d, k - 1))
                heapq.heappush(heap, (c + d, 1))
        return bits / total if total else 0.0

    return runs.map(one)


def stream_bits(counts: DataFrame, keys: Sequence[str], code: str = "entropy") -> DataFrame:
    """``keys, stream, n, bits``: symbols and mean bits under the code. Counts are gathered by their value, so no row grows with the symbols."""
    runs = counts.groupBy(*keys, "stream", F.col("n").alias("c")).agg(F.count("*").alias("m"))
    weight = F.col("c") * F.col("m")
    out = runs.groupBy(*keys, "stream").agg(
        F.sum(weight).alias("n"), F.sum("m").alias("distinct"), F.sum(weight * F.log2("c")).alias("_s"), *([F.collect_list(F.struct("c", "m")).alias("_runs")] if code == "huffman" else []),
    )
    bits = {
        "entropy": lambda: F.log2("n") - F.col("_s") / F.col("n"), "huffman": lambda: huffman_of_runs("_runs"), "fixed": lambda: F.ceil(F.log2(F.greatest(F.col("distinct"), F.lit(2)))).cast("double"),
    }[code]()
    return out.select(*keys, "stream", "n", bits.alias("bits"))


def stream_costs(counts: DataFrame, all_keys: DataFrame, keys: Sequence[str], code: str = "entropy") -> DataFrame:
    """``bit_costs`` from joined ``stream_counts`` of the fold; ``all_keys`` has each key once."""
    bits = stream_bits(counts, keys, code)
    out = all_keys
    for name in ("residual", "kinds", "factors"):
        h = bits.where(F.col("stream") == name).select(*keys, F.col("n").alias(f"n_{name}"), F.col("bits").alias(f"bit_{name}"))
        out = out.join(h, list(keys), "left").fillna(0, [f"n_{name}", f"bit_{name}"])
    return _with_gate(out)


def _with_gate(out: DataFrame) -> DataFrame:
    per = F.greatest(F.col("bit_residual"), F.lit(1e-12))
    total = sum((F.col(f"n_{p}") * F.col(f"bit_{p}") for p in ("residual", "kinds", "factors")), F.lit(0.0))
    return out.withColumns({"alpha": F.col("bit_factors") / per, "beta": 1 + F.col("bit_kinds") / per, "total_bits": total})
