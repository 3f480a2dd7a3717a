"""Set-based forms: positions, suffix order, common prefixes, groups and typing as relations, without Python on the executors."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from repeatfold.functions.columns import end_bound, left_greedy, typed
from repeatfold.plans.lineage import cut


def positions(df: DataFrame, ids: Sequence[str], text_col: str = "text") -> DataFrame:
    """A row for each place of each unit: ``ids, text, pos``."""
    return df.where(F.length(text_col) > 0).select(*ids, F.col(text_col).alias("text"), F.explode(F.sequence(F.lit(1), F.length(text_col))).alias("pos"))


def substrings(df: DataFrame, ids: Sequence[str], length: int, text_col: str = "text") -> DataFrame:
    """Classes of equal substrings of a length: ``ids, sub, starts`` with two starts at least. A class is bounded by its unit."""
    p = positions(df.where(F.length(text_col) >= length), ids, text_col).where(F.col("pos") <= F.length("text") - length + 1)
    subs = p.select(*ids, F.substring("text", F.col("pos"), F.lit(length)).alias("sub"), F.col("pos").cast("long").alias("pos"))
    return subs.groupBy(*ids, "sub").agg(F.array_sort(F.collect_list("pos")).alias("starts")).where(F.size("starts") > 1)


def suffix_order(df: DataFrame, ids: Sequence[str], text_col: str = "text") -> DataFrame:
    """``ids, rank, pos``: for short units, by the suffixes themselves."""
    p = positions(df, ids, text_col)
    w = Window.partitionBy(*ids).orderBy(F.substring("text", F.col("pos"), F.length("text")))
    return p.select(*ids, F.row_number().over(w).cast("long").alias("rank"), F.col("pos").cast("long").alias("pos"))


def doubling_order(df: DataFrame, ids: Sequence[str], max_common: int, text_col: str = "text") -> DataFrame:
    """``ids, rank, pos`` by prefix doubling: one window a round, enough rounds for common prefixes up to ``max_common``."""
    p = positions(df, ids, text_col).select(*ids, F.col("pos").cast("long").alias("pos"), F.substring("text", F.col("pos"), F.lit(1)).alias("c"))
    r = p.select(*ids, "pos", F.dense_rank().over(Window.partitionBy(*ids).orderBy("c")).alias("r"))
    width = 1
    while width <= max_common:
        ahead = F.coalesce(F.lead("r", width).over(Window.partitionBy(*ids).orderBy("pos")), F.lit(0))
        r = r.withColumn("r2", ahead).select(*ids, "pos", F.dense_rank().over(Window.partitionBy(*ids).orderBy("r", "r2")).alias("r"))
        width *= 2
    return r.select(*ids, F.col("r").cast("long").alias("rank"), "pos")


def common_prefixes(order: DataFrame, df: DataFrame, ids: Sequence[str], text_col: str = "text") -> DataFrame:
    """``ids, rank, pos, lcp`` beside the unit's previous rank; the first rank has 0."""
    w = Window.partitionBy(*ids).orderBy("rank")
    rows = order.withColumn("before", F.lag("pos").over(w)).join(df.select(*ids, F.col(text_col).alias("text")), list(ids))
    a, b = F.substring("text", F.col("pos"), F.length("text")), F.substring("text", F.col("before"), F.length("text"))
    n = F.least(F.length(a), F.length(b))
    # equality of prefixes is monotone in the length: halve, 17 rounds reach texts of 131,071 symbols
    lcp = F.aggregate(F.array(*[F.lit(1 << k) for k in range(16, -1, -1)]), F.lit(0), lambda x, s: F.when((x + s <= n) & (F.substring(a, F.lit(1), x + s) == F.substring(b, F.lit(1), x + s)), x + s).otherwise(x))
    return rows.select(*ids, "rank", "pos", F.when(F.col("before").isNull(), 0).otherwise(lcp).cast("int").alias("lcp"))


def prefix_groups(lcp: DataFrame, ids: Sequence[str], p: int) -> DataFrame:
    """``ids, p, lo, hi``: runs of ranks whose neighbours share p symbols at least, with one that shares no more."""
    w = Window.partitionBy(*ids).orderBy("rank")
    run = lcp.withColumn("run", F.sum((F.col("lcp") < p).cast("int")).over(w.rowsBetween(Window.unboundedPreceding, 0)))
    g = run.groupBy(*ids, "run").agg(F.min("rank").alias("lo"), F.max("rank").alias("hi"), F.min(F.when(F.col("lcp") >= p, F.col("lcp"))).alias("least"))
    return g.where((F.col("hi") > F.col("lo")) & (F.col("least") == p)).select(*ids, F.lit(p).alias("p"), "lo", "hi")


def longest_classes(df: DataFrame, ids: Sequence[str], longest: DataFrame, text_col: str = "text") -> DataFrame:
    """``ids, len, starts``: of each unit's longest repeats the one that stands first. ``longest``: ids, len, first."""
    first = longest.groupBy(*ids).agg(F.min(F.struct(F.col("first"), F.col("len"))).alias("x")).select(*ids, "x.first", "x.len")
    p = positions(df, ids, text_col).join(first, list(ids))
    hit = p.where((F.col("pos") <= F.length("text") - F.col("len") + 1) & (F.substring("text", F.col("pos"), F.col("len")) == F.substring("text", F.col("first"), F.col("len"))))
    return hit.groupBy(*ids, "len").agg(F.array_sort(F.collect_list(F.col("pos").cast("long"))).alias("starts"))


def typed_rows(classes: DataFrame, ids: Sequence[str]) -> DataFrame:
    """``ids, pos, type`` of each class's occurrences."""
    return classes.select(*ids, F.explode(typed(F.col("starts"), F.col("len"))).alias("x")).select(*ids, "x.pos", F.col("x.type").cast("int").alias("type"))


def greedy_rows(classes: DataFrame, ids: Sequence[str]) -> DataFrame:
    rows = classes.select(*ids, F.col("len").alias("_len"), left_greedy(F.col("starts"), F.col("len")).alias("_chosen"))
    return rows.select(*ids, F.col("_len").cast("int").alias("len"), F.explode("_chosen").alias("pos"))


def bound_rows(classes: DataFrame, ids: Sequence[str]) -> DataFrame:
    return classes.select(*ids, F.array_min("starts").alias("first"), end_bound(F.col("starts"), F.col("len")).cast("long").alias("e"))


def longest_by_groups(df: DataFrame, ids: Sequence[str], text_col: str = "text") -> DataFrame:
    """``ids, len, first, n_occ`` of each unit's longest repeats: lengths are halved for all units at once, each by groups of equal substrings.

    Sixteen rounds reach texts of 65,535 symbols; a longer one raises.
    """
    p = positions(df, ids, text_col)
    bound = p.select(F.max(F.length("text"))).first()[0] or 0
    if bound >= 1 << 16:
        raise ValueError("texts of 65,536 symbols or more belong to the other engines")
    best = df.where(F.length(text_col) > 1).select(*ids).distinct().withColumn("len", F.lit(0))
    step = 1 << max(0, int(bound).bit_length() - 1)

    def classes(at: DataFrame) -> DataFrame:
        rows = p.join(at, list(ids)).where((F.col("len") > 0) & (F.col("pos") <= F.length("text") - F.col("len") + 1))
        subs = rows.groupBy(*ids, "len", F.substring("text", F.col("pos"), F.col("len")).alias("sub"))
        return subs.agg(F.min("pos").cast("long").alias("first"), F.count("*").alias("n_occ")).where("n_occ > 1")

    while step:
        hit = classes(best.withColumn("len", F.col("len") + step)).select(*ids, F.lit(step).alias("_more")).distinct()
        best = cut(best.join(hit, list(ids), "left").select(*ids, (F.col("len") + F.coalesce("_more", F.lit(0))).alias("len")))
        step //= 2
    return classes(best).select(*ids, F.col("len").cast("int").alias("len"), "first", "n_occ")


def maximal_groups(lcp: DataFrame, df: DataFrame, ids: Sequence[str], text_col: str = "text") -> DataFrame:
    """``ids, p, lo, hi``: the groups of every common prefix length at once whose suffixes have two different symbols before them (the text's start is one of its own).

    A neighbour pair of ranks with p common symbols belongs to the group between the nearest ranks around it that share less; for short units.
    """
    same = list(ids)
    pair = lcp.where("lcp > 0").select(*ids, F.col("rank").alias("r"), F.col("lcp").alias("p"))
    less = pair.join(lcp.select(*ids, F.col("rank").alias("s"), "lcp"), same).where("lcp < p")
    ends = less.groupBy(*ids, "r", "p").agg(F.max(F.when(F.col("s") < F.col("r"), F.col("s"))).alias("lo"), F.min(F.when(F.col("s") > F.col("r"), F.col("s"))).alias("above"))
    last = lcp.groupBy(*ids).agg(F.max("rank").alias("last"))
    groups = ends.join(last, same).select(*ids, "p", "lo", F.coalesce(F.col("above") - 1, "last").alias("hi")).distinct()
    before = lcp.join(df.select(*ids, F.col(text_col).alias("text")), same).select(*ids, "rank", F.when(F.col("pos") == 1, "").otherwise(F.substring("text", F.col("pos") - 1, F.lit(1))).alias("a"))
    diverse = groups.join(before, same).where("rank between lo and hi").groupBy(*ids, "p", "lo", "hi").agg(F.count_distinct("a").alias("n")).where("n > 1")
    return diverse.drop("n")


def chain(jumps: DataFrame, ids: Sequence[str], steps: int) -> DataFrame:
    """``ids, pos``: positions that following ``pos -> next`` from 1 meets, by doubling the jumps ``steps`` times."""
    same = list(ids)
    met = jumps.where("pos = 1").select(*ids, "pos")
    far = jumps.select(*ids, "pos", "next")
    for _ in range(steps):
        ahead = met.join(far, [*same, "pos"]).select(*ids, F.col("next").alias("pos"))
        met = cut(met.union(ahead).distinct())
        again = far.select(*ids, F.col("pos").alias("next"), F.col("next").alias("then"))
        far = cut(far.join(again, [*same, "next"]).select(*ids, "pos", F.col("then").alias("next")))
    return met


def lz77_rows(df: DataFrame, ids: Sequence[str], text_col: str = "text", self_ref: bool = True) -> DataFrame:
    """``ids, idx, pos, len`` of the factors of short units: longest earlier match of every position, then the chain of factors."""
    p = positions(df, ids, text_col).select(*ids, "text", F.col("pos").cast("long").alias("pos"))
    q = p.select(*ids, F.col("pos").alias("q"))
    pairs = p.join(q, list(ids)).where((F.col("q") < F.col("pos")) & (F.substring("text", F.col("q"), F.lit(1)) == F.substring("text", F.col("pos"), F.lit(1))))
    room = F.length("text") - F.col("pos") + 1
    if not self_ref:
        room = F.least(room, F.col("pos") - F.col("q"))
    here = lambda start, n: F.substring(F.col("text"), start, n)
    match = F.aggregate(F.array(*[F.lit(1 << k) for k in range(16, -1, -1)]), F.lit(0), lambda x, s: F.when((x + s <= room) & (here(F.col("q"), x + s) == here(F.col("pos"), x + s)), x + s).otherwise(x))
    longest = pairs.select(*ids, "pos", match.alias("m")).groupBy(*ids, "pos").agg(F.max("m").alias("m"))
    jumps = cut(p.join(longest, [*ids, "pos"], "left").select(*ids, "pos", F.greatest(F.coalesce("m", F.lit(1)), F.lit(1)).cast("long").alias("len")).withColumn("next", F.col("pos") + F.col("len")))
    most = jumps.agg(F.max("pos")).first()[0] or 1
    met = chain(jumps, ids, int(most).bit_length()).join(jumps, [*ids, "pos"])
    return met.select(*ids, F.row_number().over(Window.partitionBy(*ids).orderBy("pos")).cast("long").alias("idx"), "pos", "len")


def first_steps(df: DataFrame, ids: Sequence[str], steps: int, text_col: str = "text") -> DataFrame:
    """``ids, step, len, first, picks``: the first steps of a fold of short units as relations, each over what the ones before left."""
    state = positions(df, ids, text_col).select(*ids, "text", F.col("pos").cast("long").alias("pos"), (F.length("text") - F.col("pos") + 1).cast("long").alias("reach"))
    out = None
    for k in range(1, steps + 1):
        subs = state.where("reach > 1").select(*ids, "text", "pos", F.explode(F.sequence(F.lit(2).cast("long"), F.col("reach"))).alias("len"))
        groups = subs.groupBy(*ids, "len", F.substring("text", F.col("pos").cast("int"), F.col("len").cast("int")).alias("sub")).agg(F.array_sort(F.collect_list("pos")).alias("starts")).where(F.size("starts") > 1)
        top = groups.groupBy(*ids).agg(F.min(F.struct((-F.col("len")).alias("l"), F.get("starts", F.lit(0)).alias("first"), "starts")).alias("x"))
        chosen = top.select(*ids, (-F.col("x.l")).alias("len"), "x.first", "x.starts")
        picks = F.transform(F.filter(typed(F.col("starts"), F.col("len")), lambda x: x["type"].between(1, 3)), lambda x: x["pos"])
        step = cut(chosen.select(*ids, F.lit(k).cast("long").alias("step"), F.col("len").cast("long").alias("len"), F.col("first").cast("long").alias("first"), picks.alias("picks")))
        out = step if out is None else out.union(step)
        gone = F.exists("picks", lambda a: F.col("pos").between(a, a + F.col("len") - 1))
        ahead = F.array_min(F.filter("picks", lambda a: a > F.col("pos")))
        left = state.join(step.select(*ids, "len", "picks"), list(ids), "left").where(~F.coalesce(gone, F.lit(False)))
        state = cut(left.select(*ids, "text", "pos", F.least("reach", F.coalesce(ahead - F.col("pos"), "reach")).alias("reach")))
    return out
