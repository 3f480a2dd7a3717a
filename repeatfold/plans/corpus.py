"""Corpus mode: one fold over units of any size, as relations of positions.

No unit has to fit a worker: suffix ranks come from prefix doubling with distributed dense ranks, common prefixes from the ranks of every
level, and the fold goes through the lengths of longest repeats in rounds. A round replaces, at one length, every class whose leftmost live
copy comes first among the classes it touches (two copies closer than the length); leftmost copies only move to the right within a length,
so this gives what taking the classes one by one from the left gives. The driver sees lengths and counts only. The starts of one class
meet in one row for typing, so a class is bounded by a row; everything else is dealt by position or rank.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from repeatfold.functions.columns import typed
from repeatfold.plans.lineage import cut

#: Ranks or positions of one block of a running sum or a neighbourhood.
BLOCK = 1 << 20


def dense_ranks(df: DataFrame, keys: list[str], name: str) -> DataFrame:
    """``keys, name``: the place of each distinct key in their order, from 0. Range partitions count for themselves; their offsets are one row each."""
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = df.select(*keys).distinct().repartitionByRange(parts, *keys).sortWithinPartitions(*keys)
    rows = cut(rows.select(*keys, F.spark_partition_id().alias("_p"), F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1).alias("_k")))
    offset, total = {}, 0
    for p, n in sorted(tuple(r) for r in rows.groupBy("_p").count().collect()):
        offset[p] = total
        total += n
    if not offset:
        return rows.select(*keys, F.col("_k").alias(name))
    base = F.create_map(*[F.lit(x) for kv in offset.items() for x in kv])
    return rows.select(*keys, (F.try_element_at(base, F.col("_p")) + F.col("_k")).cast("long").alias(name))


def running(df: DataFrame, order: str, value: str, name: str) -> DataFrame:
    """``df`` with the running sum of ``value`` by ``order`` (numbers from 0): blocks sum for themselves, block totals are one row each."""
    rows = df.withColumn("_b", F.floor(F.col(order) / BLOCK))
    totals = rows.groupBy("_b").agg(F.sum(value).alias("_t"))
    before = totals.withColumn("_base", F.coalesce(F.sum("_t").over(Window.orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("_t")
    own = F.sum(value).over(Window.partitionBy("_b").orderBy(order).rowsBetween(Window.unboundedPreceding, 0))
    return rows.withColumn("_own", own).join(before, "_b").withColumn(name, F.col("_own") + F.col("_base")).drop("_b", "_own", "_base")


def suffix_ranks(positions: DataFrame, max_common: int | None = None) -> tuple[DataFrame, list[DataFrame]]:
    """``(unit, pos, rank)`` with distinct ranks, and the ranks by prefixes of 1, 2, 4 … symbols. ``positions``: unit, pos (from 1), code."""
    n = positions.count()
    first = dense_ranks(positions, ["unit", "code"], "rank")
    now = cut(positions.join(first, ["unit", "code"]).select("unit", "pos", "rank"))
    levels, width = [now], 1
    while now.select("rank").distinct().count() < n and (max_common is None or width <= max_common):
        ahead = now.select("unit", (F.col("pos") - width).alias("pos"), (F.col("rank") + 1).alias("next"))
        pair = cut(now.join(ahead, ["unit", "pos"], "left").select("unit", "pos", "rank", F.coalesce("next", F.lit(0)).alias("next")))
        fresh = dense_ranks(pair, ["rank", "next"], "fresh")
        now = cut(pair.join(fresh, ["rank", "next"]).select("unit", "pos", F.col("fresh").alias("rank")))
        levels.append(now)
        width *= 2
    return now, levels


def neighbour_prefixes(ranks: DataFrame, levels: list[DataFrame]) -> DataFrame:
    """``rank, lcp`` with the rank before, within a unit; 0 at a unit's first rank."""
    a = ranks.select(F.col("unit"), F.col("pos").alias("p"), "rank")
    b = ranks.select(F.col("unit"), F.col("pos").alias("q"), (F.col("rank") + 1).alias("rank"))
    rows = cut(a.join(b, ["unit", "rank"], "left").select("unit", "rank", "p", "q", F.lit(0).cast("long").alias("lcp")))
    for t in range(len(levels) - 1, -1, -1):
        x = levels[t].select("unit", F.col("pos").alias("pp"), F.col("rank").alias("x"))
        y = levels[t].select("unit", F.col("pos").alias("qq"), F.col("rank").alias("y"))
        step = rows.withColumns({"pp": F.col("p") + F.col("lcp"), "qq": F.col("q") + F.col("lcp")}).join(x, ["unit", "pp"], "left").join(y, ["unit", "qq"], "left")
        rows = cut(step.select("unit", "rank", "p", "q", (F.col("lcp") + F.when(F.col("x") == F.col("y"), 1 << t).otherwise(0)).alias("lcp")))
    return rows.select("rank", "lcp")


def _classes(state: DataFrame, lcp: DataFrame, length: int) -> DataFrame:
    """``run, unit, pos`` of live starts that share ``length`` symbols with another one."""
    runs = running(lcp.withColumn("_new", (F.col("lcp") < length).cast("long")), "rank", "_new", "run").select("rank", "run")
    live = state.where(F.col("reach") >= length).join(runs, "rank").select("run", "unit", "pos")
    return live.join(live.groupBy("run").count().where("count > 1").select("run"), "run")


def _first_in_sight(members: DataFrame, length: int) -> DataFrame:
    """Classes whose leftmost start is the least among the leftmost starts of all members closer than ``length``: ``run, unit, starts``."""
    first = members.groupBy("run", "unit").agg(F.min("pos").alias("first"), F.array_sort(F.collect_list("pos")).alias("starts"))
    rows = members.join(first.select("run", "first"), "run")
    # neighbourhoods by blocks with their rims, so that no unit has to be one window
    size = max(BLOCK, 4 * length)
    blocks = F.array_distinct(F.transform(F.array(F.col("pos") - length, F.col("pos"), F.col("pos") + length), lambda p: F.floor(p / size)))
    rim = rows.withColumn("home", F.floor(F.col("pos") / size)).withColumn("block", F.explode(blocks))
    near = F.min("first").over(Window.partitionBy("unit", "block").orderBy("pos").rangeBetween(-(length - 1), length - 1))
    seen = rim.withColumn("near", near).where("home = block").groupBy("run").agg(F.min("near").alias("near"))
    return first.join(seen, "run").where("near = first").select("run", "unit", "first", "starts")


def fold_steps(positions: DataFrame, min_len: int = 2) -> DataFrame:
    """Replaced copies of an exact fold: ``unit, len, first, pos, kind``; the order of steps is by length down, then ``first``."""
    ranks, levels = suffix_ranks(positions)
    lcp = cut(neighbour_prefixes(ranks, levels))
    ends = positions.groupBy("unit").agg(F.max("pos").alias("end"))
    state = cut(ranks.join(ends, "unit").select("unit", "pos", "rank", (F.col("end") - F.col("pos") + 1).alias("reach")))
    log = None
    limit = (lcp.agg(F.max("lcp")).first()[0] or 0) + 1
    while True:
        # the greatest length that still repeats; a prefix of a repeat repeats, so halving finds it. It is mostly the last one or little less:
        # steps down from there that double come first
        low, high, step = min_len - 1, limit, 1
        while high - low > 1:
            mid = max(high - step, (low + high) // 2) if step else (low + high) // 2
            if not _classes(state, lcp, mid).isEmpty():
                low, step = mid, 0
            else:
                high, step = mid, 2 * step
        if low < min_len:
            break
        length, limit = low, low + 1
        members = cut(_classes(state, lcp, length))
        picked = _first_in_sight(members, length).select("unit", "first", F.explode(F.filter(typed(F.col("starts"), F.lit(length)), lambda x: x["type"].between(1, 3))).alias("x"))
        picked = cut(picked.select("unit", F.lit(length).alias("len"), F.col("first").cast("long").alias("first"), "x.pos", F.col("x.type").cast("int").alias("kind")))
        log = picked if log is None else log.union(picked)
        cells = picked.select("unit", F.col("pos").alias("i"), F.explode(F.sequence(F.col("pos") - length + 1, F.col("pos") + length - 1)).alias("pos"))
        least = cells.groupBy("unit", "pos").agg(F.min(F.greatest(F.col("i") - F.col("pos"), F.lit(0))).alias("room"))
        state = cut(state.join(least, ["unit", "pos"], "left").select("unit", "pos", "rank", F.least("reach", F.coalesce("room", "reach")).alias("reach")))
    if log is None:
        return positions.sparkSession.createDataFrame([], "unit long, len int, first long, pos long, kind int")
    return log


def grouped_positions(df: DataFrame, key_cols: list[str], order_cols: list[str], text_col: str = "text") -> tuple[DataFrame, DataFrame]:
    """Positions ``unit, pos, code`` of the units of ``sources.grouped_units`` without gathering any of them, and ``unit`` beside its keys.

    ``order_cols`` must tell the rows of a key apart. Places come from distributed ranks and running sums; no row holds more than one text.
    """
    same = lambda a, b, cols: [a[c].eqNullSafe(b[c]) for c in cols]
    rows = df.where(F.col(text_col).isNotNull()).select(*key_cols, *order_cols, F.col(text_col).alias("_x"), (F.length(text_col) + 1).cast("long").alias("_n"))
    ranks = dense_ranks(rows, [*key_cols, *order_cols], "k")
    ranked = rows.join(ranks, same(rows, ranks, [*key_cols, *order_cols])).select(*(rows[c] for c in key_cols), "k", "_x", "_n")
    placed = cut(running(ranked, "k", "_n", "_end"))
    base = cut(placed.groupBy(*key_cols).agg(F.min("k").alias("unit"), F.min(F.col("_end") - F.col("_n")).alias("_start")))
    at = placed.join(base, same(placed, base, key_cols)).select("unit", (F.col("k") - F.col("unit")).alias("_i"), (F.col("_end") - F.col("_n") - F.col("_start")).alias("_from"), "_x")
    codes = F.when(F.col("_x") == "", F.array().cast("array<int>")).otherwise(F.transform(F.split("_x", ""), lambda c: F.ascii(c).cast("int")))
    ended = F.concat(codes, F.array((F.col("_i") + 0x110000).cast("int")))
    out = at.select("unit", "_from", F.posexplode(ended).alias("_p", "code")).select("unit", (F.col("_from") + F.col("_p") + 1).alias("pos"), "code")
    return out, base.select("unit", *key_cols)
