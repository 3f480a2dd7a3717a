"""Near-duplicate vectors by spherical-cap filters.

A code is a set of filter directions with product structure: after a fixed random rotation the space is cut into two halves, each half has
its own random unit codewords, and a filter is a pair of codewords, whose score is the sum of the halves' inner products. Each vector is
list-decoded to all filters of every code whose score exceeds the cap's threshold (its few best ones at least), from the sorted halves
without looking at most pairs. Vectors that meet in a filter are verified by their cosine in double precision. Several independent codes
stand in for a longer one; their number and the list length set the recall, the number of filters follows the number of vectors, so that
buckets keep their size as the data grow.

What travels to every filter is a node number and a sketch of ``SKETCH`` signs; only where two sketches are as close as those of a link may be
(``SIGMAS`` deviations of their distance allowed for) do the vectors follow, in the table's own precision, and their lists are worked out
again. A pair that meets in several filters counts in the smallest one. Identical vectors are one class with a multiplicity before anything
is joined. A bucket of more than ``SPLIT`` vectors is dealt out as pairs of its blocks, so that no task holds more than two blocks.

Vectors that are null, empty, zero or hold null or non-finite components link with nothing; only vectors of equal length are compared.
Repeated rows are other vectors: they link. Rows with a null id take part and bridge others; a component is named by its smallest id, and only
one without any id has a null name. ``kept`` is true for the row of that name, and for rows without an id only in a component without a name.
An empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import FloatType

from repeatfold.llm.common import components, cut, spread_out

CODES = 5
LIST = 4
BEST = 2
#: Vectors for each filter of a code.
PER_FILTER = 12.0
SPLIT = 8_000
TILE = 1024
#: Signs of a sketch, and deviations that its distance may lie above a link's.
SKETCH = 192
SIGMAS = 5.0


@lru_cache(maxsize=8)
def code(dim: int, size: int, number: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, float]:
    """(rotation, codewords of either half, threshold) of one code; the same everywhere."""
    rng = np.random.default_rng([dim, size, number, 7])
    turn = np.linalg.qr(rng.normal(size=(dim, dim)))[0]
    half = dim // 2
    words = []
    for width in (half, dim - half):
        w = rng.normal(size=(size, width))
        words.append(w / np.linalg.norm(w, axis=1)[:, None])
    x = rng.normal(size=(400, dim))
    x = (x / np.linalg.norm(x, axis=1)[:, None]) @ turn
    a, b = x[:, :half] @ words[0].T, x[:, half:] @ words[1].T
    some = rng.integers(0, size, (2, 4_000))
    sums = (a[:, some[0]] + b[:, some[1]]).ravel() if size * size > 4_000 else (a[:, :, None] + b[:, None, :]).ravel()
    return turn, words[0], words[1], float(np.quantile(sums, max(0.0, 1 - LIST / (size * size))))


def decode(x: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """(vector, filter) pairs of unit vectors over all codes, sorted."""
    n, dim = x.shape
    who, what = [], []
    for number in range(CODES):
        turn, w1, w2, cap = code(dim, size, number)
        y = x @ turn
        s1, s2 = y[:, : dim // 2] @ w1.T, y[:, dim // 2 :] @ w2.T
        o1, o2 = np.argsort(-s1, axis=1), np.argsort(-s2, axis=1)
        s1, s2 = np.take_along_axis(s1, o1, 1), np.take_along_axis(s2, o2, 1)
        top = (s1[:, :BEST, None] + s2[:, None, :BEST]).reshape(n, -1)
        t = np.minimum(cap, np.sort(top, axis=1)[:, -min(BEST, top.shape[1])])
        for r in range(size):
            live = np.flatnonzero(s1[:, r] + s2[:, 0] >= t)
            if not len(live):
                break
            width = int((s2[live] >= (t[live] - s1[live, r])[:, None]).sum(1).max())
            i, j = np.nonzero(s2[live, :width] + s1[live, r][:, None] >= t[live][:, None])
            who.append(live[i])
            what.append(number * size * size + o1[live[i], r] * size + o2[live[i], j])
    a, b = np.concatenate(who), np.concatenate(what)
    order = np.lexsort((b, a))
    return a[order], b[order]


@lru_cache(maxsize=8)
def planes(dim: int) -> np.ndarray:
    return np.random.default_rng([dim, 11]).normal(size=(dim, SKETCH))


def sketch(x: np.ndarray) -> np.ndarray:
    """Sides of random planes that vectors lie on, as rows of 64-bit words."""
    return np.packbits(x @ planes(x.shape[1]) >= 0, axis=1).view("<i8")


def sketch_limit(least: float) -> int:
    """The greatest distance of two sketches at which their vectors may link."""
    p = np.arccos(np.clip(least, -1, 1)) / np.pi
    return int(np.ceil(SKETCH * p + SIGMAS * np.sqrt(SKETCH * p * (1 - p))))


def unit(x: np.ndarray) -> np.ndarray:
    """Rows of length 1, without overflow on the way; short ones get zeros."""
    x = x.astype(np.float64)
    x = x / np.abs(x).max(1)[:, None]
    x = x / np.linalg.norm(x, axis=1)[:, None]
    return x if x.shape[1] >= 8 else np.pad(x, ((0, 0), (0, 8 - x.shape[1])))


def by_length(vectors: pa.Array) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(length, rows, matrix) of each length among a column of vectors, in pieces of 512 rows at most."""
    lengths = vectors.value_lengths().to_numpy()
    for dim in np.unique(lengths).tolist():
        pick = np.flatnonzero(lengths == dim)
        for a in range(0, len(pick), 512):
            rows = pick[a : a + 512]
            yield dim, rows, vectors.take(pa.array(rows)).flatten().to_numpy().reshape(-1, dim)


def close_sketches(s: np.ndarray, side: np.ndarray | None, limit: int) -> np.ndarray:
    """Whether each sketch of a bucket has another one within ``limit``."""
    out = np.zeros(len(s), bool)
    for a in range(0, len(s), TILE):
        for b in range(a, len(s), TILE):
            x, y = s[a : a + TILE], s[b : b + TILE]
            far = np.zeros((len(x), len(y)), np.uint16)
            for w in range(s.shape[1]):
                far += np.bitwise_count(x[:, w, None] ^ y[None, :, w])
            near = far <= limit
            if a == b:
                np.fill_diagonal(near, False)
            if side is not None:
                near &= side[a : a + TILE, None] != side[None, b : b + TILE]
            out[a : a + TILE] |= near.any(1)
            out[b : b + TILE] |= near.any(0)
    return out


def link_labels(n: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """The smallest index reachable from each of ``n`` over the edges (i, j)."""
    label = np.arange(n)
    while len(i):
        low = np.minimum(label[i], label[j])
        before = label.copy()
        np.minimum.at(label, i, low)
        np.minimum.at(label, j, low)
        np.minimum.at(label, before[i], low)
        np.minimum.at(label, before[j], low)
        while True:
            up = label[label]
            if (up == label).all():
                break
            label = up
        if (label == before).all():
            break
        stay = label[i] != label[j]
        i, j = i[stay], j[stay]
    return label


class Bucket:
    """Links among the vectors of one filter: how many each has here, counted in pairs' smallest common filters, and a spanning forest."""

    def __init__(self, fid: int, x: np.ndarray, weight: np.ndarray, lists: np.ndarray, side: np.ndarray | None, least: float) -> None:
        n = len(x)
        self.count = np.zeros(n, np.int64)
        early = np.where((lists >= 0) & (lists < fid), lists, -1)
        ei, ej = [], []
        for a in range(0, n, TILE):
            for b in range(a, n, TILE):
                near = x[a : a + TILE] @ x[b : b + TILE].T >= least
                if a == b:
                    near = np.triu(near, 1)
                if side is not None:  # of two blocks only pairs across them, or of one block its own
                    near &= side[a : a + TILE, None] != side[None, b : b + TILE]
                if not near.any():
                    continue
                i, j = np.nonzero(near)
                own = self._owned(early[a : a + TILE], early[b : b + TILE], i, j)
                i, j = i[own] + a, j[own] + b
                self.count += np.bincount(i, weight[j], n).astype(np.int64) + np.bincount(j, weight[i], n).astype(np.int64)
                ei.append(i)
                ej.append(j)
        self.label = link_labels(n, np.concatenate(ei), np.concatenate(ej)) if ei else np.arange(n)

    @staticmethod
    def _owned(p: np.ndarray, q: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """True for pairs whose lists of smaller filters have nothing in common."""
        values = np.unique(np.concatenate([p.ravel(), q.ravel()]))
        values = values[values >= 0]
        if not len(values):
            return np.ones(len(i), bool)
        if len(i) * p.shape[1] * p.shape[1] > 2 * len(p) * len(q) * len(values):
            sets = []
            for m in (p, q):
                s = np.zeros((len(m), len(values) + 1), np.float32)
                np.put_along_axis(s, np.where(m >= 0, np.searchsorted(values, m), len(values)), 1, 1)
                sets.append(s[:, :-1])
            return (sets[0] @ sets[1].T)[i, j] == 0
        out = np.ones(len(i), bool)
        for a in range(0, len(i), 4096):
            u, v = p[i[a : a + 4096]], q[j[a : a + 4096]]
            out[a : a + 4096] = ~((u[:, :, None] == v[:, None, :]) & (u[:, :, None] >= 0)).any((1, 2))
        return out


def _usable(v: Column) -> Column:
    bad = F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return v.isNotNull() & (F.size(v) > 0) & ~bad & F.exists(v, lambda x: x != 0)


def _in_blocks(rows: DataFrame, keys: list[str]) -> DataFrame:
    """``rows`` with ``task, block``: buckets of over ``SPLIT`` rows are dealt out as pairs of blocks."""
    big = rows.groupBy(*keys).count().where(F.col("count") > SPLIT)
    big = cut(big.select(*keys, F.ceil(F.col("count") / (SPLIT // 2)).cast("int").alias("blocks")))
    if big.isEmpty():
        return rows.select("*", F.lit(0).alias("task"), F.lit(0).alias("block"))
    some = rows.join(big, keys, "left").withColumn("blocks", F.coalesce("blocks", F.lit(1)))
    some = some.withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    pair = F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda c: F.least(F.col("block"), c) * F.col("blocks") + F.greatest(F.col("block"), c))
    return some.withColumn("task", F.explode(pair)).select(*rows.columns, "task", "block")


def _buckets(batches: Iterator[pa.RecordBatch]) -> tuple[pa.Table | None, list[np.ndarray]]:
    """A partition's rows and, for each (dim, filter, task) with two at least, their numbers."""
    some = [b for b in batches if len(b)]
    if not some:
        return None, []
    table = pa.Table.from_batches(some)
    keys = [table[c].to_numpy() for c in ("dim", "filter", "task")]
    order = np.lexsort((table["node"].to_numpy(), *keys[::-1]))
    cuts = np.flatnonzero(np.any([np.diff(k[order]) != 0 for k in keys], axis=0)) + 1
    return table, [r for r in np.split(order, cuts) if len(r) > 1]


def near_duplicates(vectors: DataFrame, least: float = 0.9, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """One row for each row of ``vectors``: ``vec_id, n_links, component_id, kept``."""
    v = F.col(vector_col)
    if not isinstance(vectors.schema[vector_col].dataType.elementType, FloatType):
        v = F.transform(v, lambda x: x.cast("double"))
    rows = vectors.select(F.col(id_col).cast("long").alias("vec_id"), v.alias("v")).withColumn("ok", F.coalesce(_usable(F.col("v")), F.lit(False)))
    rows = rows.withColumns({"h": F.when(F.col("ok"), F.xxhash64("v")), "g": F.when(F.col("ok"), F.xxhash64(F.lit(1), F.reverse("v")))})
    classes = rows.where("ok").groupBy("h", "g").agg(F.min("vec_id").alias("rep"), F.count("*").alias("n"), F.first("v").alias("v"))
    classes = cut(classes.withColumn("node", F.monotonically_increasing_id()))
    total = classes.count()
    if not total:
        return rows.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    size = int(np.clip(np.ceil(np.sqrt(total / PER_FILTER)), 12, 23_000))
    limit = sketch_limit(least)
    signs = [f"s{w}" for w in range(SKETCH // 64)]

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for dim, at, x in by_length(batch.column(1)):
                x = unit(x)
                who, what = decode(x, size)
                s = sketch(x)[who]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(who), dim, np.int32)), pa.array(what.astype(np.int32)), batch.column(0).take(pa.array(at[who])), *(pa.array(s[:, w]) for w in range(len(signs)))], ["dim", "filter", "node", *signs])

    def sift(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, buckets = _buckets(batches)
        if table is None:
            return
        s = np.stack([table[c].to_numpy() for c in signs], 1).view(np.uint64)  # bits of signed numbers are counted without the sign
        block = table["block"].to_numpy()
        keep = np.zeros(len(s), bool)
        for at in buckets:
            side = block[at]
            keep[at] = close_sketches(s[at], side if len(np.unique(side)) > 1 else None, limit)
        yield from table.select(["dim", "filter", "node"]).filter(pa.array(keep)).combine_chunks().to_batches()

    dealt = classes.select("node", "v").mapInArrow(deal, "dim int, filter int, node long, " + ", ".join(f"{c} long" for c in signs))
    met = cut(spread_out(_in_blocks(dealt, ["dim", "filter"]), "dim", "filter", "task").mapInArrow(sift, "dim int, filter int, node long").distinct())

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, buckets = _buckets(batches)
        if not buckets:
            return
        fids, nodes, ns, block = (table[c].to_numpy() for c in ("filter", "node", "n", "block"))
        # each vector once: its matrix row and its list of filters
        once, first, back = np.unique(nodes, return_index=True, return_inverse=True)
        x: list[np.ndarray | None] = [None] * len(once)
        lists: list[np.ndarray | None] = [None] * len(once)
        for _, at, m in by_length(table["v"].combine_chunks().take(pa.array(first))):
            m = unit(m)
            who, what = decode(m, size)
            ends = np.searchsorted(who, np.arange(len(m) + 1))
            for k, r in enumerate(at.tolist()):
                x[r], lists[r] = m[k], what[ends[k] : ends[k + 1]]
        out: list[list[np.ndarray]] = [[], [], []]
        for at in buckets:
            mine = [lists[r] for r in back[at].tolist()]
            wide = np.full((len(at), max(map(len, mine))), -1, np.int64)
            for k, r in enumerate(mine):
                wide[k, : len(r)] = r
            side = block[at]
            bucket = Bucket(int(fids[at[0]]), np.stack([x[r] for r in back[at].tolist()]), ns[at], wide, side if len(np.unique(side)) > 1 else None, least)
            linked = np.flatnonzero(bucket.count)
            for o, y in zip(out, (nodes[at][linked], bucket.count[linked], nodes[at][bucket.label[linked]]), strict=True):
                o.append(y)
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(o)) for o in out], ["node", "links", "root"])

    pairs = _in_blocks(met, ["dim", "filter"]).join(classes.select("node", "n", "v"), "node")
    found = cut(spread_out(pairs, "dim", "filter", "task").mapInArrow(verify, "node long, links long, root long"))
    links = found.groupBy("node").agg(F.sum("links").alias("links"))
    comp = components(found.select(F.col("node").alias("a"), F.col("root").alias("b")))
    named = cut(classes.select("h", "g", "node", "rep", "n").join(links, "node", "left").join(comp, "node", "left").withColumn("comp", F.coalesce("component", "node")))
    names = named.groupBy("comp").agg(F.min("rep").alias("component_id"))
    done = named.join(names, "comp").select("h", "g", (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links"), "component_id")
    out = rows.select("vec_id", "h", "g").join(done, ["h", "g"], "left")
    component = F.coalesce("component_id", "vec_id")
    return out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, component.isNull()).alias("kept"))
