"""Exact top-k search by inner product with multi-resolution segment statistics.

Each vector has the mean and the deviation of its segments, from one segment over the whole vector to finer ones. Segment by segment,
length * (mean * mean' + deviation * deviation') is an upper bound of the inner product (a lower bound of the distance between vectors of
given norms). Vectors are packed into small blocks, which carry the ranges of these statistics. Query blocks and candidate blocks are dealt to
tasks as a grid; a task holds its queries and streams its candidates: whole blocks are dropped by their ranges, then vectors by bounds taken
coarse to fine, each level only for what the one before left above the query's k-th best score so far, and exact integer scores are taken only of
the survivors, so nothing that belongs to the answer is lost. A last window merges the tasks' best of each query.

Vectors that are null, empty or hold null or non-finite components take no part, nor do rows with a null id; only vectors of equal length are
compared. Repeated candidate rows each take a place; a query id that is repeated is answered once, for its least vector. Components are scaled to
integers; where a sum of their products could leave 64 bits the search raises. An empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Queries that a task holds.
QUERIES = 16_384
#: Bytes of a packed block's vectors, so that a batch of rows stays small whatever the dimension.
BLOCK_BYTES = 16_384
#: Query rows scored together against a batch, and candidates a step.
TILE_Q, TILE_C = 256, 1024


def valid_rows(ids: pa.Array, vectors: pa.Array, scale: float = 1024.0) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """dimension -> (ids, integer vectors) of the rows that take part."""
    out = {}
    vectors = vectors.cast(pa.list_(pa.float64()))
    sizes = pc.fill_null(pc.list_value_length(vectors), 0).to_numpy(zero_copy_only=False)
    for dim in np.unique(sizes[sizes > 0]).tolist():
        rows = np.flatnonzero(sizes == dim)
        part = vectors.take(pa.array(rows))
        x = pc.fill_null(part.flatten(), float("nan")).to_numpy(zero_copy_only=False).reshape(-1, dim)
        good = np.isfinite(x).all(1)
        key = ids.take(pa.array(rows[good]))
        named = pc.is_valid(key).to_numpy(zero_copy_only=False)
        scaled = np.floor(scale * x[good][named])
        most = float(np.abs(scaled).max(initial=0.0))
        if most >= 2**31 or dim * most * most >= 2**63:
            raise OverflowError(f"a component of {most / scale:g}: inner products of {dim} such ones may not fit 64 bits")
        out[dim] = (key.filter(pa.array(named)).to_numpy().astype(np.int64), scaled.astype(np.int64))
    return out


def levels(dim: int) -> list[np.ndarray]:
    """Starts of the segments of each level: 1, 4, 16 … of them, while a segment has two components at least."""
    out, n = [], 1
    while n == 1 or dim // n >= 2:
        out.append(np.unique(np.arange(n) * dim // n))
        n *= 4
    return out


def statistics(x: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Rows of sqrt(length) * (means, deviations), whose inner products are the bounds."""
    length = np.diff(np.append(starts, x.shape[1])).astype(float)
    mean = np.add.reduceat(x, starts, axis=1) / length
    square = np.add.reduceat(x * x, starts, axis=1) / length
    return np.concatenate([mean * np.sqrt(length), np.sqrt(np.maximum(square - mean * mean, 0)) * np.sqrt(length)], 1)


def ranges(stats: np.ndarray) -> np.ndarray:
    """What bounds a whole block at one level: least and greatest means, greatest deviations."""
    half = stats.shape[1] // 2
    return np.concatenate([stats[:, :half].min(0), stats[:, :half].max(0), stats[:, half:].max(0)])


def block_bounds(queries: np.ndarray, blocks: np.ndarray) -> np.ndarray:
    """Upper bounds of the inner products of each query (rows of ``statistics``) with anything in each block (rows of ``ranges``)."""
    half = queries.shape[1] // 2
    mean, deviation = queries[:, :half], queries[:, half:]
    low, high, most = blocks[:, :half], blocks[:, half : 2 * half], blocks[:, 2 * half :]
    return np.maximum(mean, 0) @ high.T + np.minimum(mean, 0) @ low.T + deviation @ most.T


def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Blocks ``dim, ids, x, ranges`` of (id, vector) rows; rows of a batch that lie close come into one block."""
    for batch in batches:
        for dim, (ids, x) in valid_rows(batch.column(0), batch.column(1)).items():
            cuts = levels(dim)
            stats = [statistics(x.astype(float), c) for c in cuts]
            coarse = stats[min(1, len(stats) - 1)]
            order = np.lexsort([*(coarse[:, : coarse.shape[1] // 2] >= 0).T, ids])
            step = max(1, BLOCK_BYTES // (4 * dim))
            rows: list[list[bytes]] = [[], [], []]
            for a in range(0, len(order), step):
                at = order[a : a + step]
                for o, y in zip(rows, (ids[at].astype("<i8"), x[at].astype("<i4"), np.concatenate([ranges(s[at]) for s in stats])), strict=True):
                    o.append(y.tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(rows[0]), dim, np.int32)), *(pa.array(o, pa.binary()) for o in rows)], ["dim", "ids", "x", "ranges"])


class Searcher:
    """Best k of a stream of candidates for each of a block of queries."""

    def __init__(self, qid: np.ndarray, q: np.ndarray, k: int) -> None:
        self.qid, self.q, self.k = qid, q, k
        self.cuts = levels(q.shape[1])
        self.stats = [statistics(q.astype(float), c) for c in self.cuts]
        self.largest = int(np.abs(q).max(initial=0))
        self.best = np.full((len(q), k), -(2**62))
        self.who = np.full((len(q), k), np.iinfo(np.int64).max)
        self.seen = self.left = self.exact = self.blocks = self.blocks_left = 0

    def worth(self, bounds: np.ndarray) -> np.ndarray:
        """Which blocks, given by the ranges of all levels, may hold a better candidate for any query."""
        floor = self.best[:, -1].astype(float)
        keep, at = np.ones(len(bounds), bool), 0
        for starts, s in zip(self.cuts, self.stats, strict=True):
            width = 3 * len(starts)
            left = np.flatnonzero(keep)
            most = block_bounds(s, bounds[left, at : at + width])
            slack = 1e-9 * np.abs(s).sum(1)[:, None] * np.abs(bounds[left, at : at + width]).sum(1)[None, :] + 1
            keep[left] = (most + slack >= floor[:, None]).any(0)
            at += width
        self.blocks += len(bounds)
        self.blocks_left += int(keep.sum())
        return keep

    def add(self, cid: np.ndarray, c: np.ndarray) -> None:
        for a in range(0, len(c), TILE_C):
            ids, x = cid[a : a + TILE_C], c[a : a + TILE_C]
            f = x.astype(float)
            stats = [statistics(f, s) for s in self.cuts]
            for b in range(0, len(self.q), TILE_Q):
                self._tile(slice(b, b + TILE_Q), ids, x, f, stats)

    def _products(self, rows: slice, x: np.ndarray, f: np.ndarray) -> np.ndarray:
        """Exact inner products: in floating point where every sum stays below 2**53."""
        if x.shape[1] * self.largest * int(np.abs(x).max(initial=0)) < 2**53:
            return (self.q[rows].astype(float) @ f.T).astype(np.int64)
        return self.q[rows] @ x.T

    def _tile(self, rows: slice, ids: np.ndarray, x: np.ndarray, f: np.ndarray, stats: list[np.ndarray]) -> None:
        floor = self.best[rows, -1].astype(float)
        slack = 1e-9 * (np.abs(self.stats[0][rows]).sum(1)[:, None] * np.abs(stats[0]).sum(1).max(initial=0.0)) + 1
        bound = self.stats[0][rows] @ stats[0].T + slack
        qi, ci = np.nonzero(bound >= floor[:, None])
        self.seen += bound.size
        for level in range(1, len(stats)):
            if not len(qi):
                break
            s, t = self.stats[level][rows], stats[level]
            if len(qi) * 8 > bound.size:  # most are left: all at once is cheaper than one by one
                some = (s @ t.T)[qi, ci]
            else:
                some = np.einsum("ij,ij->i", s[qi], t[ci])
            stay = some + slack[qi, 0] >= floor[qi]
            qi, ci = qi[stay], ci[stay]
        self.exact += len(qi)
        if not len(qi):
            return
        got = self._products(rows, x, f)[qi, ci] if len(qi) * 8 > bound.size else np.einsum("ij,ij->i", self.q[rows][qi], x[ci])
        # what does not reach the k-th best so far cannot change anything
        other = (self.qid[rows][qi] != ids[ci]) & (got >= self.best[rows, -1][qi])
        qi, ci, got = qi[other], ci[other], got[other]
        touched = np.unique(qi)
        at = qi + rows.start
        q = np.concatenate([at, np.repeat(touched + rows.start, self.k)])
        score = np.concatenate([got, self.best[touched + rows.start].ravel()])
        who = np.concatenate([ids[ci], self.who[touched + rows.start].ravel()])
        order = np.lexsort((who, -score, q))
        q, score, who = q[order], score[order], who[order]
        first = np.searchsorted(q, touched + rows.start)
        pick = first[:, None] + np.arange(self.k)[None, :]
        self.best[touched + rows.start], self.who[touched + rows.start] = score[pick], who[pick]

    def rows(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        q, r = np.nonzero(self.who < np.iinfo(np.int64).max)
        return self.qid[q], self.who[q, r], self.best[q, r]


class Task:
    """One cell of the grid: queries first, then candidate blocks, a step's worth at a time."""

    def __init__(self, k: int) -> None:
        self.k = k
        self.queries: dict[int, list[tuple[np.ndarray, np.ndarray]]] = {}
        self.searchers: dict[int, Searcher] = {}
        self.waiting: dict[int, list[tuple[np.ndarray, np.ndarray, np.ndarray]]] = {}

    def row(self, kind: int, dim: int, ids: np.ndarray, x: np.ndarray, bounds: np.ndarray) -> None:
        if kind == 0:
            self.queries.setdefault(dim, []).append((ids, x))
            return
        if dim not in self.queries:
            return
        if dim not in self.searchers:
            self.searchers[dim] = Searcher(*(np.concatenate(o) for o in zip(*self.queries[dim], strict=True)), self.k)
        todo = self.waiting.setdefault(dim, [])
        todo.append((ids, x, bounds))
        if sum(len(w[0]) for w in todo) >= TILE_C:
            self.flush(dim)

    def flush(self, dim: int) -> None:
        todo, self.waiting[dim] = self.waiting.get(dim, []), []
        if not todo:
            return
        keep = self.searchers[dim].worth(np.stack([w[2] for w in todo]))
        left = [w for w, good in zip(todo, keep, strict=True) if good]
        if left:
            self.searchers[dim].add(np.concatenate([w[0] for w in left]), np.concatenate([w[1] for w in left]))

    def results(self) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        for dim, searcher in self.searchers.items():
            self.flush(dim)
            yield searcher.rows()


def search(vectors: DataFrame, queries: DataFrame, k: int = 10, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """``(query_id, rank, vec_id, score)``: for each row of ``queries`` its k best among all of ``vectors`` but those of its own id.

    The grid has as many query parts as hold ``QUERIES`` each, and candidate parts for all the session's shuffle partitions: queries travel to every
    candidate part, candidates to every query part, and nothing of either comes to the driver but the number of queries.
    """
    packed = "dim int, ids binary, x binary, ranges binary"
    todo = queries.select(F.col(id_col).cast("long").alias("id"), F.col(vector_col).alias("v"))
    usable = F.coalesce((F.size("v") > 0) & ~F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))), F.lit(False))
    todo = todo.where(F.col("id").isNotNull() & usable).groupBy("id").agg(F.min("v").alias("v"))
    total = todo.count()
    q_parts = max(1, -(-total // QUERIES))
    c_parts = max(1, -(-int(vectors.sparkSession.conf.get("spark.sql.shuffle.partitions")) // q_parts))
    deal = lambda df, parts: df.withColumn("at", F.pmod(F.xxhash64("ids", "dim"), F.lit(parts)).cast("int"))
    every = lambda parts: F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))
    q = deal(todo.mapInArrow(pack, packed), q_parts).select("*", F.lit(0).alias("kind"), every(c_parts).alias("other"))
    c = deal(vectors.select(F.col(id_col).cast("long"), F.col(vector_col)).mapInArrow(pack, packed), c_parts).select("*", F.lit(1).alias("kind"), every(q_parts).alias("other"))
    columns = ["kind", "dim", "ids", "x", "ranges"]
    grid = q.select((F.col("at") * c_parts + F.col("other")).alias("task"), *columns).union(c.select((F.col("other") * c_parts + F.col("at")).alias("task"), *columns))
    grid = grid.repartitionById(q_parts * c_parts, F.col("task")).sortWithinPartitions("kind")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task = Task(k)
        for batch in batches:
            kind, dim = batch.column(1).to_pylist(), batch.column(2).to_pylist()
            for r in range(len(batch)):
                ids, x, bounds = (np.frombuffer(batch.column(col)[r].as_buffer(), t) for col, t in ((3, "<i8"), (4, "<i4"), (5, "<f8")))
                task.row(kind[r], dim[r], ids, x.reshape(-1, dim[r]).astype(np.int64), bounds)
        for rows in task.results():
            yield pa.RecordBatch.from_arrays([pa.array(o) for o in rows], ["query_id", "vec_id", "score"])

    out = grid.mapInArrow(run, "query_id long, vec_id long, score long")
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return out.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
