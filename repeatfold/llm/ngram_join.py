"""N-gram Jaccard self-join with signature trees: components of documents whose shingle sets are similar.

A document's set is its distinct 5-word shingles (A-Z lower-cased), the whole sequence with fewer words. Two sets x, y link when
100 * |x & y| >= least * |x | y|. The join is exact:

1. Equal sets are one class. Everything below is about classes.
2. Tokens (shingle hashes) have one order for all documents, frequent ones last; sets that link share a token of their prefixes, so each
   prefix token makes a group of classes. Groups with the same members are one group.
3. Groups of the very first tokens are joined with their sets at hand; this finds nearly all links of copies, as components.
4. A group of full prefixes whose members already are one component has nothing left to find. In every other one a signature tree, whose
   nodes hold OR-combined token bitmaps, size ranges and least bit counts, is traversed against itself; node pairs are dropped when the
   maximum possible overlap is too small or both sides are one component, and surviving pairs of classes are verified on their sets.

Frequent tokens come from counts over all documents in a table of fixed size; they only set the order, never the result. Postings are one for
each class and map task, however many copies it holds; those of very frequent tokens are dealt over ``SALT`` partitions. A group with more than
``SPLIT`` members is dealt out as pairs of its blocks.

Classes are told apart by 96 bits of their set and then have row numbers as names; a class's set is read again from one of its rows, found by
id and text hash.

Null and empty texts and texts without words: an empty set, linked with nothing, a component of its own. Repeated rows are copies. Rows with a
null id link and bridge like others; a component is named by its smallest id, and only one without any id has a null name. An empty table
gives no rows; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from repeatfold.llm.common import components, cut, fresh, row_key, spread_out
from repeatfold.llm.near_dup import link_labels
from repeatfold.llm.words import Slice, combine, mix, relax, window_hashes, word_slices

WIDTH = 5
SLOT_BITS = 20
#: Slots of frequent tokens that are sent to all tasks at most.
HOT_SLOTS = 1 << 16
FIRST = 4
#: Binary logarithm of the count, and one more, from which a token is never one of the first.
VERY_HOT = 13
#: Partitions over which the postings of one such token are dealt, and partitions of postings for each one of the session's shuffles.
SALT = 16
PARTS = 1
SPLIT = 4_000
LEAF, FAN = 64, 8


def shingle_sets(s: Slice, width: int = WIDTH) -> Iterator[tuple[int, np.ndarray]]:
    """(document, sorted distinct shingle hashes) of each document of a slice; empty without words."""
    words = s.hashes() if len(s.start) else np.zeros(0, np.uint64)
    n = np.diff(s.at)
    full = window_hashes(words, width)
    short = {w: window_hashes(words, w) + np.uint64(w) for w in range(1, width)} if ((n > 0) & (n < width)).any() else {}
    for d in range(s.n):
        a = s.at[d]
        if n[d] >= width:
            h = np.sort(full[a : a + n[d] - width + 1])
            yield d, h[np.concatenate([[True], h[1:] != h[:-1]])]
        elif n[d]:
            yield d, short[int(n[d])][a : a + 1]
        else:
            yield d, np.zeros(0, np.uint64)


def class_of(h: np.ndarray) -> tuple[int, int] | None:
    """96 bits that name a whole set, as two signed numbers; None for an empty one."""
    if not len(h):
        return None
    first, second = combine(h, np.zeros(1, np.int64)), combine(mix(h), np.zeros(1, np.int64))
    return int(first.view(np.int64)[0]) ^ len(h), int((second >> np.uint64(32)).astype(np.uint32).view(np.int32)[0])


def bitmap(h: np.ndarray) -> np.ndarray:
    """Token bits, 1024 at least and four or more for each token; a wider map folds to a narrower one by OR."""
    bits = max(10, int(4 * len(h) - 1).bit_length())
    out = np.zeros(1 << bits, bool)
    out[(h & np.uint64((1 << bits) - 1)).astype(np.int64)] = True
    return np.packbits(out, bitorder="little").view("<u8")


def fold(b: np.ndarray, words: int) -> np.ndarray:
    return np.bitwise_or.reduce(b.reshape(-1, words), axis=0)


def popcount(x: np.ndarray) -> np.ndarray:
    return np.bitwise_count(x).sum(-1, dtype=np.int64)


def links(overlap: np.ndarray, n: np.ndarray, m: np.ndarray, least: int) -> np.ndarray:
    return 100 * overlap >= least * (n + m - overlap)


class SignatureTree:
    """Members of a group by size; ``candidates()`` yields the pairs that bounds and known components leave."""

    def __init__(self, size: np.ndarray, maps: list[np.ndarray], comp: np.ndarray, side: np.ndarray | None, least: int) -> None:
        self.least, self.maps, self.sizes = least, maps, size.tolist()
        self.order = np.lexsort((comp, size))
        self.size, self.comp = size[self.order], comp[self.order]
        self.side = None if side is None else side[self.order]
        words = min(len(m) for m in maps)
        # the members' maps at one width, the smallest one's, or 65,536 bits if that is less
        self.words = min(words, 1024)
        self.bits = np.stack([fold(maps[i], self.words) for i in self.order])
        self.count = popcount(self.bits)
        self.levels = [self._summary(LEAF, self.bits, self.size, self.size, self.count, self.comp, self.comp)]
        while len(self.levels[-1][0]) > 1:
            self.levels.append(self._summary(FAN, *self.levels[-1]))

    @staticmethod
    def _summary(fan: int, bits, low, high, count, c_low, c_high):
        at = np.arange(0, len(bits), fan)
        return (np.bitwise_or.reduceat(bits, at, axis=0), np.minimum.reduceat(low, at), np.maximum.reduceat(high, at), np.minimum.reduceat(count, at), np.minimum.reduceat(c_low, at), np.maximum.reduceat(c_high, at))

    def _may(self, level, p: np.ndarray, q: np.ndarray) -> np.ndarray:
        bits, low, high, count, c_low, c_high = level
        shared = popcount(bits[p] & bits[q])
        # bits of a member that the other side lacks are tokens it lacks
        most = np.minimum(high[p] - np.maximum(0, count[p] - shared), high[q] - np.maximum(0, count[q] - shared))
        most = np.minimum(most, np.minimum(high[p], high[q]))
        one = (c_low[p] == c_high[p]) & (c_low[q] == c_high[q]) & (c_low[p] == c_low[q])
        return ~one & links(most, np.maximum(low[p], most), np.maximum(low[q], most), self.least)

    def candidates(self) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        p = q = np.zeros(1, np.int64)
        for depth in range(len(self.levels) - 1, -1, -1):
            level = self.levels[depth]
            keep = self._may(level, p, q)
            p, q = p[keep], q[keep]
            if not depth or not len(p):
                break
            width = len(self.levels[depth - 1][0])
            kids = np.arange(FAN)
            a = (p[:, None, None] * FAN + kids[None, :, None]).repeat(FAN, 2).ravel()
            b = (q[:, None, None] * FAN + kids[None, None, :]).repeat(FAN, 1).ravel()
            ok = (a <= b) & (a < width) & (b < width)
            p, q = a[ok], b[ok]
        for a, b in zip(p.tolist(), q.tolist(), strict=True):
            x, y = slice(a * LEAF, (a + 1) * LEAF), slice(b * LEAF, (b + 1) * LEAF)
            n, m = self.size[x][:, None], self.size[y][None, :]
            some = self.comp[x][:, None] != self.comp[y][None, :]
            if a == b:
                some &= np.triu(np.ones(some.shape, bool), 1)
            if self.side is not None:
                some &= self.side[x][:, None] != self.side[y][None, :]
            some &= links(np.minimum(n, m), n, m, self.least)
            i, j = np.nonzero(some)
            if not len(i):
                continue
            i, j = i + a * LEAF, j + b * LEAF
            shared = popcount(self.bits[i] & self.bits[j])
            most = np.minimum(self.size[i] - (self.count[i] - shared), self.size[j] - (self.count[j] - shared))
            ok = links(most, self.size[i], self.size[j], self.least)
            i, j = self.order[i[ok]], self.order[j[ok]]
            ok = np.array([self._wide(a, b) for a, b in zip(i.tolist(), j.tolist(), strict=True)], bool)
            if ok.any():
                yield i[ok], j[ok]

    def _wide(self, a: int, b: int) -> bool:
        """The bound once more, at the width of the narrower of the two members' own maps."""
        x, y = self.maps[a], self.maps[b]
        width = min(len(x), len(y))
        if width == self.words:
            return True
        x, y = (m if len(m) == width else fold(m, width) for m in (x, y))
        n, m, shared = self.sizes[a], self.sizes[b], int(popcount(x & y))
        most = min(n - (int(popcount(x)) - shared), m - (int(popcount(y)) - shared))
        return bool(links(most, n, m, self.least))


def join_sets(cls: np.ndarray, sets: list[np.ndarray], least: int) -> tuple[np.ndarray, np.ndarray]:
    """Verified links (a spanning forest of them) among the sets of one group."""
    n = len(sets)
    size = np.array([len(s) for s in sets])
    label = np.arange(n)
    got: list[list[int]] = [[], []]
    tree = SignatureTree(size, [bitmap(s) for s in sets], label, None, least)
    for i, j in tree.candidates():
        while True:
            live = label[i] != label[j]
            i, j = i[live], j[live]
            if not len(i):
                break
            # one pair for each member a round: what it links with joins its component and makes other pairs idle
            _, pick = np.unique(i, return_index=True)
            good = []
            for k in pick.tolist():
                x, y = sets[i[k]], sets[j[k]]
                o = len(np.intersect1d(x, y, assume_unique=True))
                good.append(100 * o >= least * (len(x) + len(y) - o))
            hit = pick[np.array(good)]
            got[0] += i[hit].tolist()
            got[1] += j[hit].tolist()
            if len(hit):
                label = link_labels(n, np.array(got[0]), np.array(got[1]))
            rest = np.ones(len(i), bool)
            rest[pick] = False
            i, j = i[rest], j[rest]
    a, b = np.array(got[0], np.int64), np.array(got[1], np.int64)
    return cls[a], cls[b]


def _groups(table: pa.Table, *keys: str) -> Iterator[np.ndarray]:
    """Row numbers of each group of equal keys."""
    columns = [table[k].to_numpy() for k in keys]
    order = np.lexsort(columns[::-1])
    if len(order):
        cuts = np.flatnonzero(np.any([c[order][1:] != c[order][:-1] for c in columns], axis=0)) + 1
        yield from np.split(order, cuts)


def _whole(batches: Iterator[pa.RecordBatch]) -> pa.Table | None:
    some = [b for b in batches if len(b)]
    return pa.Table.from_batches(some) if some else None


def _sets_of(docs: DataFrame, wanted: DataFrame, width: int) -> DataFrame:
    """``wanted (k1, k2, cls, …)`` with ``set binary``: the class's tokens, from a row of that key."""
    extra = [c for c in wanted.columns if c not in ("k1", "k2", "cls")]
    rows = docs.join(wanted, ["k1", "k2"]).select("_text", "cls", *extra)
    names = rows.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for s in word_slices(batch.column(0), lower=True):
                part = batch.slice(s.first, s.n)
                blobs = [h.astype("<u8").tobytes() for _, h in shingle_sets(s, width)]
                yield pa.RecordBatch.from_arrays([*part.columns[1:], pa.array(blobs, pa.binary())], [*names[1:], "set"])

    schema = ", ".join(f"`{c}` {t}" for c, t in rows.dtypes[1:]) + ", set binary"
    return rows.mapInArrow(run, schema).dropDuplicates(["cls"])


def similar_components(docs: DataFrame, least: int = 80, width: int = WIDTH, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each row of ``docs``: ``doc_id, n_shingles, component_id`` (the smallest id reachable by links)."""
    found = grouped(docs, least, width, id_col, text_col)
    return found.select(F.col("_id").alias(id_col), "n_shingles", "component_id")


def representatives(docs: DataFrame, least: int = 80, width: int = WIDTH, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Of each group of linked rows of ``docs`` the one with the smallest id (one without an id only if none has one), whole; of repeated rows one.

    Rows without words are in no group and stay, repeated ones once.
    """
    found = grouped(docs, least, width, id_col, text_col)
    first = found.where("grp is not null").groupBy("grp").agg(F.min(F.struct(F.col("_id").isNull().alias("n"), "_id", "k1", "k2")).alias("x")).select("x.k1", "x.k2")
    stay = first.union(found.where("grp is null").select("k1", "k2")).distinct()
    k1, k2 = fresh(docs, "_k1", "_k2")
    keyed = docs.withColumns(dict(zip((k1, k2), row_key(F.col(id_col), F.col(text_col)), strict=True)))
    kept = keyed.join(stay.withColumnsRenamed({"k1": k1, "k2": k2}), [k1, k2], "left_semi")
    return kept.dropDuplicates([k1, k2]).select(*docs.columns)


def grouped(docs: DataFrame, least: int, width: int, id_col: str, text_col: str) -> DataFrame:
    """One row for each row of ``docs``: ``_id, k1, k2`` (as of ``row_key``), ``n_shingles, grp`` (a number of its component; null for an empty set), ``component_id``."""
    k1, k2 = row_key(F.col(id_col), F.col(text_col))
    docs = docs.select(F.col(id_col).cast("long").alias("_id"), F.col(text_col).alias("_text"), k1.alias("k1"), k2.alias("k2"))
    n_parts = PARTS * int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def describe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for s in word_slices(batch.column(1), lower=True):
                part = batch.slice(s.first, s.n)
                sets = [h for _, h in shingle_sets(s, width)]
                names = [class_of(h) for h in sets]
                hashes = [pa.array([x and x[k] for x in names], t) for k, t in ((0, pa.int64()), (1, pa.int32()))]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), part.column(3), pa.array([len(h) for h in sets], pa.int64()), *hashes, pa.array([bitmap(h).tobytes() if len(h) else None for h in sets], pa.binary())], ["_id", "k1", "k2", "n", "c1", "c2", "map"])

    described = docs.mapInArrow(describe, "_id long, k1 long, k2 long, n long, c1 long, c2 int, map binary")
    described = cut(described.withColumn("row", F.monotonically_increasing_id()))
    # a class is named by its first row; that of a row with an id, if there is one, has its set read again
    chosen = F.min(F.struct(F.col("_id").isNull().alias("x"), "_id", "k1", "k2", "row")).alias("at")
    classes = cut(described.where("c1 is not null").groupBy("c1", "c2").agg(chosen, F.max("n").alias("n")).select("c1", "c2", F.col("at.row").alias("cls"), F.col("at._id").alias("rep"), "at.k1", "at.k2", "n"))

    def frequent(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = np.zeros(1 << SLOT_BITS, np.int64)
        for batch in batches:
            for s in word_slices(batch.column(1), lower=True):
                slots = [(h >> np.uint64(64 - SLOT_BITS)).astype(np.int64) for _, h in shingle_sets(s, width)]
                count += np.bincount(np.concatenate(slots), minlength=len(count))
        hot = np.flatnonzero(count >= 8 + 2 * count.mean())
        if len(hot) > HOT_SLOTS:
            hot = hot[np.argsort(-count[hot], kind="stable")[:HOT_SLOTS]]
        yield pa.RecordBatch.from_arrays([pa.array(hot), pa.array(count[hot])], ["slot", "count"])

    top = docs.mapInArrow(frequent, "slot long, count long").groupBy("slot").agg(F.sum("count").alias("count")).orderBy(F.desc("count"), "slot").limit(HOT_SLOTS)
    hot = np.zeros(1 << SLOT_BITS, np.uint8)
    hot_slots = top.toArrow()
    if len(hot_slots):
        # frequent ones last, in steps of doubling counts
        hot[hot_slots["slot"].to_numpy()] = np.log2(hot_slots["count"].to_numpy()).astype(np.uint8) + 1

    def prefix_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[tuple[int, int]] = set()
        for batch in batches:
            tokens, owners, others, first = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)], [np.zeros(0, np.int32)], [np.zeros(0, bool)]
            for s in word_slices(batch.column(1), lower=True):
                for _, h in shingle_sets(s, width):
                    name = class_of(h)
                    if name is None or name in seen:
                        continue
                    seen.add(name)
                    size = len(h) - (least * len(h) + 99) // 100 + 1
                    heat = hot[(h >> np.uint64(64 - SLOT_BITS)).astype(np.int64)]
                    chosen, lead = np.zeros(len(h), bool), np.zeros(len(h), bool)
                    chosen[np.lexsort((h, heat))[:size] if heat.any() else slice(size)] = True
                    # copies share what is frequent because of them: only the most frequent tokens are no first ones
                    lead[np.argsort(heat >= VERY_HOT, kind="stable")[:FIRST]] = True
                    both = chosen | lead
                    tokens.append(h[both])
                    owners.append(np.full(int(both.sum()), name[0], np.int64))
                    others.append(np.full(int(both.sum()), name[1], np.int32))
                    first.append(lead[both])
            t, o, p, f = (np.concatenate(x) for x in (tokens, owners, others, first))
            very = hot[(t >> np.uint64(64 - SLOT_BITS)).astype(np.int64)] >= VERY_HOT
            salt = np.where(very, mix(o.view(np.uint64)) % np.uint64(SALT), np.uint64(0))
            part = (mix(t + salt) % np.uint64(n_parts)).astype(np.int64)
            order = np.argsort(part, kind="stable")
            t, o, p, f, part = t[order], o[order], p[order], f[order], part[order]
            at = np.searchsorted(part, np.arange(n_parts + 1))
            have = [k for k in range(n_parts) if at[k] < at[k + 1]]
            yield pa.RecordBatch.from_arrays([pa.array(have, pa.int32()), *(pa.array([x[at[k] : at[k + 1]].tobytes() for k in have], pa.binary()) for x in (t, o, p, f))], ["part", "t", "o", "p", "f"])

    def group_tokens(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = _whole(batches)
        if table is None:
            return
        t, o, p, f = (np.frombuffer(b"".join(table[c].to_pylist()), d) for c, d in (("t", "<u8"), ("o", "<i8"), ("p", "<i4"), ("f", "?")))
        order = np.lexsort((p, o, t))
        t, o, p, f = t[order], o[order], p[order], f[order]
        new = np.concatenate([[True], (t[1:] != t[:-1]) | (o[1:] != o[:-1]) | (p[1:] != p[:-1])])
        f = np.maximum.reduceat(f, np.flatnonzero(new)) if len(new) else f
        t, o, p = t[new], o[new], p[new]
        very = hot[(t >> np.uint64(64 - SLOT_BITS)).astype(np.int64)] >= VERY_HOT
        # phase 1: only members for which the token is one of the first
        for phase, in_phase in ((1, f), (2, np.ones(len(t), bool))):
            # a token that is dealt over partitions has a group by its own name; its members are counted later
            some = in_phase & very
            if some.any():
                yield pa.RecordBatch.from_arrays([pa.array(np.full(int(some.sum()), phase, np.int32)), pa.array(mix(t[some]).view(np.int64)), pa.array(o[some]), pa.array(p[some]), pa.nulls(int(some.sum()), pa.int64())], ["phase", "grp", "c1", "c2", "members"])
            some = in_phase & ~very
            tt, oo, pp = t[some], o[some], p[some]
            if not len(tt):
                continue
            start = np.flatnonzero(np.concatenate([[True], tt[1:] != tt[:-1]]))
            count = np.diff(np.append(start, len(tt)))
            name = combine(oo.view(np.uint64) ^ pp.astype(np.uint64), start) ^ count.astype(np.uint64)
            many = np.flatnonzero(count > 1)
            _, once = np.unique(name[many], return_index=True)
            pick = many[once]
            if not len(pick):
                continue
            rows = np.repeat(start[pick] - (np.cumsum(count[pick]) - count[pick]), count[pick]) + np.arange(int(count[pick].sum()))
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(rows), phase, np.int32)), pa.array(np.repeat(name[pick], count[pick]).view(np.int64)), pa.array(oo[rows]), pa.array(pp[rows]), pa.array(np.repeat(count[pick], count[pick]).astype(np.int64))], ["phase", "grp", "c1", "c2", "members"])
        relax()

    postings = docs.mapInArrow(prefix_rows, "part int, t binary, o binary, p binary, f binary")
    groups = cut(postings.repartitionById(n_parts, F.col("part")).mapInArrow(group_tokens, "phase int, grp long, c1 long, c2 int, members long"))
    counted = cut(groups.where("members is null").groupBy("phase", "grp").agg(F.count("*").alias("count")).where("count > 1"))
    groups = groups.join(classes.select("c1", "c2", "cls"), ["c1", "c2"]).select("phase", "grp", "cls", "members")
    if not counted.isEmpty():
        dealt = groups.where("members is null").drop("members").join(counted, ["phase", "grp"]).select("phase", "grp", "cls", F.col("count").alias("members"))
        groups = groups.where("members is not null").union(dealt)
    groups = cut(groups.where("members is not null"))

    # phase 1: groups of first tokens, with their sets; large ones in blocks, since phase 2 finds what is left
    firsts = groups.where("phase = 1").select("grp", "cls", F.pmod(F.xxhash64("cls"), F.ceil(F.col("members") / SPLIT)).cast("int").alias("block"))
    wanted = firsts.distinct().groupBy("cls").agg(F.collect_list(F.struct("grp", "block")).alias("tasks")).join(classes.select("cls", "k1", "k2"), "cls")
    with_sets = _sets_of(docs, wanted, width).withColumn("x", F.explode("tasks")).select("x.grp", "x.block", "cls", "set")

    def join_groups(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = _whole(batches)
        if table is None:
            return
        cls, blobs = table["cls"].to_numpy(), table["set"].combine_chunks()
        for rows in _groups(table, "grp", "block"):
            if len(rows) > 1:
                a, b = join_sets(cls[rows], [np.frombuffer(x.as_buffer(), "<u8") for x in blobs.take(pa.array(rows))], least)
                if len(a):
                    yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], ["a", "b"])
        relax()

    edges = cut(spread_out(with_sets, "grp", "block").mapInArrow(join_groups, "a long, b long"))
    known = components(edges)

    # phase 2: groups that still span components
    members = groups.where("phase = 2").select("grp", "cls").distinct().join(known.withColumnRenamed("node", "cls"), "cls", "left")
    members = cut(members.select("grp", "cls", F.coalesce("component", "cls").alias("comp")))
    spans = cut(members.groupBy("grp").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.count("*").alias("members"), F.bit_xor(F.xxhash64("cls")).alias("sum")).where("lo <> hi").groupBy("sum", "members").agg(F.min("grp").alias("grp")))
    maps = described.select(F.col("row").alias("cls"), "n", "map").join(members.select("cls").distinct(), "cls", "left_semi")
    open_ = members.join(spans.select("grp", F.ceil(F.col("members") / (SPLIT // 2)).cast("int").alias("blocks")), "grp").join(maps, "cls")
    open_ = open_.withColumn("block", F.when(F.col("blocks") > 2, F.pmod(F.xxhash64("cls"), F.col("blocks")).cast("int")).otherwise(0))
    pair = F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda c: F.least("block", c) * F.col("blocks") + F.greatest("block", c))
    open_ = open_.withColumn("task", F.explode(F.when(F.col("blocks") > 2, pair).otherwise(F.array(F.lit(0))))).select("grp", "task", "block", "cls", "comp", "n", "map")

    def traverse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = _whole(batches)
        if table is None:
            return
        cls, comp, n, block, blobs = table["cls"].to_numpy(), table["comp"].to_numpy(), table["n"].to_numpy(), table["block"].to_numpy(), table["map"].combine_chunks()
        out: list[list[np.ndarray]] = [[], []]
        for rows in _groups(table, "grp", "task"):
            if len(rows) < 2:
                continue
            side = block[rows]
            tree = SignatureTree(n[rows], [np.frombuffer(x.as_buffer(), "<u8") for x in blobs.take(pa.array(rows))], comp[rows], side if len(np.unique(side)) > 1 else None, least)
            for i, j in tree.candidates():
                a, b = cls[rows[i]], cls[rows[j]]
                out[0].append(np.minimum(a, b))
                out[1].append(np.maximum(a, b))
        if out[0]:
            pairs = np.unique(np.stack([np.concatenate(o) for o in out]), axis=1)
            yield pa.RecordBatch.from_arrays([pa.array(pairs[0]), pa.array(pairs[1])], ["a", "b"])

    pairs = cut(spread_out(open_, "grp", "task").mapInArrow(traverse, "a long, b long").distinct())
    if not pairs.isEmpty():
        needed = pairs.select(F.explode(F.array("a", "b")).alias("cls")).distinct().join(classes.select("cls", "k1", "k2"), "cls")
        sets = cut(_sets_of(docs, needed, width).select("cls", "set"))
        both = pairs.join(sets.select(F.col("cls").alias("a"), F.col("set").alias("x")), "a").join(sets.select(F.col("cls").alias("b"), F.col("set").alias("y")), "b")

        def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                keep = []
                for k in range(len(batch)):
                    x, y = (np.frombuffer(batch.column(c)[k].as_buffer(), "<u8") for c in (2, 3))
                    o = len(np.intersect1d(x, y, assume_unique=True))
                    if 100 * o >= least * (len(x) + len(y) - o):
                        keep.append(k)
                yield pa.RecordBatch.from_arrays([batch.column(c).take(pa.array(keep, pa.int64())) for c in (0, 1)], ["a", "b"])

        more = cut(both.select("a", "b", "x", "y").mapInArrow(check, "a long, b long"))
        known = components(edges.union(more))
    named = cut(classes.join(known.withColumnRenamed("node", "cls"), "cls", "left").select("c1", "c2", "rep", F.coalesce("component", "cls").alias("grp")))
    ids = named.groupBy("grp").agg(F.min("rep").alias("component_id"))
    ids = cut(named.join(ids, "grp").select("c1", "c2", "grp", "component_id"))
    out = described.select("_id", "k1", "k2", "n", "c1", "c2").join(ids, ["c1", "c2"], "left")
    return out.select("_id", "k1", "k2", F.col("n").alias("n_shingles"), "grp", F.when(F.col("c1").isNull(), F.col("_id")).otherwise(F.col("component_id")).alias("component_id"))
