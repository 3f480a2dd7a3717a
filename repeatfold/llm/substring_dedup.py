"""Substring dedup with suffix automata: words covered by long word sequences that also stand elsewhere are removed.

Every window of ``width`` words has an anchor, the least hash of the k-grams in it; equal windows have equal anchors, and the consecutive
windows of a document with one anchor are a segment. So a window's other occurrences are found among the segments of its anchor alone:

* anchors are counted over the whole corpus; those that stand once are done;
* the distinct segments of all others, with their multiplicities, are dealt out by anchor and packed into reference shards of at most
  ``SHARD_WORDS`` words; each shard's suffix automaton is built where the shard is, the segments stream through it, and the matching statistics
  with the states' occurrence counts say which windows repeat, hence the maximal spans to remove;
* an anchor with more than ``SHARD`` distinct segments does not fit: its segments are cut up again by anchors of longer k-grams (``GRAMS``, then
  whole windows), which equal windows share too, and those go the same way.

Windows are judged on the input. Words are ``[^\\x20\\x09-\\x0D]+``, taken as they are and compared by 64-bit hashes. A segment that goes on for more
than ``RUN`` windows (a periodic text) is cut there, so a shard's size does not follow a text's.

``strip_reference`` removes what matches a given reference instead: automata of its shards are broadcast (the size is checked) and documents
stream through them.

Null and empty texts have no words: nothing is removed, the kept text is empty. Repeated rows are occurrences of each other. A very long
text is one slice of a batch. Ids may be of any type, and null. Columns of the input named like the results are replaced, other names never
clash; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StringType, StructField, StructType

from repeatfold.llm.common import cut, fresh, row_key, spread_out
from repeatfold.llm.words import Slice, mix, window_hashes, word_slices, _powers

GRAMS = (8, 20)
#: Distinct segments of an anchor that go into one shard, and words of a shard (of more than one segment).
SHARD = 2_000
SHARD_WORDS = 100_000
#: Windows of one segment at most.
RUN = 2_048
#: Words of a broadcast reference at most.
MAX_REFERENCE = 2_000_000


class SuffixAutomaton:
    """States of all word sequences of a shard; sequences have multiplicities, states the occurrences of what they stand for."""

    def __init__(self) -> None:
        self.next: list[dict[int, int]] = [{}]
        self.link, self.length, self.count = [-1], [0], [0]
        self.settled = False

    def _clone(self, p: int, q: int, w: int) -> int:
        nxt, link = self.next, self.link
        c = len(nxt)
        nxt.append(nxt[q].copy())
        link.append(link[q])
        self.length.append(self.length[p] + 1)
        self.count.append(0)
        link[q] = c
        while p >= 0 and nxt[p].get(w) == q:
            nxt[p][w] = c
            p = link[p]
        return c

    def add(self, words: list[int], times: int = 1) -> None:
        nxt, link, length, count = self.next, self.link, self.length, self.count
        last = 0
        for w in words:
            q = nxt[last].get(w)
            if q is not None:
                last = q if length[q] == length[last] + 1 else self._clone(last, q, w)
            else:
                new, p = len(nxt), last
                nxt.append({})
                length.append(length[last] + 1)
                count.append(0)
                link.append(0)
                while p >= 0:
                    out = nxt[p]
                    if w in out:
                        q = out[w]
                        link[new] = q if length[q] == length[p] + 1 else self._clone(p, q, w)
                        break
                    out[w] = new
                    p = link[p]
                last = new
            count[last] += times
        self.settled = False

    def settle(self) -> None:
        """Occurrences reach the shorter sequences that end with a state's ones."""
        count, link = self.count, self.link
        for s in np.argsort(-np.array(self.length[1:]), kind="stable").tolist():
            count[link[s + 1]] += count[s + 1]
        self.settled = True

    def window_counts(self, words: list[int], width: int) -> list[int]:
        """For each window of ``width`` words, how often it stands in the shard: 0 where the matching statistic is shorter."""
        if not self.settled:
            self.settle()
        nxt, link, length, count = self.next, self.link, self.length, self.count
        out, state, matched = [], 0, 0
        for k, w in enumerate(words):
            to = nxt[state].get(w)
            while to is None and state:
                state = link[state]
                matched = length[state]
                to = nxt[state].get(w)
            if to is not None:
                state = to
                matched += 1
            if matched > width:
                while length[link[state]] >= width:
                    state = link[state]
                    matched = length[state]
            if k >= width - 1:
                out.append(count[state] if matched >= width else 0)
        return out


def _sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    """Least of each ``width`` neighbours, by doubling."""
    out, have = x, 1
    while 2 * have <= width:
        out = np.minimum(out[:-have], out[have:])
        have *= 2
    rest = width - have
    return np.minimum(out[: len(out) - rest], out[rest:]) if rest else out


def segments(words: np.ndarray, at: np.ndarray, width: int, gram: int = GRAMS[0]) -> tuple[np.ndarray, ...]:
    """(document, first word within it, windows, anchor, content hash, whether a window may stand in it twice) of all segments of a slice.

    ``at``: first word of each document, and the end.
    """
    gram = min(gram, width)
    grams = window_hashes(words, gram)
    if len(words) < width:
        return tuple(np.zeros(0, t) for t in (np.int64, np.int64, np.int64, np.uint64, np.uint64, bool))
    anchor = _sliding_min(grams, width - gram + 1)
    doc = np.repeat(np.arange(len(at) - 1), np.diff(at))
    inside = doc[: len(anchor)] == doc[width - 1 :]
    new = inside.copy()
    new[1:] &= (anchor[1:] != anchor[:-1]) | ~inside[:-1]
    stop = inside.copy()
    stop[:-1] &= (anchor[1:] != anchor[:-1]) | ~inside[1:]
    a, b = np.flatnonzero(new), np.flatnonzero(stop) + 1
    if len(a) and (b - a).max() > RUN:
        pieces = -(-(b - a) // RUN)
        k = np.arange(int(pieces.sum())) - np.repeat(np.cumsum(pieces) - pieces, pieces)
        a, b = np.repeat(a, pieces) + RUN * k, np.repeat(b, pieces)
        b = np.minimum(b, a + RUN)
    head = np.concatenate([[0], np.cumsum((grams[: len(anchor)] == anchor) & inside)])
    again = head[b - 1] > head[a]
    p, q = _powers(len(words) + 1)
    total = np.zeros(len(words) + 1, np.uint64)
    np.cumsum(words * p[: len(words)], out=total[1:])
    content = mix((total[b + width - 1] - total[a]) * q[a] + (b - a).astype(np.uint64))
    return doc[a], a - at[doc[a]], b - a, anchor[a], content, again


CONTENT = "anchor long, seg long, times long, words binary"


def _marks(content: DataFrame, width: int, grams: tuple[int, ...]) -> DataFrame:
    """``(anchor, seg, idx)``: windows of the distinct segments ``content`` that repeat; ``idx`` null where all do."""

    def match(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        some = [b for b in batches if len(b)]
        if not some:
            return
        table = pa.Table.from_batches(some)
        anchor, seg, times, blobs = table["anchor"].to_numpy(), table["seg"].to_numpy(), table["times"].to_numpy(), table["words"].combine_chunks()
        size = np.diff(np.frombuffer(blobs.buffers()[1], np.int32)[blobs.offset : blobs.offset + len(blobs) + 1]) // 8
        order = np.lexsort((seg, anchor))
        starts = np.flatnonzero(np.concatenate([[True], anchor[order][1:] != anchor[order][:-1]]))
        # whole anchors, one after another, fill a shard
        weight = np.add.reduceat(size[order], starts)
        shard, shards, room = [], [], SHARD_WORDS
        for k, w in enumerate(weight.tolist()):
            if shard and w > room:
                shards.append(shard)
                shard, room = [], SHARD_WORDS
            shard.append(k)
            room -= w
        shards.append(shard)
        ends = np.append(starts[1:], len(order))
        for shard in shards:
            rows = order[starts[shard[0]] : ends[shard[-1]]]
            # words by small numbers, which dictionaries take faster
            stop = np.cumsum(size[rows])
            flat = np.unique(np.frombuffer(b"".join(blobs.take(pa.array(rows)).to_pylist()), "<i8"), return_inverse=True)[1].tolist()
            texts = [flat[b - n : b] for b, n in zip(stop.tolist(), size[rows].tolist(), strict=True)]
            automaton = SuffixAutomaton()
            for words, n in zip(texts, times[rows].tolist(), strict=True):
                automaton.add(words, n)
            out: list[list] = [[], [], []]
            for words, k in zip(texts, rows.tolist(), strict=True):
                counts = automaton.window_counts(words, width)
                hit = [i for i, c in enumerate(counts) if c > 1]
                if hit:
                    for o, x in zip(out, (int(anchor[k]), int(seg[k]), None if len(hit) == len(counts) else hit), strict=True):
                        o.append(x)
            yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.list_(pa.int32()))], ["anchor", "seg", "idx"])

    here = lambda df: spread_out(df, "anchor").mapInArrow(match, "anchor long, seg long, idx array<int>")
    crowded = cut(content.groupBy("anchor").count().where(F.col("count") > SHARD).select("anchor")) if grams else None
    if crowded is None or crowded.isEmpty():
        return here(content)

    def cut_again(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(len(batch)):
                words = np.frombuffer(batch.column(3)[k].as_buffer(), "<u8")
                _, start, n, anchor, inner, _ = segments(words, np.array([0, len(words)]), width, grams[0])
                longer = mix(anchor ^ mix(batch.column(0).slice(k, 1).to_numpy().view(np.uint64)))
                blobs = [words[a : a + m + width - 1].tobytes() for a, m in zip(start.tolist(), n.tolist(), strict=True)]
                own = batch.take(pa.array(np.full(len(start), k)))
                yield pa.RecordBatch.from_arrays([own.column(0), own.column(1), own.column(2), pa.array(start.astype(np.int32)), pa.array(n.astype(np.int32)), pa.array(longer.view(np.int64)), pa.array(inner.view(np.int64)), pa.array(blobs, pa.binary())], ["outer", "outer_seg", "times", "start", "n", "anchor", "seg", "words"])

    finer = content.join(crowded, "anchor", "left_semi").select("anchor", "seg", "times", "words")
    finer = cut(finer.mapInArrow(cut_again, "outer long, outer_seg long, times long, start int, n int, anchor long, seg long, words binary"))
    inner = cut(finer.groupBy("anchor", "seg").agg(F.sum("times").alias("times"), F.first("words").alias("words")))
    found = finer.select("outer", "outer_seg", "start", "n", "anchor", "seg").join(_marks(inner, width, grams[1:]), ["anchor", "seg"])
    every = F.coalesce("idx", F.sequence(F.lit(0), F.col("n") - 1))
    back = found.select("outer", "outer_seg", F.explode(F.transform(every, lambda i: i + F.col("start"))).alias("i")).groupBy(F.col("outer").alias("anchor"), F.col("outer_seg").alias("seg")).agg(F.collect_set("i").alias("idx"))
    return here(content.join(crowded, "anchor", "left_anti")).union(back)


def repeated_spans(docs: DataFrame, width: int) -> DataFrame:
    """``(k1, k2, spans)`` for the rows of ``docs`` (``k1, k2, _text``) with repeated windows: structs (start, n, idx), n windows from ``start`` or only those at ``idx``."""

    def cut_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for s in word_slices(batch.column(2)):
                doc, start, n, anchor, content, again = segments(s.hashes() if len(s.start) else np.zeros(0, np.uint64), s.at, width)
                at = pa.array(doc + s.first)
                yield pa.RecordBatch.from_arrays([batch.column(0).take(at), batch.column(1).take(at), pa.array(start.astype(np.int32)), pa.array(n.astype(np.int32)), pa.array(anchor.view(np.int64)), pa.array(content.view(np.int64)), pa.array(again)], ["k1", "k2", "start", "n", "anchor", "seg", "again"])

    segs = docs.select("k1", "k2", "_text").mapInArrow(cut_up, "k1 long, k2 long, start int, n int, anchor long, seg long, again boolean")
    anchors = cut(segs.groupBy("anchor").agg(F.count("*").alias("rows"), F.max("again").alias("again")).where("rows > 1 or again").select("anchor"))
    found = cut(segs.drop("again").join(anchors, "anchor"))
    variants = found.groupBy("anchor", "seg").agg(F.count("*").alias("times"), F.min(F.struct("k1", "k2", "start", "n")).alias("at"))
    wanted = variants.groupBy(F.col("at.k1").alias("k1"), F.col("at.k2").alias("k2")).agg(F.collect_list(F.struct("anchor", "seg", "times", F.col("at.start").alias("start"), F.col("at.n").alias("n"))).alias("w"))

    def fetch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column(1)
            for s in word_slices(batch.column(0)):
                h = s.hashes() if len(s.start) else np.zeros(0, np.uint64)
                part = lists.slice(s.first, s.n)
                flat = part.flatten()
                owner = np.repeat(np.arange(s.n), part.value_lengths().to_numpy())
                begin = s.at[owner] + flat.field("start").to_numpy()
                end = begin + flat.field("n").to_numpy() + width - 1
                blobs = [h[a:b].astype("<i8").tobytes() for a, b in zip(begin.tolist(), end.tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([flat.field("anchor"), flat.field("seg"), flat.field("times"), pa.array(blobs, pa.binary())], ["anchor", "seg", "times", "words"])

    # rows that share id and text bring a segment twice
    content = docs.join(wanted, ["k1", "k2"]).select("k1", "k2", "_text", "w").dropDuplicates(["k1", "k2"]).select("_text", "w").mapInArrow(fetch, CONTENT)
    marks = cut(_marks(cut(content), width, (*GRAMS[1:], width)))
    some = found.join(marks, ["anchor", "seg"]).select("k1", "k2", "start", "n", "idx")
    return some.groupBy("k1", "k2").agg(F.collect_set(F.struct("start", "n", "idx")).alias("spans"))


def covered(s: Slice, spans: pa.Array, width: int) -> np.ndarray:
    """Words of a slice that its documents' repeated windows cover."""
    depth = np.zeros(len(s.start) + 1, np.int64)
    owner = np.repeat(np.arange(s.n), np.nan_to_num(spans.value_lengths().to_numpy(zero_copy_only=False)).astype(np.int64))
    flat = spans.flatten()
    if len(flat):
        begin = s.at[owner] + flat.field("start").to_numpy()
        idx = flat.field("idx")
        full = idx.is_null().to_numpy(zero_copy_only=False)
        np.add.at(depth, begin[full], 1)
        np.add.at(depth, begin[full] + flat.field("n").to_numpy()[full] + width - 1, -1)
        rows = np.flatnonzero(~full)
        if len(rows):
            part = idx.take(pa.array(rows))
            first = np.repeat(begin[rows], part.value_lengths().to_numpy()) + part.flatten().to_numpy()
            np.add.at(depth, first, 1)
            np.add.at(depth, first + width, -1)
    return np.cumsum(depth)[:-1] > 0


def kept_bytes(s: Slice, keep: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of each document's kept words joined by one space."""
    edge = np.zeros(len(s.data) + 1, np.int8)
    edge[s.start[keep]] += 1
    np.subtract.at(edge, s.end[keep], 1)
    chosen = np.cumsum(edge[:-1], dtype=np.int8) > 0
    which = np.flatnonzero(keep)
    doc = np.searchsorted(s.at, which, "right") - 1
    between = which[:-1][doc[:-1] == doc[1:]] if len(which) else which
    data = s.data.copy()
    gap = s.end[between]
    data[gap] = 0x20
    chosen[gap] = True
    size = np.concatenate([[0], np.cumsum(chosen)])
    return data[chosen], size[s.offsets]


def dedup(docs: DataFrame, width: int = 35, id_col: str = "doc_id", text_col: str = "text", with_text: bool = True) -> DataFrame:
    """One row for each row of ``docs``: its columns but the text's old value, with ``n_words, n_removed, kept_sha256`` and, with ``with_text``, the kept text in ``text_col``."""
    own = ["n_words", "n_removed", "kept_sha256"]
    rest = [c for c in docs.columns if c not in (text_col, *own)] if with_text else [id_col]
    key = row_key(F.col(id_col), F.col(text_col))
    spans = repeated_spans(docs.select(key[0].alias("k1"), key[1].alias("k2"), F.col(text_col).alias("_text")), width)
    k1, k2, found = fresh(docs, "_k1", "_k2", "_spans")
    spans = spans.withColumnsRenamed({"k1": k1, "k2": k2, "spans": found})
    rows = docs.withColumns({k1: key[0], k2: key[1]}).join(spans, [k1, k2], "left").select(*rest, F.col(text_col), found)
    fields = [docs.schema[c] for c in rest] + ([StructField(text_col, StringType())] if with_text else [])
    n_rest = len(rest)

    def strip(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for s in word_slices(batch.column(n_rest)):
                gone = covered(s, batch.column(n_rest + 1).slice(s.first, s.n), width)
                data, at = kept_bytes(s, ~gone)
                raw = memoryview(data.tobytes())
                at = at.tolist()
                sha = [hashlib.sha256(raw[a:b]).hexdigest() for a, b in zip(at, at[1:], strict=False)]
                removed = np.concatenate([[0], np.cumsum(gone)])[s.at]
                columns = [batch.column(c).slice(s.first, s.n) for c in range(n_rest)]
                if with_text:
                    columns.append(pa.array([str(raw[a:b], "utf-8") for a, b in zip(at, at[1:], strict=False)], pa.string()))
                yield pa.RecordBatch.from_arrays([*columns, pa.array(np.diff(s.at).astype(np.int64)), pa.array(np.diff(removed).astype(np.int64)), pa.array(sha)], [f.name for f in fields] + own)

    schema = StructType([*fields, StructField("n_words", LongType()), StructField("n_removed", LongType()), StructField("kept_sha256", StringType())])
    return rows.mapInArrow(strip, schema)


def strip_reference(docs: DataFrame, reference: DataFrame, width: int = 35, shard_words: int = 100_000, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(id, n_words, n_matched, text)``: every row of ``docs`` without the words in windows that also stand in ``reference`` (column ``text``).

    The reference reaches every executor, so it may have ``MAX_REFERENCE`` words at most; a longer one raises. Its anchors tell which windows
    are worth matching; those stream through the automata of the shards that hold their anchor.
    """
    texts = reference.select("text").where("text is not null")
    total = texts.agg(F.sum(F.regexp_count("text", F.lit(r"[^ \t-\r]+")))).first()[0] or 0
    if total > MAX_REFERENCE:
        raise ValueError(f"a reference of {total} words; at most {MAX_REFERENCE} are broadcast")
    items: list[np.ndarray] = []
    for s in word_slices(texts.toArrow()["text"]) if total else ():
        h = s.hashes()
        items += [h[s.at[d] : s.at[d + 1]] for d in range(s.n) if s.at[d + 1] - s.at[d] >= width]
    items.sort(key=lambda x: x.tobytes())
    shards: list[list[np.ndarray]] = [[]]
    for x in items:
        if sum(map(len, shards[-1])) + len(x) > shard_words and shards[-1]:
            shards.append([])
        shards[-1].append(x)
    anchors = [np.unique(np.concatenate([segments(x, np.array([0, len(x)]), width)[3] for x in shard])) if shard else np.zeros(0, np.uint64) for shard in shards]
    sent = docs.sparkSession.sparkContext.broadcast((shards, anchors))
    kind = dict(docs.dtypes)[id_col]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, keys = sent.value
        automata: dict[int, SuffixAutomaton] = {}
        for batch in batches:
            for s in word_slices(batch.column(1)):
                h = s.hashes() if len(s.start) else np.zeros(0, np.uint64)
                doc, start, n, anchor, _, _ = segments(h, s.at, width)
                depth = np.zeros(len(h) + 1, np.int64)
                for k, known in enumerate(keys):
                    for r in np.flatnonzero(np.isin(anchor, known)).tolist():
                        if k not in automata:
                            automata[k] = SuffixAutomaton()
                            for x in parts[k]:
                                automata[k].add(x.view(np.int64).tolist())
                        a = int(s.at[doc[r]] + start[r])
                        for i, c in enumerate(automata[k].window_counts(h[a : a + int(n[r]) + width - 1].view(np.int64).tolist(), width)):
                            if c:
                                depth[a + i] += 1
                                depth[a + i + width] -= 1
                gone = np.cumsum(depth)[:-1] > 0
                data, at = kept_bytes(s, ~gone)
                removed = np.concatenate([[0], np.cumsum(gone)])[s.at]
                raw, at = data.tobytes(), at.tolist()
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(s.first, s.n), pa.array(np.diff(s.at).astype(np.int64)), pa.array(np.diff(removed).astype(np.int64)), pa.array([raw[a:b].decode() for a, b in zip(at, at[1:], strict=False)], pa.string())], [id_col, "n_words", "n_matched", text_col])

    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, n_words long, n_matched long, `{text_col}` string")
