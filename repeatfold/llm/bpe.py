"""Byte-pair merging of many short sequences at once on ragged numpy arrays.

All sequences lie one after another in one flat array of symbols. In a round each sequence finds its lowest rank among the
neighbouring pairs and merges that pair; a round is a handful of array operations over every sequence that still changes.
Ranks whose product may at once take part in a better pair, and ranks shared by several pieces, are merged one (leftmost)
occurrence a round, so that the result is that of a priority queue over (rank, position).

A round reads a whole sequence, so sequences of over ``LONG`` symbols take the same merges on linked arrays: a round goes to the places of the
lowest rank alone, and the work follows the number of merges.
"""

from __future__ import annotations

import heapq
import json
from functools import lru_cache

import numpy as np

from repeatfold.llm.words import hash_spans, mix

NONE = np.int32(2**31 - 1)
#: Symbols of a sequence from which rounds go to the places of a rank instead of reading the whole sequence.
LONG = 400


class PairTable:
    """(left id, right id) -> (rank, merged id), an open-addressing table of fixed size for one vocabulary."""

    def __init__(self, left: np.ndarray, right: np.ndarray, rank: np.ndarray, merged: np.ndarray) -> None:
        key = left.astype(np.uint64) << np.uint64(32) | right.astype(np.uint64)
        self.bits = max(4, (4 * len(key) - 1).bit_length())
        self.keys = np.full(1 << self.bits, 2**64 - 1, np.uint64)
        self.rank = np.full(1 << self.bits, NONE, np.int32)
        self.merged = np.zeros(1 << self.bits, np.int32)
        mask = np.uint64((1 << self.bits) - 1)
        todo, at = np.arange(len(key)), mix(key) & mask
        self.probes = 0
        while len(todo):
            self.probes += 1
            free = self.keys[at] == 2**64 - 1
            _, one = np.unique(at[free], return_index=True)
            put = np.flatnonzero(free)[one]
            self.keys[at[put]], self.rank[at[put]], self.merged[at[put]] = key[todo[put]], rank[todo[put]], merged[todo[put]]
            rest = np.ones(len(todo), bool)
            rest[put] = False
            todo, at = todo[rest], (at[rest] + np.uint64(1)) & mask
        low = {}
        for a, b, r in zip(left.tolist(), right.tolist(), rank.tolist(), strict=True):
            for x in (a, b):
                low[x] = min(low.get(x, r), r)
        self.single = np.zeros(int(rank.max(initial=0)) + 1, bool)
        seen: dict[int, int] = {}
        for m, r in zip(merged.tolist(), rank.tolist(), strict=True):
            if low.get(m, r + 1) <= r or seen.setdefault(r, m) != m:
                self.single[r] = True

    def find(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rank (``NONE`` without such a pair) and place in the table."""
        key = left.astype(np.uint64) << np.uint64(32) | right.astype(np.uint64)
        mask = np.uint64((1 << self.bits) - 1)
        at = mix(key) & mask
        rank = np.full(len(key), NONE, np.int32)
        place = at.astype(np.int64)
        found = self.keys[at]
        hit = found == key
        rank[hit] = self.rank[at[hit]]
        todo = np.flatnonzero(~hit & (found != 2**64 - 1))
        while len(todo):
            at = (place[todo].astype(np.uint64) + np.uint64(1)) & mask
            place[todo] = at
            found = self.keys[at]
            hit = found == key[todo]
            rank[todo[hit]] = self.rank[at[hit]]
            todo = todo[~hit & (found != 2**64 - 1)]
        return rank, place


def merge_all(symbols: np.ndarray, lengths: np.ndarray, table: PairTable) -> tuple[np.ndarray, np.ndarray]:
    """Surviving symbols and their number in each sequence. ``symbols``: ids, below 0 for what never merges."""
    done_sym: list[np.ndarray] = []
    done_seq: list[np.ndarray] = []
    seq = np.repeat(np.arange(len(lengths)), lengths)
    sym = symbols.astype(np.int32)
    while len(sym):
        rank = np.full(len(sym), NONE, np.int32)
        place = np.zeros(len(sym), np.int64)
        ok = np.flatnonzero((seq[:-1] == seq[1:]) & (sym[:-1] >= 0) & (sym[1:] >= 0))
        rank[ok], place[ok] = table.find(sym[ok], sym[ok + 1])
        starts = np.flatnonzero(np.concatenate([[True], seq[1:] != seq[:-1]]))
        size = np.diff(np.append(starts, len(seq)))
        best = np.minimum.reduceat(rank, starts)
        active = best < NONE
        if not active.all():
            quiet = np.repeat(~active, size)
            done_sym.append(sym[quiet])
            done_seq.append(seq[quiet])
            keep = ~quiet
            sym, seq, rank, place = sym[keep], seq[keep], rank[keep], place[keep]
            size, best = size[active], best[active]
            starts = np.concatenate([[0], np.cumsum(size)[:-1]]).astype(np.int64) if len(size) else np.zeros(0, np.int64)
        if not len(sym):
            break
        take = rank == np.repeat(best, size)
        at = np.flatnonzero(take)
        owner = np.searchsorted(starts, at, "right") - 1
        first = np.concatenate([[True], owner[1:] != owner[:-1]])
        gap = np.concatenate([[True], np.diff(at) != 1]) | first
        run = np.maximum.accumulate(np.where(gap, np.arange(len(at)), 0))
        pick = at[np.where(table.single[best[owner]], first, (np.arange(len(at)) - run) % 2 == 0)]
        sym[pick] = table.merged[place[pick]]
        stay = np.ones(len(sym), bool)
        stay[pick + 1] = False
        sym, seq = sym[stay], seq[stay]
    if not done_sym:
        return np.zeros(0, np.int32), np.zeros(len(lengths), np.int64)
    sym, seq = np.concatenate(done_sym), np.concatenate(done_seq)
    order = np.argsort(seq, kind="stable")
    return sym[order], np.bincount(seq, minlength=len(lengths))


def merge_linked(symbols: np.ndarray, lengths: np.ndarray, table: PairTable) -> tuple[np.ndarray, np.ndarray]:
    """As ``merge_all``, for long sequences: places are kept by rank, and a round merges all places of the lowest one.

    Where a product would at once take part in a pair of that rank or a lower one, its sequence's later places wait for the next round.
    """
    n = len(symbols)
    seq = np.repeat(np.arange(len(lengths)), lengths)
    # one place more at the end, of no sequence, follows the last symbol and precedes the first
    sym, seq = np.append(symbols, -1).astype(np.int32), np.append(seq, -1)
    after, before = np.arange(1, n + 2), np.arange(-1, n)
    after[n], before[0] = n, n
    alive = np.ones(n + 1, bool)
    rank, product = np.full(n + 1, NONE, np.int32), np.zeros(n + 1, np.int32)
    waiting: dict[int, list[np.ndarray]] = {}
    heap: list[int] = []

    def find(left: np.ndarray, right: np.ndarray, same: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        out, made = np.full(len(left), NONE, np.int32), np.zeros(len(left), np.int32)
        ok = np.flatnonzero(same & (left >= 0) & (right >= 0))
        out[ok], place = table.find(left[ok], right[ok])
        made[ok] = table.merged[place]
        return out, made

    def wait(at: np.ndarray) -> None:
        at = at[rank[at] < NONE]
        at = at[np.argsort(rank[at], kind="stable")]
        r = rank[at]
        cuts = np.flatnonzero(r[1:] != r[:-1]) + 1
        for part in np.split(at, cuts) if len(at) else []:
            k = int(rank[part[0]])
            if k not in waiting:
                heapq.heappush(heap, k)
            waiting.setdefault(k, []).append(part)

    every = np.arange(n)
    rank[:n], product[:n] = find(sym[:n], sym[after[:n]], seq[:n] == seq[after[:n]])
    wait(every)
    while heap:
        best = heapq.heappop(heap)
        at = np.unique(np.concatenate(waiting.pop(best)))
        at = at[alive[at] & (rank[at] == best)]
        if not len(at):
            continue
        # of places that share symbols every other one
        apart = np.concatenate([[True], after[at[:-1]] != at[1:]])
        run = np.maximum.accumulate(np.where(apart, np.arange(len(at)), 0))
        pick = at[(np.arange(len(at)) - run) % 2 == 0]
        gone = after[pick]
        beyond, ahead = after[gone], before[pick]
        made = product[pick]
        left = sym[ahead]
        joined = np.flatnonzero(ahead[1:] == gone[:-1]) + 1
        left[joined] = made[joined - 1]
        better = (find(made, sym[beyond], seq[pick] == seq[beyond])[0] <= best) | (find(left, made, seq[ahead] == seq[pick])[0] <= best)
        if better.any():
            first = np.concatenate([[True], seq[pick][1:] != seq[pick][:-1]])
            earlier = np.cumsum(better) - better
            held = earlier > earlier[np.maximum.accumulate(np.where(first, np.arange(len(pick)), 0))]
            pick, gone, beyond, made = pick[~held], gone[~held], beyond[~held], made[~held]
        sym[pick], alive[gone], rank[gone] = made, False, NONE
        after[pick], before[beyond] = beyond, pick
        touched = np.unique(np.concatenate([pick, before[pick]]))
        touched = touched[touched < n]
        rank[touched], product[touched] = find(sym[touched], sym[after[touched]], seq[touched] == seq[after[touched]])
        wait(np.union1d(touched, at[alive[at] & (rank[at] == best)]))
    alive[n] = False
    return sym[alive], np.bincount(seq[alive], minlength=len(lengths))


def merge(symbols: np.ndarray, lengths: np.ndarray, table: PairTable) -> tuple[np.ndarray, np.ndarray]:
    """Surviving symbols and their number in each sequence, whatever the sequences' lengths."""
    long = lengths > LONG
    if not long.any():
        return merge_all(symbols, lengths, table)
    mine = np.repeat(long, lengths)
    sizes = np.zeros(len(lengths), np.int64)
    (a, sizes[long]), (b, sizes[~long]) = merge_linked(symbols[mine], lengths[long], table), merge_all(symbols[~mine], lengths[~long], table)
    out = np.zeros(int(sizes.sum()), np.int32)
    mine = np.repeat(long, sizes)
    out[mine], out[~mine] = a, b
    return out, sizes


class SpanCache:
    """hash of a span -> ragged values, in sorted arrays; holds at most ``limit`` spans, later ones are worked out anew."""

    def __init__(self, limit: int = 400_000) -> None:
        self.limit = limit
        self.keys = np.zeros(0, np.uint64)
        self.at = np.zeros(0, np.int64)
        self.size = np.zeros(0, np.int32)
        self.pool = np.zeros(0, np.int32)

    def get(self, keys: np.ndarray, work) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """``keys`` sorted and distinct; ``work(indices)`` gives (values, sizes) of unknown ones. Returns (pool, at, size)."""
        i = np.minimum(np.searchsorted(self.keys, keys), max(0, len(self.keys) - 1))
        known = self.keys[i] == keys if len(self.keys) else np.zeros(len(keys), bool)
        at, size = np.zeros(len(keys), np.int64), np.zeros(len(keys), np.int32)
        at[known], size[known] = self.at[i[known]], self.size[i[known]]
        new = np.flatnonzero(~known)
        if not len(new):
            return self.pool, at, size
        values, sizes = work(new)
        at[new] = len(self.pool) + np.concatenate([[0], np.cumsum(sizes)[:-1]])
        size[new] = sizes
        pool = np.concatenate([self.pool, values.astype(np.int32)])
        if len(self.keys) + len(new) <= self.limit:
            self.pool = pool
            merged = np.concatenate([self.keys, keys[new]])
            order = np.argsort(merged, kind="stable")
            self.keys, self.at, self.size = merged[order], np.concatenate([self.at, at[new]])[order], np.concatenate([self.size, size[new]])[order]
        return pool, at, size


def spread(pool: np.ndarray, at: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The concatenation of ``pool[at[i]:at[i]+size[i]]``."""
    total = int(size.sum())
    if not total:
        return np.zeros(0, pool.dtype)
    ends = np.cumsum(size, dtype=np.int64)
    return pool[np.arange(total) + np.repeat(at - (ends - size), size)]


class PieceCounter:
    """Token counts as the sentencepiece library gives them for a BPE model with byte fallback, a dummy prefix and identity normalisation."""

    def __init__(self, path: str) -> None:
        import sentencepiece
        from sentencepiece import sentencepiece_model_pb2

        self.library = sentencepiece.SentencePieceProcessor(model_file=path)
        model = sentencepiece_model_pb2.ModelProto()
        with open(path, "rb") as f:
            model.ParseFromString(f.read())
        spec = model.normalizer_spec
        pieces = {p.piece: (i, -p.score) for i, p in enumerate(model.pieces) if p.type in (1, 4, 5)}
        self.plain = (
            model.trainer_spec.model_type == 2 and model.trainer_spec.byte_fallback and spec.add_dummy_prefix and spec.escape_whitespaces
            and not spec.remove_extra_whitespaces and not spec.precompiled_charsmap and all(p.type in (1, 2, 3, 6) for p in model.pieces)
            and not any("▁" in p.lstrip("▁") or "\n" in p for p in pieces)
        )
        ranks = {s: r for r, s in enumerate(sorted({s for _, s in pieces.values()}))}
        rows = [(pieces[p[:k]][0], pieces[p[k:]][0], ranks[s], i) for p, (i, s) in pieces.items() for k in range(1, len(p)) if p[:k] in pieces and p[k:] in pieces]
        self.table = PairTable(*np.array(rows, np.int64).reshape(-1, 4).T)
        chars = {ord(p): i for p, (i, _) in pieces.items() if len(p) == 1}
        self.char = np.full(0x110000, -1, np.int32)
        self.char[list(chars)] = list(chars.values())
        self.char[0x20] = self.char[0x2581]
        self.cache = SpanCache()

    def _sizes(self, spans: list[bytes]) -> np.ndarray:
        texts = [s.decode() for s in spans]
        lengths = np.array([len(t) for t in texts], np.int64)
        code = np.frombuffer("".join(texts).encode("utf-32-le"), np.uint32)
        ids = self.char[code]
        # a character that is no piece gives a token for each of its bytes
        odd = np.where(ids < 0, 1 + (code > 0x7F).astype(np.int64) + (code > 0x7FF) + (code > 0xFFFF) - 1, 0)
        _, sizes = merge(ids, lengths, self.table)
        if odd.any():
            sizes = sizes + np.bincount(np.repeat(np.arange(len(texts)), lengths), odd, len(texts)).astype(np.int64)
        return sizes

    def count(self, first: int, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Tokens of each text of a slice."""
        n = len(offsets) - 1
        if not self.plain:
            return np.array([len(x) for x in self.library.encode([data[offsets[i] : offsets[i + 1]].tobytes().decode() for i in range(n)], num_threads=1)], np.int64)
        filled = np.flatnonzero(np.diff(offsets))
        if not len(filled):
            return np.zeros(n, np.int64)
        # every text that is not empty gets the dummy prefix, here as a space
        data = np.insert(data, offsets[filled], 0x20)
        begin_doc = offsets[filled] + np.arange(len(filled))
        space, line = data == 0x20, data == 0x0A
        begin = np.zeros(len(data), bool)
        begin[1:] = (space[1:] & ~space[:-1]) | line[1:] | line[:-1]
        # the piece mark itself, in a text, is the same letter as a space
        mark = np.flatnonzero(data == 0xE2)
        if len(mark):
            padded = np.concatenate([data, [0, 0]])
            mark = mark[(padded[mark + 1] == 0x96) & (padded[mark + 2] == 0x81)]
            begin[mark] |= ~space[mark - 1]
            after = mark[mark + 3 < len(data)] + 3
            begin[after[space[after]]] = False
            begin[np.intersect1d(mark, mark + 3)] = False
        begin[begin_doc] = True
        start = np.flatnonzero(begin)
        end = np.append(start[1:], len(data))
        keys, back = np.unique(hash_spans(data, start, end), return_inverse=True)
        some = np.zeros(len(keys), np.int64)
        some[back] = np.arange(len(back))
        sizes = lambda new: (self._sizes([data[start[i] : end[i]].tobytes() for i in some[new]]), np.ones(len(new), np.int32))
        pool, at, _ = self.cache.get(keys, sizes)
        out = np.zeros(n, np.int64)
        out[filled] = np.add.reduceat(pool[at][back], np.searchsorted(start, begin_doc))
        return out


class WordEncoder:
    """Ids of a word-level BPE of the tokenizers library (lower case, white space dropped, word ends marked).

    Texts are cut at white space, which the library's own steps never cross. Spans of ASCII and two-byte Latin letters are merged here;
    any other span (other scripts, quotes, special strings, control bytes) is encoded by the library itself.
    """

    def __init__(self, path: str) -> None:
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.library = Tokenizer.from_file(path)
        self.library.no_padding()
        self.library.no_truncation()
        vocab, suffix = spec["model"]["vocab"], spec["model"]["end_of_word_suffix"]
        rows = []
        for rank, pair in enumerate(spec["model"]["merges"]):
            a, b = pair.split(" ") if isinstance(pair, str) else pair
            rows.append((vocab[a], vocab[b], rank, vocab[a + b]))
        self.table = PairTable(*np.array(rows, np.int64).T)
        # byte-level letters: printable bytes stand for themselves, the others for code points from 256 on
        shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
        hidden = iter(range(256, 512))
        letter = {b: chr(b) if b in shown else chr(next(hidden)) for b in range(256)}
        self.inner = np.array([vocab[letter[b]] for b in range(256)], np.int32)
        self.last = np.array([vocab[letter[b] + suffix] for b in range(256)], np.int32)
        #: 0 not merged here, 1 letter, 2 digit, 3 other sign, 4 lead byte of a Latin letter, 5 a following byte
        self.kind = np.zeros(256, np.uint8)
        self.kind[33:127] = 3
        self.kind[[*range(65, 91), *range(97, 123)]] = 1
        self.kind[48:58] = 2
        self.kind[0xC3] = 4
        self.kind[0x80:0xC0] = 5
        self.kind[ord("'")] = 0
        self.fold = np.arange(256, dtype=np.uint8)
        self.fold[65:91] += 32
        self.cache = SpanCache()

    def _encode(self, data: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        length = end - start
        flat = data[np.arange(int(length.sum())) + np.repeat(start - (np.cumsum(length) - length), length)]
        owner = np.repeat(np.arange(len(start)), length)
        first = np.concatenate([[0], np.cumsum(length)[:-1]])
        kind = self.kind[flat]
        before = np.concatenate([[0], kind[:-1]])
        before[first] = 0
        after = np.concatenate([kind[1:], [0]])
        after[first + length - 1] = 0
        wrong = (kind == 0) | ((kind == 4) & (after != 5)) | ((kind == 5) & (before != 4))
        low = np.concatenate([flat[1:], np.zeros(1, np.uint8)])
        wrong |= (kind == 4) & ((low == 0x97) | (low == 0xB7))  # the signs for times and divided by
        wrong |= (flat == ord("<")) & (low == ord("|"))
        plain = np.bincount(owner, wrong, len(start)) == 0
        out: list[np.ndarray] = [np.zeros(0, np.int32)] * 2
        odd = np.flatnonzero(~plain)
        texts = [data[start[i] : end[i]].tobytes().decode() for i in odd]
        ids = [x.ids for x in self.library.encode_batch(texts, add_special_tokens=False)] if texts else []
        keep = plain[owner]
        flat, owner, kind, before = flat[keep], owner[keep], kind[keep], before[keep]
        lower = self.fold[flat]
        upper = (kind == 5) & (flat < 0x9F)
        lower[upper] += 32
        cls = np.where(kind >= 4, 1, kind)
        new = np.ones(len(flat), bool)
        new[1:] = (owner[1:] != owner[:-1]) | (cls[1:] != cls[:-1]) | (cls[1:] == 2)
        at = np.flatnonzero(new)
        final = np.zeros(len(flat), bool)
        final[np.append(at[1:], len(flat))[: len(at)] - 1] = True
        symbols = np.where(final, self.last[lower], self.inner[lower])
        sym, sizes = merge(symbols, np.diff(np.append(at, len(flat))), self.table)
        per = np.bincount(owner[at], sizes, len(start)).astype(np.int64) if len(at) else np.zeros(len(start), np.int64)
        if not ids:
            return sym, per
        for i, x in zip(odd, ids, strict=True):
            per[i] = len(x)
        out = np.zeros(int(per.sum()), np.int32)
        mine = np.repeat(plain, per)
        out[mine] = sym
        out[~mine] = np.array([y for x in ids for y in x], np.int32)
        return out, per

    def encode(self, data: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all spans one after another, ids in each span)."""
        if not len(start):
            return np.zeros(0, np.int32), np.zeros(0, np.int32)
        keys, back = np.unique(hash_spans(data, start, end), return_inverse=True)
        some = np.zeros(len(keys), np.int64)
        some[back] = np.arange(len(back))
        pool, at, size = self.cache.get(keys, lambda new: self._encode(data, start[some[new]], end[some[new]]))
        return spread(pool, at[back], size[back]), size[back]


@lru_cache(maxsize=4)
def piece_counter(path: str) -> PieceCounter:
    return PieceCounter(path)


@lru_cache(maxsize=4)
def word_encoder(path: str) -> WordEncoder:
    return WordEncoder(path)
