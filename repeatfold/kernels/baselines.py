"""Baselines: LZ77, pair grammar, longest-first grammar, with their decoders."""

from __future__ import annotations

import heapq
from collections import Counter

from repeatfold.kernels.reach import steps_of
from repeatfold.kernels.suffix import order_of


def lz77(codes: list[int], sa: list[int], lcp: list[int]) -> list[tuple[int, int, int]]:
    """Self-referencing factors (source, length, literal); a literal has length 1 and source -1, other factors literal -1. 0-based sources.

    The longest earlier match of a position is at its nearest neighbour in suffix order with a smaller position, found by deleting
    positions from the last to the first.
    """
    n = len(codes)
    rank = [0] * n
    for r, p in enumerate(sa):
        rank[p] = r
    up, down = [r - 1 for r in range(n)], [r + 1 for r in range(n)]
    h = [*lcp, 0]
    best, source = [0] * n, [-1] * n
    for p in range(n - 1, -1, -1):
        r = rank[p]
        a, b = h[r], h[down[r]] if down[r] <= n else 0
        if a and a >= b:
            best[p], source[p] = a, sa[up[r]]
        elif b:
            best[p], source[p] = b, sa[down[r]]
        h[down[r]] = min(a, b)
        if up[r] >= 0:
            down[up[r]] = down[r]
        if down[r] < n:
            up[down[r]] = up[r]
    out, p = [], 0
    while p < n:
        if best[p]:
            out.append((source[p], best[p], -1))
            p += best[p]
        else:
            out.append((-1, 1, codes[p]))
            p += 1
    return out


def lz77_apart(codes: list[int]) -> list[tuple[int, int, int]]:
    """Factors whose source ends before the factor begins; the leftmost longest source."""
    text = "".join(map(chr, _dense(codes)))
    n, out, p = len(codes), [], 0
    while p < n:
        good, bad = 0, min(p, n - p) + 1
        step = 1
        while good + 1 < bad:  # gallop, then close in
            step = min(step, bad - good - 1)
            if text.find(text[p : p + good + step], 0, p) >= 0:
                good += step
                step *= 2
            else:
                bad = good + step
                step = 1
        out.append((text.find(text[p : p + good], 0, p), good, -1) if good else (-1, 1, codes[p]))
        p += max(1, good)
    return out


def _dense(codes: list[int]) -> list[int]:
    """Codes as code points that a string can hold."""
    name: dict[int, int] = {}
    return [(k := name.setdefault(c, len(name))) + (0x800 if k >= 0xD800 else 0) for c in codes]


def lz77_decode(factors: list[tuple[int, int, int]]) -> list[int]:
    out: list[int] = []
    for src, length, literal in factors:
        if src < 0:
            out.append(literal)
        elif len(out) - src >= length:
            out += out[src : src + length]
        else:
            unit = out[src:]
            out += (unit * (length // len(unit) + 1))[:length]
    return out


def disjoint_pairs(codes: list[int]) -> Counter:
    """Disjoint copies of each neighbouring pair, taken from left to right."""
    count: Counter = Counter()
    last: dict[tuple[int, int], int] = {}
    for i in range(len(codes) - 1):
        pair = (codes[i], codes[i + 1])
        if pair[0] == pair[1] and last.get(pair) == i - 1:
            last.pop(pair)
            continue
        last[pair] = i
        count[pair] += 1
    return count


def pair_grammar(codes: list[int]) -> tuple[dict[int, list[int]], list[int]]:
    """The most frequent pair with two disjoint copies becomes a rule, until none is left; the pair that stands first wins a tie.

    Cells are linked, each pair knows its places, and a heap with stale entries gives the most frequent one. Rules are named -10, -11, …
    """
    n = len(codes)
    sym: list[int | None] = list(codes)
    nxt, prev = list(range(1, n + 1)), list(range(-1, n - 1))
    places: dict[tuple[int, int], set[int]] = {}
    for i in range(n - 1):
        places.setdefault((codes[i], codes[i + 1]), set()).add(i)

    def chosen(pair: tuple[int, int]) -> list[int]:
        """Disjoint copies from left to right."""
        at = sorted(places.get(pair, ()))
        if pair[0] != pair[1]:
            return at
        out, taken = [], -1
        for i in at:
            if i != taken:
                out.append(i)
                taken = nxt[i]
        return out

    heap = [(-len(c), c[0], p) for p in places if len(c := chosen(p)) > 1]
    heapq.heapify(heap)
    rules: dict[int, list[int]] = {}
    while heap:
        k, first, pair = heapq.heappop(heap)
        at = chosen(pair)
        if len(at) < 2:
            continue
        if (-len(at), at[0]) != (k, first):
            heapq.heappush(heap, (-len(at), at[0], pair))
            continue
        name = -10 - len(rules)
        rules[name] = list(pair)
        touched = set()
        for i in at:
            j = nxt[i]
            if sym[i] != pair[0] or j >= n or sym[j] != pair[1]:
                continue
            left, right = prev[i], nxt[j]
            for a in (left, i, j):
                if a >= 0 and nxt[a] < n and sym[nxt[a]] is not None:
                    places.get((sym[a], sym[nxt[a]]), set()).discard(a)
            sym[i], sym[j] = name, None
            nxt[i] = right
            if right < n:
                prev[right] = i
            for a in (left, i):
                if a >= 0 and nxt[a] < n:
                    new = (sym[a], sym[nxt[a]])
                    places.setdefault(new, set()).add(a)
                    touched.add(new)
        places.pop(pair, None)
        for new in touched:
            if len(c := chosen(new)) > 1:
                heapq.heappush(heap, (-len(c), c[0], new))
    return rules, [s for s in sym if s is not None]


def longest_grammar(codes: list[int], sa: list[int], lcp: list[int]) -> tuple[dict[int, list[int]], list[int]]:
    """The longest string with two disjoint copies becomes a rule and all its chosen copies go, until none is left; bodies stay as they are."""
    rules: dict[int, list[int]] = {}
    name_at: dict[int, tuple[int, int]] = {}
    for step in steps_of(len(codes), sa, lcp, mode="grammar"):
        name = -10 - len(rules)
        rules[name] = codes[step.first : step.first + step.len]
        for p, _ in step.picks:
            name_at[p] = (name, step.len)
    start, p = [], 0
    while p < len(codes):
        name, length = name_at.get(p, (codes[p], 1))
        start.append(name)
        p += length
    return rules, start


def longest_grammar_bodies(codes: list[int], sa: list[int], lcp: list[int]) -> tuple[dict[int, list[int]], list[int]]:
    """As ``longest_grammar`` with rule bodies searched too: until neither the start sequence nor a body has a string that stands disjointly elsewhere.

    Start and bodies lie one after another with separators of their own, and the search goes over all of them, round by round.
    """
    rules, start = longest_grammar(codes, sa, lcp)
    while True:
        names = list(rules)
        line, low = [], min(rules, default=-9) - 1
        for k, part in enumerate([start, *(rules[x] for x in names)]):
            line += [*part, -(1 << 40) - k]
        dense = {c: k for k, c in enumerate(sorted(set(line)))}
        more, left = longest_grammar([dense[c] for c in line], *order_of([dense[c] for c in line]))
        if not more:
            return rules, start
        back = {k: c for c, k in dense.items()} | {-10 - k: low - k for k in range(len(more))}
        fresh = {back[name]: [back[c] for c in body] for name, body in more.items()}
        parts, part = [], []
        for c in (back[c] for c in left):
            if c <= -(1 << 40):
                parts.append(part)
                part = []
            else:
                part.append(c)
        rules = dict(zip(names, parts[1:], strict=True)) | fresh
        # a body that was replaced as a whole is another rule's: that one stands in for it
        same = {x: body[0] for x, body in rules.items() if len(body) == 1}
        rules = {x: [same.get(c, c) for c in body] for x, body in rules.items() if x not in same}
        start = [same.get(c, c) for c in parts[0]]


def expand(rules: dict[int, list[int]], start: list[int]) -> list[int]:
    """The only word of a grammar."""
    out, todo = [], list(reversed(start))
    while todo:
        s = todo.pop()
        if s in rules:
            todo += reversed(rules[s])
        else:
            out.append(s)
    return out
