"""Suffix order and common prefixes of many units at once, by prefix doubling on numpy arrays.

Units lie one after another in one array; ranks never mix units, so one sort serves a whole batch. Only positions whose rank is still
shared are sorted again, and the ranks of every level are kept: they answer common-prefix questions for any two positions of a unit.
"""

from __future__ import annotations

import numpy as np


class Order:
    """Suffix order of units ``codes[starts[u]:starts[u+1]]``."""

    def __init__(self, codes: np.ndarray, starts: np.ndarray) -> None:
        n = len(codes)
        self.starts, self.n = starts, n
        unit = np.repeat(np.arange(len(starts) - 1), np.diff(starts))
        end = starts[1:][unit] if n else unit
        self.end = end
        _, rank = np.unique(np.stack([unit, codes.astype(np.int64)], 1), axis=0, return_inverse=True) if n else (None, np.zeros(0, np.int64))
        rank = rank.reshape(-1).astype(np.int64)
        # ranks are places in the sorted order, so refining a group leaves the others alone
        order = np.argsort(rank, kind="stable")
        rank = self._places(rank, order)
        self.levels = [rank]
        width = 1
        while n:
            count = np.bincount(rank, minlength=n)
            shared = np.flatnonzero(count[rank] > 1)
            if not len(shared):
                break
            nxt = shared + width
            key = np.where(nxt < end[shared], rank[np.minimum(nxt, n - 1)] + 1, 0)
            sub = np.lexsort((key, rank[shared]))
            ids = shared[sub]
            r, k = rank[ids], key[sub]
            group = np.concatenate([[True], r[1:] != r[:-1]])
            fresh = group | np.concatenate([[True], k[1:] != k[:-1]])
            at = np.arange(len(ids))
            first_group = np.maximum.accumulate(np.where(group, at, 0))
            first_fresh = np.maximum.accumulate(np.where(fresh, at, 0))
            rank = rank.copy()
            rank[ids] = r + first_fresh - first_group
            self.levels.append(rank)
            width *= 2
        self.rank = rank
        self.sa = np.empty(n, np.int64)
        self.sa[rank] = np.arange(n)

    @staticmethod
    def _places(rank: np.ndarray, order: np.ndarray) -> np.ndarray:
        """Each value replaced by the first place of its group in the order."""
        if not len(rank):
            return rank
        s = rank[order]
        first = np.maximum.accumulate(np.where(np.concatenate([[True], s[1:] != s[:-1]]), np.arange(len(s)), 0))
        out = np.empty_like(rank)
        out[order] = first
        return out

    def lce(self, p: np.ndarray, q: np.ndarray) -> np.ndarray:
        """Length of the common prefix of the suffixes at ``p`` and ``q`` (of one unit)."""
        p, q, got = p.copy(), q.copy(), np.zeros(len(p), np.int64)
        top = self.n - 1
        for t in range(len(self.levels) - 1, -1, -1):
            ok = (p < self.end[np.minimum(p, top)]) & (q < self.end[np.minimum(q, top)]) & (p <= top) & (q <= top)
            same = ok & (self.levels[t][np.minimum(p, top)] == self.levels[t][np.minimum(q, top)])
            step = same * (1 << t)
            p, q, got = p + step, q + step, got + step
        return got

    def lcp(self) -> np.ndarray:
        """``lcp[r]``: common prefix of the suffixes of ranks ``r-1`` and ``r``; 0 at a unit's first rank."""
        out = np.zeros(self.n, np.int64)
        if self.n > 1:
            a, b = self.sa[:-1], self.sa[1:]
            same = np.flatnonzero(self.end[a] == self.end[b])
            out[1 + same] = self.lce(a[same], b[same])
        return out

    def unit(self, u: int, lcp: np.ndarray) -> tuple[list[int], list[int]]:
        """Suffix order (0-based within the unit) and common prefixes of unit ``u``."""
        a, b = int(self.starts[u]), int(self.starts[u + 1])
        return (self.sa[a:b] - a).tolist(), lcp[a:b].tolist()


def order_of(codes) -> tuple[list[int], list[int]]:
    """Suffix order and common prefixes of one unit."""
    x = np.asarray(codes, np.int64)
    o = Order(x, np.array([0, len(x)]))
    return o.unit(0, o.lcp())


def intervals(sa: list[int], lcp: list[int]) -> list[tuple[int, int, int]]:
    """All ``(p, lo, hi)``: the longest common prefix of the suffixes of ranks lo…hi is p >= 1, and of no wider range."""
    out, stack = [], []  # (p, lo)
    for r in range(1, len(sa) + 1):
        p = lcp[r] if r < len(sa) else 0
        lo = r - 1
        while stack and stack[-1][0] > p:
            q, lo = stack.pop()
            out.append((q, lo, r - 1))
        if p and (not stack or stack[-1][0] < p):
            stack.append((p, lo))
    return out


def maximal_repeats(codes: list[int], sa: list[int], lcp: list[int]) -> list[tuple[int, int, int]]:
    """The intervals whose common prefix has two different letters before it; the text's start counts as a letter of its own."""
    before = [codes[p - 1] if p else None for p in sa]
    change = [0] * (len(sa) + 1)  # runs of equal letters before
    for r in range(1, len(sa)):
        change[r] = change[r - 1] + (before[r] != before[r - 1])
    return [(p, lo, hi) for p, lo, hi in intervals(sa, lcp) if change[hi] > change[lo]]
