"""State of a fold, its step log, and the output triple."""

from __future__ import annotations

from dataclasses import dataclass, field

MARK, END = -2, -1


@dataclass
class Step:
    """One replaced (or refused) repeat."""

    k: int
    len: int
    first: int
    starts: list[int]
    picks: list[tuple[int, int]]
    s: int = 0
    accepted: bool = True
    edges: int = 0
    nodes_new: int = 0
    bucket_ops: int = 0
    select_work: int = 0


@dataclass
class Folded:
    """``residual`` (marks are MARK), ``factors`` (a, len) with 1-based positions, ``kinds``, the steps, and the most cells of working arrays held."""

    n: int
    residual: list[int] = field(default_factory=list)
    factors: list[tuple[int, int]] = field(default_factory=list)
    kinds: list[int] = field(default_factory=list)
    steps: list[Step] = field(default_factory=list)
    cells: int = 0


def triple(codes: list[int], steps: list[Step], terminator: bool = False) -> Folded:
    """Residual, factors in text order and kinds from the accepted steps."""
    n = len(codes)
    at: dict[int, tuple[int, int, int]] = {}  # pick -> (kind code, first, length)
    group = 0
    lead: set[int] = set()
    for step in steps:
        if not step.accepted:
            continue
        threes = [p for p, kind in step.picks if kind == 3]
        if threes:
            group += 1
            lead.add(min(threes))
        for p, kind in step.picks:
            at[p] = (2 + group if kind == 3 else kind, step.first, step.len)
    out = Folded(n, steps=steps)
    p = 0
    while p < n:
        hit = at.get(p)
        if hit is None:
            out.residual.append(codes[p])
            p += 1
            continue
        code, first, length = hit
        out.residual.append(MARK)
        out.kinds.append(code)
        if code == 1:
            out.factors.append((p - first, length))
        elif code == 2 or p in lead:
            out.factors.append((first + 1, length))
        p += length
    if terminator:
        out.residual.append(END)
    return out


def unfold(residual: list[int], factors: list[tuple[int, int]], kinds: list[int]) -> list[int]:
    """The codes behind a triple, from left to right; a terminator is dropped."""
    out: list[int] = []
    known: dict[int, tuple[int, int]] = {}
    take, kind = iter(factors), iter(kinds)
    for c in residual:
        if c == END:
            continue
        if c != MARK:
            out.append(c)
            continue
        k = next(kind)
        if k <= 2:
            a, length = next(take)
            src = len(out) - a if k == 1 else a - 1
        else:
            if k not in known:
                known[k] = next(take)
            a, length = known[k]
            src = a - 1
        gap = len(out) - src
        if gap >= length:
            out += out[src : src + length]
        else:  # the copy overlaps itself
            unit = out[src:]
            out += (unit * (length // gap + 1))[:length]
    return out
