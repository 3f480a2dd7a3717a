"""Which occurrences of a longest repeat are replaced, and as what.

Kinds: 1 overlaps the leftmost copy and is the second one; 2 the only one to take after that; 3 one of several; 4 not taken.
"""

from __future__ import annotations

import zlib


def left_greedy(starts: list[int], length: int, after: int = -1) -> list[int]:
    """Disjoint starts beyond ``after``, taken from left to right; ``starts`` ascending."""
    out, free = [], after + 1
    for s in starts:
        if s >= free:
            out.append(s)
            free = s + length
    return out


def end_bound(starts: list[int], length: int) -> tuple[int | None, int]:
    """(the kind-1 start or None, last cell of what stays beside it); ``starts`` ascending."""
    first = starts[0]
    if len(starts) > 1 and first + length > starts[1]:
        return starts[1], starts[1] + length - 1
    return None, first + length - 1


def pick(starts: list[int], length: int) -> list[tuple[int, int]]:
    """(start, kind) of the replaced occurrences in text order; ``starts`` ascending."""
    one, bound = end_bound(starts, length)
    rest = left_greedy(starts, length, bound)
    out = [] if one is None else [(one, 1)]
    return out + [(s, 2 if len(rest) == 1 else 3) for s in rest]


def pick_simple(starts: list[int], length: int, order: str = "ends_first") -> list[tuple[int, int]]:
    """As ``pick`` with any maximal disjoint set as kind 3, in no sorted order; ``ends_first`` keeps at least half of what ``pick`` takes."""
    first = min(starts)
    second = min((s for s in starts if s != first), default=None)
    one = second if second is not None and first + length > second else None
    bound = (first if one is None else one) + length - 1
    rest = [s for s in starts if s > bound]
    out = [] if one is None else [(one, 1)]
    if not rest:
        return out
    low, high = min(rest), max(rest)
    if low + length > high:
        return [*out, (low, 2)]
    if order == "hash":
        rest = sorted(rest, key=lambda s: zlib.crc32(s.to_bytes(8, "little")))
    elif order == "ends_first":
        rest = [low, high, *rest]
    taken: set[int] = set()  # cells of chosen copies, one in `length`: a copy is met at its first or last cell's block
    chosen = []
    blocks: dict[int, int] = {}
    for s in rest:
        if s in taken:
            continue
        a, b = s // length, (s + length - 1) // length
        if any(abs(blocks[k] - s) < length for k in {a - 1, a, b} if k in blocks):
            continue
        blocks[a] = s
        taken.add(s)
        chosen.append(s)
    kind = 3 if len(chosen) > 1 else 2
    return out + sorted((s, kind) for s in chosen)


def classify(starts: list[int], length: int, mode: str = "greedy") -> list[tuple[int, int]]:
    """(start, kind) of every occurrence but the leftmost, which has kind 0."""
    kinds = dict(pick(sorted(starts), length) if mode == "greedy" else pick_simple(starts, length))
    first = min(starts)
    return [(s, 0 if s == first else kinds.get(s, 4)) for s in sorted(starts)]
