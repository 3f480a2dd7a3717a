"""Gated fold: maximal repeats of the input, longest first, each replaced only if its length passes a test of its number of copies."""

from __future__ import annotations

from repeatfold.kernels.assemble import Folded, Step, triple
from repeatfold.kernels.suffix import maximal_repeats
from repeatfold.kernels.typing import pick


def gate(length: int, s: int, alpha: float, beta: float, type1: str = "never") -> bool:
    """length >= alpha / s + beta; without a copy of kind 2 or 3 false (unless ``alpha`` is 0 or ``type1`` is "always")."""
    if s == 0:
        return type1 == "always" or (alpha == 0 and length >= beta)
    return length >= alpha / s + beta


def run(codes: list[int], sa: list[int], lcp: list[int], alpha: float = 30, beta: float = 80, gate_type1: str = "never", rescan: bool = False, terminator: bool = False) -> Folded:
    n = len(codes)
    reach = list(range(n, 0, -1))
    steps: list[Step] = []
    todo = [(p, lo, hi) for p, lo, hi in maximal_repeats(codes, sa, lcp) if p >= 2]
    cells = 2 * n + 3 * len(todo)
    todo.sort(key=lambda x: (-x[0], min(sa[x[1] : x[2] + 1])))
    while todo:
        refused = []
        changed = False
        for p, lo, hi in todo:
            starts = sorted(q for q in sa[lo : hi + 1] if reach[q] >= p)
            if len(starts) < 2:
                continue
            picks = pick(starts, p)
            s = sum(k > 1 for _, k in picks)
            ok = gate(p, s, alpha, beta, gate_type1)
            steps.append(Step(len(steps) + 1, p, starts[0], starts, picks, s, ok))
            if not ok:
                refused.append((p, lo, hi))
                continue
            changed = True
            for i, _ in picks:
                for q in range(i, i + p):
                    reach[q] = 0
                q, room = i - 1, 1
                while q >= 0 and 0 < reach[q] and reach[q] > room:
                    reach[q] = room
                    q -= 1
                    room += 1
        todo = refused if rescan and changed else []
    out = triple(codes, steps, terminator)
    out.cells = cells
    return out
