"""The scheme by its definition: every step searches the current string anew. For short units and as the other engines' yardstick."""

from __future__ import annotations

from collections import defaultdict

from repeatfold.kernels.assemble import Folded, Step, triple
from repeatfold.kernels.typing import pick, pick_simple


def _classes(codes: list[int], alive: list[bool], length: int) -> dict[tuple[int, ...], list[int]]:
    out: dict[tuple[int, ...], list[int]] = defaultdict(list)
    run = 0
    for p in range(len(codes)):
        run = run + 1 if alive[p] else 0
        if run >= length:
            out[tuple(codes[p - length + 1 : p + 1])].append(p - length + 1)
    return {x: s for x, s in out.items() if len(s) > 1}


def run(codes: list[int], tie: str = "leftmost", min_len: int = 2, max_steps: int | None = None, mode: str = "greedy", order: str = "ends_first", terminator: bool = False) -> Folded:
    n = len(codes)
    alive, steps = [True] * n, []
    length = n - 1
    while length >= min_len and (max_steps is None or len(steps) < max_steps):
        found = _classes(codes, alive, length)
        if not found:
            length -= 1
            continue
        x = min(found, key=(lambda w: found[w][0]) if tie == "leftmost" else (lambda w: w))
        starts = found[x]
        picks = pick(starts, length) if mode == "greedy" else pick_simple(starts, length, order)
        steps.append(Step(len(steps) + 1, length, starts[0], starts, picks, s=sum(k > 1 for _, k in picks)))
        for p, _ in picks:
            alive[p : p + length] = [False] * length
    return triple(codes, steps, terminator)
