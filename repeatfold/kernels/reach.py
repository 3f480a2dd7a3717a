"""Fold on a static suffix order: no tree is edited.

``reach[p]`` is the number of live cells from p to the end of its live run; a longest repeat of the current string is a stretch of live
cells of the original, so the live common prefix of p and q is min(lcp, reach[p], reach[q]). Lengths go down from the longest common prefix;
at each length neighbouring ranks with that common prefix are united and positions whose reach allows that length wake up. A class with two
awake positions is a longest repeat. After it is replaced at most one of its positions stays awake, so the work is linear beside the sorts.
"""

from __future__ import annotations

import heapq

from repeatfold.kernels.assemble import Folded, Step, triple
from repeatfold.kernels.typing import left_greedy, pick, pick_simple


def steps_of(n: int, sa: list[int], lcp: list[int], tie: str = "leftmost", min_len: int = 2, max_steps: int | None = None, mode: str = "greedy", order: str = "ends_first", meter: dict | None = None) -> list[Step]:
    """``mode``: greedy, simple, or grammar (two disjoint copies are needed and every chosen copy goes, the first one too).

    ``meter`` gets ``cells``, the most entries held at once; a step's ``select_work`` is what was touched since the one before.
    """
    meter = {} if meter is None else meter
    meter["cells"], work, waiting = 0, 0, 0
    top = max(lcp, default=0)
    if top < min_len or n < 2:
        return []
    grammar = mode == "grammar"
    rank = [0] * n
    for r, p in enumerate(sa):
        rank[p] = r
    reach = list(range(n, 0, -1))
    most = [max(lcp[r], lcp[r + 1] if r + 1 < n else 0) for r in range(n)]  # by rank
    unions: dict[int, list[int]] = {}
    for r in range(1, n):
        if lcp[r] >= min_len:
            unions.setdefault(lcp[r], []).append(r)
    wakes: dict[int, list[int]] = {}
    for p in range(n):
        w = min(reach[p], most[rank[p]])
        if w >= min_len:
            wakes.setdefault(w, []).append(p)
            waiting += 1
    joined = sum(map(len, unions.values()))
    meter["cells"] = 6 * n + waiting + joined
    again: dict[int, list[int]] = {}  # grammar: classes whose copies are apart at that length only
    root = list(range(n))
    awake: list[dict[int, None] | None] = [None] * n  # in the order of waking

    def find(r: int) -> int:
        while root[r] != r:
            root[r] = root[root[r]]
            r = root[r]
        return r

    steps: list[Step] = []
    for length in range(top, min_len - 1, -1):
        touched = set()
        work += len(unions.get(length, ())) + len(wakes.get(length, ()))
        waiting -= len(wakes.get(length, ()))
        for r in unions.pop(length, ()):
            a, b = find(r - 1), find(r)
            if a != b:
                # the smaller rank stays the root: it names the class's string
                if a > b:
                    a, b = b, a
                root[b] = a
                x, y = awake[a], awake[b]
                if x is None:
                    awake[a] = y
                elif y is not None:
                    if len(x) < len(y):
                        x, y = y, x
                    x |= y  # the shorter one behind
                    awake[a] = x
                awake[b] = None
            touched.add(a)
        for p in wakes.pop(length, ()):
            if reach[p] >= length:
                a = find(rank[p])
                if awake[a] is None:
                    awake[a] = {p: None}
                else:
                    awake[a][p] = None
                touched.add(a)
        for a in again.pop(length, ()):
            touched.add(find(a))
        heap = []
        for a in touched:
            a = find(a)
            group = awake[a]
            if group is None or len(group) < 2:
                continue
            live = {p: None for p in group if reach[p] >= length}
            work += len(group)
            awake[a] = live
            if len(live) > 1:
                heap.append((min(live) if tie == "leftmost" else a, a))
        heap = list(set(heap))
        heapq.heapify(heap)
        while heap:
            if max_steps is not None and len(steps) >= max_steps:
                return steps
            key, a = heapq.heappop(heap)
            live = {p: None for p in awake[a] if reach[p] >= length}
            work += len(awake[a]) + 1
            awake[a] = live
            if len(live) < 2:
                continue
            if tie == "leftmost" and (low := min(live)) != key:
                heapq.heappush(heap, (low, a))
                continue
            if grammar:
                starts = sorted(live)
                chosen = left_greedy(starts, length)
                if len(chosen) < 2:
                    if (gap := starts[-1] - starts[0]) >= min_len:
                        again.setdefault(gap, []).append(a)
                    continue
                picks = [(p, 3) for p in chosen]
                first = starts[0]
            elif mode == "simple":
                starts = list(live)
                picks = pick_simple(starts, length, order)
                first = min(starts)
            else:
                starts = sorted(live)
                picks = pick(starts, length)
                first = starts[0]
            steps.append(Step(len(steps) + 1, length, first, starts, picks, s=sum(k > 1 for _, k in picks), select_work=work))
            work = 2 * length * len(picks)
            for i, _ in picks:
                for p in range(i, i + length):
                    reach[p] = 0
                p, room = i - 1, 1
                while room < length and p >= 0 and reach[p] > 0:
                    if reach[p] > room:
                        reach[p] = room
                        if room >= min_len and most[rank[p]] > room:
                            wakes.setdefault(room, []).append(p)
                            waiting += 1
                        elif room >= min_len:
                            # sleeps or is awake for its common prefix, which the reach still allows
                            if most[rank[p]] == room:
                                wakes.setdefault(room, []).append(p)
                                waiting += 1
                    p -= 1
                    room += 1
            meter["cells"] = max(meter["cells"], 6 * n + waiting + joined)
            awake[a] = {p: None for p in awake[a] if reach[p] >= length}
            if grammar and len(awake[a]) > 1:
                heapq.heappush(heap, (min(awake[a]) if tie == "leftmost" else a, a))
    return steps


def run(codes: list[int], sa: list[int], lcp: list[int], terminator: bool = False, **options) -> Folded:
    meter: dict[str, int] = {}
    out = triple(codes, steps_of(len(codes), sa, lcp, meter=meter, **options), terminator)
    out.cells = meter["cells"]
    return out
