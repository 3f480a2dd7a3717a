"""Fold on a suffix tree that is kept equal to the suffix tree of the current string.

Nodes are numbers in arrays; a child is found by the first symbol of its edge. Positions keep their places, a replaced copy is one mark
followed by dead cells. Inner nodes below the root's children never spell a mark, so their labels can be read from the original text.
"""

from __future__ import annotations

import heapq
from collections import OrderedDict

from repeatfold.kernels.assemble import END, Folded, Step, triple
from repeatfold.kernels.typing import pick, pick_simple

ROOT = 0


class Tree:
    """Suffix tree of ``codes`` and an end symbol, with suffix links and nodes listed by depth."""

    def __init__(self, codes: list[int], sa: list[int], lcp: list[int]) -> None:
        n = len(codes)
        self.n, self.text = n, [*codes, END]
        self.parent, self.depth, self.key = [-1], [0], [0]
        self.kids: list[dict[int, int] | None] = [{}]
        self.link, self.at, self.leaf_id = [ROOT], [0], [-1]
        self.leaf = [-1] * (n + 1)
        self.buckets: dict[int, OrderedDict[int, None]] = {}
        self.created: list[tuple[int, int]] = []
        self.edges = self.made = self.ops = 0
        self.waiting: list[int] = []
        sa, lcp = [n, *sa], [0, 0, *lcp[1:]]
        stack = [ROOT]
        for r, p in enumerate(sa):
            h = lcp[r]
            last = -1
            while self.depth[stack[-1]] > h:
                last = stack.pop()
            top = stack[-1]
            if self.depth[top] < h:
                # a new node between top and what was popped
                v = self._node(h, self.at[last])
                self._hang(v, top, self.text[self.at[last] + self.depth[top]])
                self._hang(last, v, self.text[self.at[last] + h])
                stack.append(v)
                top = v
            leaf = self._node(n + 1 - p, p, p)
            self.leaf[p] = leaf
            self._hang(leaf, top, self.text[p + self.depth[top]])
            stack.append(leaf)
        inner = [v for v in self._preorder() if self.kids[v] is not None and v != ROOT]
        for v in inner:
            if self.depth[v] >= 2:
                self.buckets.setdefault(self.depth[v], OrderedDict())[v] = None
        for v in sorted(inner, key=self.depth.__getitem__):
            self.link[v] = self._seek(ROOT if self.parent[v] == ROOT else self.link[self.parent[v]], self.at[v] + 1, self.depth[v] - 1)
        self.edges = self.ops = 0

    def _preorder(self) -> list[int]:
        out, todo = [], [ROOT]
        while todo:
            v = todo.pop()
            out.append(v)
            if self.kids[v]:
                todo += [self.kids[v][k] for k in sorted(self.kids[v], reverse=True)]
        return out

    def _node(self, depth: int, at: int, leaf_id: int = -1) -> int:
        self.parent.append(-1)
        self.depth.append(depth)
        self.key.append(0)
        self.kids.append(None if leaf_id >= 0 else {})
        self.link.append(ROOT)
        self.at.append(at)
        self.leaf_id.append(leaf_id)
        return len(self.parent) - 1

    def _hang(self, v: int, u: int, key: int) -> None:
        self.parent[v], self.key[v] = u, key
        self.kids[u][key] = v

    def _seek(self, u: int, at: int, depth: int) -> int:
        """The explicit node of the string ``text[at:at+depth]`` below ``u``, whose path it begins with."""
        while self.depth[u] < depth:
            u = self.kids[u][self.text[at + self.depth[u]]]
        return u

    def below(self, u: int, at: int, depth: int) -> int:
        """From ``u`` down the string ``text[at:at+depth]``, as deep as explicit nodes of at most that depth go; counts edges."""
        while self.depth[u] < depth:
            v = self.kids[u][self.text[at + self.depth[u]]]
            if self.depth[v] > depth or self.kids[v] is None:
                break
            u = v
            self.edges += 1
        return u

    def _drop(self, v: int) -> None:
        u = self.parent[v]
        del self.kids[u][self.key[v]]
        self.waiting.append(u)

    def _splice(self) -> None:
        """Nodes left with one child go, after the whole pick: until then suffix links may still pass through them."""
        while self.waiting:
            u = self.waiting.pop()
            if u == ROOT or self.kids[u] is None or len(self.kids[u]) > 1 or self.parent[u] < 0:
                continue
            p = self.parent[u]
            for c in self.kids[u].values():
                self._hang(c, p, self.key[u])
            if not self.kids[u]:
                del self.kids[p][self.key[u]]
                self.waiting.append(p)
            self.parent[u] = -1
            bucket = self.buckets.get(self.depth[u])
            if bucket is not None and u in bucket:
                del bucket[u]
                self.ops += 1

    def deepest(self, limit: int) -> int:
        """The greatest depth, ``limit`` at most, that has nodes; 0 if none has."""
        while limit >= 2 and not self.buckets.get(limit):
            limit -= 1
        return limit if limit >= 2 else 0

    def starts(self, v: int) -> list[int]:
        return [self.leaf_id[c] for c in self.kids[v].values()]

    def replace(self, i: int, length: int, mark: int, lo: int) -> None:
        """One copy at ``i``: its inner leaves go, the contexts in ``lo…i-1`` are edited, leaf ``i`` goes below the mark."""
        for p in range(i + 1, i + length):
            self._drop(self.leaf[p])
            self.leaf[p] = -1
        self.text[i] = mark
        j = i - lo
        u, fresh = ROOT, -1
        if j:
            u = self.below(ROOT, lo, j)
        while j:
            leaf = self.leaf[i - j]
            up = self.parent[leaf]
            here = u
            if self.depth[up] > j:
                if self.depth[u] < j:  # the context is inside an edge
                    c = self.kids[u][self.text[i - j + self.depth[u]]]
                    here = self._node(j, i - j)
                    first = self.key[c]
                    self._hang(here, u, first)
                    self._hang(c, here, self._inner_symbol(c, j))
                    if j >= 2:
                        self.buckets.setdefault(j, OrderedDict())[here] = None
                        self.created.append((j, here))
                        self.ops += 1
                    self.made += 1
                    if fresh >= 0:
                        self.link[fresh] = here
                    fresh = here
                elif fresh >= 0:
                    self.link[fresh] = here
                    fresh = -1
                up = self.parent[leaf]
                if up != here:
                    self._drop(leaf)
                    self._hang(leaf, here, mark)
                else:
                    del self.kids[here][self.key[leaf]]
                    self._hang(leaf, here, mark)
            else:
                if fresh >= 0 and self.depth[u] == j:
                    self.link[fresh] = u
                    fresh = -1
                if self.depth[up] == j:
                    del self.kids[up][self.key[leaf]]
                    self._hang(leaf, up, mark)
            j -= 1
            if j:
                u = self.below(self.link[u] if u != ROOT else ROOT, i - j, j)
        if fresh >= 0:
            self.link[fresh] = ROOT

    def _inner_symbol(self, c: int, depth: int) -> int:
        """First symbol of the edge to ``c`` if it began at ``depth``."""
        return self.text[self.at[c] + depth] if self.kids[c] is None else self.label[self.at[c] + depth]

    label: list[int]


class Front:
    """Nodes of the greatest depth in the order of a tie rule, chosen without looking through all of them.

    There all children are leaves and no node gets a leaf that was not below it before, so a node's least start only moves to the right: a heap
    holds each node once, and what it is sorted by is renewed from the node's own sorted starts when the node comes to the top.
    """

    def __init__(self, tree: Tree, tie: str, rank: list[int]) -> None:
        self.tree, self.tie, self.rank = tree, tie, rank
        self.depth, self.heap = 0, []
        self.left: dict[int, list[int]] = {}
        self.work = 0

    def _push(self, v: int) -> None:
        self.work += 1
        if self.tie == "lex":
            heapq.heappush(self.heap, (self.rank[self.tree.at[v]], v))
            return
        starts = sorted(self.tree.starts(v), reverse=True)
        self.work += len(starts)
        self.left[v] = starts
        heapq.heappush(self.heap, (starts[-1], v))

    def choose(self, depth: int) -> int:
        tree, nodes = self.tree, self.tree.buckets[depth]
        if self.tie == "bucket":
            self.work += 1
            tree.created.clear()
            return next(iter(nodes))
        if depth != self.depth:
            self.depth, self.heap, self.left = depth, [], {}
            for v in nodes:
                self._push(v)
        else:
            for j, v in tree.created:
                if j == depth and v in nodes:
                    self._push(v)
        tree.created.clear()
        while True:
            key, v = self.heap[0]
            self.work += 1
            if v not in nodes:
                heapq.heappop(self.heap)
                continue
            if self.tie == "lex":
                return v
            starts = self.left[v]
            while tree.leaf[starts[-1]] < 0 or tree.parent[tree.leaf[starts[-1]]] != v:
                starts.pop()
                self.work += 1
            if starts[-1] == key:
                return v
            heapq.heapreplace(self.heap, (starts[-1], v))


def run(codes: list[int], sa: list[int], lcp: list[int], tie: str = "leftmost", min_len: int = 2, max_steps: int | None = None, mode: str = "greedy", order: str = "ends_first", terminator: bool = False, check=None) -> Folded:
    """``tie``: leftmost, lex, or bucket (first in the list of the greatest depth). ``check(tree, alive)`` is called after each step."""
    tree = Tree(codes, sa, lcp)
    tree.label = [*codes, END]
    steps, alive = [], [True] * len(codes)
    length = max(tree.buckets, default=0)
    rank = [0] * (len(codes) + 1)
    if tie == "lex":
        for r, p in enumerate(sa):
            rank[p] = r
    front, held = Front(tree, tie, rank), 0
    while max_steps is None or len(steps) < max_steps:
        length = tree.deepest(length)
        if length < max(2, min_len):
            break
        front.work = 0
        v = front.choose(length)
        tree.edges = tree.made = tree.ops = 0
        starts = tree.starts(v)
        if mode == "greedy":
            starts.sort()
            picks = pick(starts, length)
        else:
            picks = pick_simple(starts, length, order)
        step = Step(len(steps) + 1, length, min(starts), starts, picks, s=sum(k > 1 for _, k in picks))
        mark = -2 - step.k
        hung = None
        for i, _ in picks:
            lo = i
            while lo > 0 and i - lo < length and alive[lo - 1]:
                lo -= 1
            tree.replace(i, length, mark, lo)
            alive[i : i + length] = [False] * length
            leaf = tree.leaf[i]
            tree._drop(leaf)
            if hung is None:
                hung = leaf
                tree._hang(leaf, ROOT, mark)
            else:
                top = tree.kids[ROOT][mark]
                if tree.kids[top] is None:
                    other = top
                    top = tree._node(1, i)
                    tree._hang(top, ROOT, mark)
                    tree._hang(other, top, _after(tree, other, length))
                tree._hang(leaf, top, _after(tree, leaf, length))
            tree._splice()
        # a copy's follower may have been replaced since it was hung
        top = tree.kids[ROOT].get(mark)
        if top is not None and tree.kids[top] is not None:
            leaves = list(tree.kids[top].values())
            tree.kids[top] = {}
            for leaf in leaves:
                tree._hang(leaf, top, _after(tree, leaf, length))
        tree.buckets[length].pop(v, None)
        step.edges, step.nodes_new, step.bucket_ops, step.select_work = tree.edges, tree.made, tree.ops + 1, front.work
        held = max(held, len(front.heap))
        steps.append(step)
        if check:
            check(tree, alive)
    out = triple(codes, steps, terminator)
    out.cells = 8 * len(tree.parent) + 4 * len(codes) + 2 * held
    return out


def _after(tree: Tree, leaf: int, length: int) -> int:
    """What tells a leaf from its siblings below a mark: the symbol after the replaced copy, or the leaf's place where that is a mark too."""
    p = tree.leaf_id[leaf] + length
    symbol = tree.text[p]
    return symbol if symbol > END else -(1 << 40) - tree.leaf_id[leaf]
