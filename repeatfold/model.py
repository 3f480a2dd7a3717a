"""Schemas of folded units, step logs and the other outputs."""

from __future__ import annotations

FACTORS = "array<struct<a:bigint,len:int>>"
FOLDED = f"n bigint, residual array<int>, factors {FACTORS}, kinds array<int>, steps int"
STEP_LOG = (
    "k int, len int, first bigint, d int, q int, n1 int, n2 int, n3 int, n4 int, sort_work double, edges bigint, nodes_new bigint, "
    "bucket_ops bigint, select_work bigint, s int, accepted boolean, picks array<bigint>, pick_kinds array<int>"
)
SUFFIXES = "rank bigint, pos bigint, lcp int"
INTERVALS = "p int, lo bigint, hi bigint, maximal boolean"
REPEATS = "len int, first bigint, n_occ bigint"
TREE_NODES = "node int, parent int, lo bigint, hi bigint, depth int, slink int, leaf_id bigint"
LZ77 = "idx int, pos bigint, src bigint, len int, literal int"
GRAMMAR = "rules map<int,array<int>>, start array<int>"

#: Codes that are no character: a replaced copy and the end of a text.
MARK, END = -2, -1
