"""Occurrences, repeats, suffix order, intervals and suffix trees of units."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from repeatfold.kernels import jvm, suffix
from repeatfold.kernels.tree import ROOT, Tree
from repeatfold.model import INTERVALS, REPEATS, SUFFIXES, TREE_NODES
from repeatfold.operators.units import map_units
from repeatfold.plans import frames


def occurrences(df: DataFrame, pattern, text_col: str = "text") -> DataFrame:
    """``df`` with ``pos`` (1-based), one row for each start of ``pattern`` (a string or a column); overlapping starts count."""
    p = F.lit(pattern) if isinstance(pattern, str) else pattern
    text = F.col(text_col)
    starts = F.sequence(F.lit(1), F.length(text) - F.length(p) + 1)
    found = F.filter(starts, lambda k: F.substring(text, k, F.length(p)) == p)
    return df.where((F.length(p) > 0) & F.contains(text, p)).withColumn("pos", F.explode(found).cast("long"))


def windows(df: DataFrame, id_cols: Sequence[str], width: int, text_col: str = "text") -> DataFrame:
    """``ids, a, b``: 122 bits of rolling hashes for each distinct string of ``width`` symbols of a unit, in one pass over it."""
    return jvm.rows(df, id_cols, text_col, "a bigint, b bigint", "windows", "none", min_len=width)


def repeats_at(df: DataFrame, length: int, id_cols: Sequence[str], text_col: str = "text") -> DataFrame:
    """Classes of equal substrings of ``length`` with two starts or more: ``len, first, n_occ``. Runs of the suffix order, no shuffle."""

    def work(codes, sa, lcp):
        lo = 0
        for r in range(1, len(sa) + 1):
            if r == len(sa) or lcp[r] < length:
                if r - lo > 1:
                    yield length, min(sa[lo:r]) + 1, r - lo
                lo = r

    return map_units(df, id_cols, text_col, REPEATS, work)


def longest_repeats(df: DataFrame, id_cols: Sequence[str], text_col: str = "text", engine: str = "lcp") -> DataFrame:
    """Longest repeats of each unit: ``len, first, n_occ``, one row for each of them; none for a unit without a repeat.

    ``engine``: lcp (runs of the suffix order), bisect (halving the length, since a prefix of a repeat repeats) or group (the same as relations
    of substrings, for short texts).
    """
    if engine == "group":
        return frames.longest_by_groups(df, id_cols, text_col)
    if engine == "bisect":
        return map_units(df, id_cols, text_col, REPEATS, lambda codes, sa, lcp: _bisected(codes), need_order=False)
    if engine != "lcp":
        raise ValueError(f"no engine {engine}")

    def work(codes, sa, lcp):
        top = max(lcp, default=0)
        r = 1
        while top and r < len(sa):
            if lcp[r] == top:
                lo = r - 1
                while r < len(sa) and lcp[r] == top:
                    r += 1
                yield top, min(sa[lo:r]) + 1, r - lo
            r += 1

    return map_units(df, id_cols, text_col, REPEATS, work)


def _bisected(codes: list[int]) -> list[tuple[int, int, int]]:
    def classes(length: int) -> dict[tuple[int, ...], list[int]]:
        out: dict[tuple[int, ...], list[int]] = {}
        for p in range(len(codes) - length + 1):
            out.setdefault(tuple(codes[p : p + length]), []).append(p)
        return {x: s for x, s in out.items() if len(s) > 1}

    low, high = 0, len(codes)
    while high - low > 1:
        mid = (low + high) // 2
        low, high = (mid, high) if classes(mid) else (low, mid)
    return [(low, s[0] + 1, len(s)) for s in classes(low).values()] if low else []


def maximal_repeats(df: DataFrame, id_cols: Sequence[str], text_col: str = "text", min_len: int = 1) -> DataFrame:
    """Left- and right-diverse repeats: ``len, first, n_occ``."""
    work = lambda codes, sa, lcp: ((p, min(sa[lo : hi + 1]) + 1, hi - lo + 1) for p, lo, hi in suffix.maximal_repeats(codes, sa, lcp) if p >= min_len)
    return map_units(df, id_cols, text_col, REPEATS, work)


def suffix_rows(df: DataFrame, id_cols: Sequence[str], text_col: str = "text") -> DataFrame:
    """Suffix order and common prefixes: ``rank, pos, lcp``, ranks and positions from 1."""
    return map_units(df, id_cols, text_col, SUFFIXES, lambda codes, sa, lcp: ((r + 1, p + 1, h) for r, (p, h) in enumerate(zip(sa, lcp, strict=True))))


def interval_rows(df: DataFrame, id_cols: Sequence[str], text_col: str = "text") -> DataFrame:
    """Groups of ranks lo…hi whose suffixes share exactly p symbols: ``p, lo, hi, maximal``."""

    def work(codes, sa, lcp):
        top = set(suffix.maximal_repeats(codes, sa, lcp))
        return ((p, lo + 1, hi + 1, (p, lo, hi) in top) for p, lo, hi in suffix.intervals(sa, lcp))

    return map_units(df, id_cols, text_col, INTERVALS, work)


def suffix_tree(df: DataFrame, id_cols: Sequence[str], text_col: str = "text") -> DataFrame:
    """Nodes of each unit's suffix tree; an edge's label is the text at lo…hi (1-based, the end symbol after the text)."""

    def work(codes, sa, lcp):
        t = Tree(codes, sa, lcp)
        for v in range(len(t.parent)):
            up = t.parent[v]
            lo = t.at[v] + (t.depth[up] if up >= 0 else 0) + 1
            leaf = t.leaf_id[v]
            yield v, up, lo, t.at[v] + t.depth[v], t.depth[v], t.link[v] if leaf < 0 and v != ROOT else None, leaf + 1 if leaf >= 0 else None

    return map_units(df, id_cols, text_col, TREE_NODES, work)
