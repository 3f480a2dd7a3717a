"""Checks of every method's output where the unit is: whether it gives the unit back, adds up, and is final by the method's own rule.

The rules are tested on the output alone, by plain searches in the text or the result, not by the structures that the methods work with.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame

from repeatfold.kernels import assemble, baselines, jvm
from repeatfold.kernels.assemble import END, MARK, Folded
from repeatfold.kernels.gated import gate
from repeatfold.operators.fold import on_jvm, runner
from repeatfold.operators.units import map_units

CHECKED = "n bigint, lossless boolean, balanced boolean, final boolean"


def _balanced(f: Folded) -> bool:
    """Literals and replaced lengths make up the unit; each mark has a kind, and factors are as many as kinds ask for."""
    groups, taken = {}, iter(f.factors)
    total = sum(c not in (MARK, END) for c in f.residual)
    for k in f.kinds:
        if k <= 2 or k not in groups:
            groups[k] = next(taken, (0, -1))[1]
        total += groups[k]
    return total == f.n and next(taken, None) is None and f.residual.count(MARK) == len(f.kinds)


def _no_repeat(residual: list[int], width: int) -> bool:
    """No ``width`` neighbouring literals stand twice."""
    seen, run = set(), 0
    for i, c in enumerate(residual):
        run = run + 1 if c >= 0 else 0
        if run >= width:
            x = tuple(residual[i - width + 1 : i + 1])
            if x in seen:
                return False
            seen.add(x)
    return True


def folded(df: DataFrame, id_cols: Sequence[str], text_col: str = "text", engine: str = "reach", **options) -> DataFrame:
    """``ids, n, lossless, balanced, final``; final: no repeat of ``min_len`` literals is left, or each copy group of a gated fold passes its gate."""
    run = runner(engine, options)
    if on_jvm(df, text_col, engine, options):
        return jvm.rows(df, id_cols, text_col, CHECKED, "checked", engine, **options)
    alpha, beta = options.get("alpha", 30), options.get("beta", 80)

    def work(codes, sa, lcp):
        f = run(codes, sa, lcp)
        if engine == "gated":
            final = all(s.accepted == gate(s.len, s.s, alpha, beta) for s in f.steps)
        else:
            final = _no_repeat(f.residual, max(2 if engine == "tree" else 1, options.get("min_len", 2)))
        yield f.n, assemble.unfold(f.residual, f.factors, f.kinds) == codes, _balanced(f), final

    return map_units(df, id_cols, text_col, CHECKED, work)


def factored(df: DataFrame, id_cols: Sequence[str], text_col: str = "text", self_ref: bool = True) -> DataFrame:
    """The same of LZ77; final: no factor could be one symbol longer, by a search in the text before it."""

    def work(codes, sa, lcp):
        factors = baselines.lz77(codes, sa, lcp) if self_ref else baselines.lz77_apart(codes)
        text = "".join(map(chr, baselines._dense(codes)))
        at, final = 0, True
        for _, length, literal in factors:
            # one symbol more than a copy, or the literal itself
            longer = text[at : at + length + (literal < 0)]
            if at + len(longer) <= len(text) and len(longer) == length + (literal < 0):
                final &= text.find(longer, 0, at + len(longer) - 1 if self_ref else at) < 0
            at += length
        yield len(codes), baselines.lz77_decode(factors) == codes, at == len(codes), final

    return map_units(df, id_cols, text_col, CHECKED, work, need_order=self_ref)


def ruled(df: DataFrame, id_cols: Sequence[str], text_col: str = "text", build: Callable = baselines.longest_grammar, pairs_of_names: bool = False, bodies: bool = False) -> DataFrame:
    """The same of grammars; final: no pair stands disjointly twice in the start sequence (nor, with ``bodies``, anywhere).

    ``pairs_of_names``: pairs that hold rule names count too. Balanced: every rule is used, from two symbols on.
    """
    engine = {baselines.longest_grammar: "longest", baselines.pair_grammar: "pairs"}.get(build)
    if engine and not bodies and pairs_of_names == (engine == "pairs") and jvm.fits(df, text_col):
        return jvm.rows(df, id_cols, text_col, CHECKED, "ruled", engine)
    if build is baselines.pair_grammar:
        build = lambda codes, sa, lcp: baselines.pair_grammar(codes)

    def work(codes, sa, lcp):
        rules, start = build(codes, sa, lcp)
        line = list(start)
        for k, body in enumerate(rules.values() if bodies else ()):
            line += [-(1 << 40) - k, *body]
        left = baselines.disjoint_pairs(line)
        final = all(n < 2 for pair, n in left.items() if pairs_of_names or min(pair) >= 0)
        used = {s for part in (start, *rules.values()) for s in part if s < 0}
        yield len(codes), baselines.expand(rules, start) == codes, used >= set(rules) and all(len(b) > 1 for b in rules.values()), final

    return map_units(df, id_cols, text_col, CHECKED, work)
