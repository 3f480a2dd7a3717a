"""Repeat folding on frames of units: exact, simple and gated, with step logs, and its inverse."""

from __future__ import annotations

import math
from collections.abc import Iterator, Sequence

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, IntegerType, StructField, StructType

from repeatfold.kernels import assemble, brute, gated, jvm, reach, tree
from repeatfold.kernels.assemble import Folded, Step
from repeatfold.model import FOLDED, STEP_LOG
from repeatfold.operators.units import map_units

ENGINES = ("reach", "tree", "brute")


def runner(engine: str, options: dict):
    if engine == "brute":
        return lambda codes, sa, lcp: brute.run(codes, **options)
    if engine == "tree":
        return lambda codes, sa, lcp: tree.run(codes, sa, lcp, **options)
    if engine == "reach":
        if options.get("tie") == "bucket":
            raise ValueError("the list order of nodes is known to the tree engine only")
        return lambda codes, sa, lcp: reach.run(codes, sa, lcp, **options)
    if engine == "gated":
        return lambda codes, sa, lcp: gated.run(codes, sa, lcp, **options)
    raise ValueError(f"no engine {engine}")


def triple_row(f: Folded) -> tuple:
    return f.n, f.residual, [{"a": a, "len": n} for a, n in f.factors], f.kinds, sum(s.accepted for s in f.steps)


def step_row(s: Step) -> tuple:
    d, kinds = len(s.starts), [k for _, k in s.picks]
    n = [kinds.count(k) if s.accepted else 0 for k in (1, 2, 3)]
    q = sum(n)
    return (s.k, s.len, s.first + 1, d, q, *n, d - 1 - q, d * math.log2(d), s.edges, s.nodes_new, s.bucket_ops, s.select_work, s.s, s.accepted, [p + 1 for p, _ in s.picks], kinds)


def on_jvm(df: DataFrame, col: str, engine: str, options: dict) -> bool:
    """Whether the JVM has the engine with these options; ``brute``, the list order of nodes and the tree's simple mode are Python's only."""
    known = engine in ("reach", "gated") or (engine == "tree" and options.get("tie") != "bucket" and options.get("mode", "greedy") == "greedy")
    return known and jvm.fits(df, col, options.get("ended", False))


def _apply(df: DataFrame, id_cols: Sequence[str], col: str, engine: str, log: bool, options: dict) -> DataFrame:
    run = runner(engine, options)
    if on_jvm(df, col, engine, options):
        return jvm.rows(df, id_cols, col, STEP_LOG if log else FOLDED, "log" if log else "fold", engine, null_row=not log, **options)
    if log:
        return map_units(df, id_cols, col, STEP_LOG, lambda *u: map(step_row, run(*u).steps))
    return map_units(df, id_cols, col, FOLDED, lambda *u: [triple_row(run(*u))], null_row=True)


def fold(df: DataFrame, id_cols: Sequence[str], text_col: str = "text", *, engine: str = "reach", tie: str = "leftmost", min_len: int = 2, max_steps: int | None = None, terminator: bool = False, log: bool = False) -> DataFrame:
    """The triple of each unit, or with ``log`` one row a step."""
    return _apply(df, id_cols, text_col, engine, log, {"tie": tie, "min_len": min_len, "max_steps": max_steps, "terminator": terminator})


def fold_simple(df: DataFrame, id_cols: Sequence[str], text_col: str = "text", *, engine: str = "reach", pick: str = "ends_first", tie: str = "leftmost", log: bool = False) -> DataFrame:
    """The linear variant: any maximal disjoint set of copies of kind 3, in the order ``pick``: ends_first, scan or hash."""
    return _apply(df, id_cols, text_col, engine, log, {"tie": tie, "mode": "simple", "order": pick})


def fold_gated(df: DataFrame, id_cols: Sequence[str], text_col: str = "text", *, alpha: float = 30, beta: float = 80, gate_type1: str = "never", rescan: bool = False, log: bool = False) -> DataFrame:
    """The earlier method: maximal repeats of the input that pass the gate."""
    return _apply(df, id_cols, text_col, "gated", log, {"alpha": alpha, "beta": beta, "gate_type1": gate_type1, "rescan": rescan})


def unfold(df: DataFrame, as_text: bool = True) -> DataFrame:
    """The units behind ``residual, factors, kinds``; other columns but ``n`` and ``steps`` stay. ``text`` string, or ``codes array<int>``."""
    drop = {"residual", "factors", "kinds", "n", "steps"}
    ids = [c for c in df.columns if c not in drop]
    name = "text" if as_text else "codes"
    kind = "string" if as_text else None
    k = len(ids)
    from pyspark.sql.types import StringType

    schema = StructType([df.schema[c] for c in ids] + [StructField(name, StringType() if kind else ArrayType(IntegerType()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for res, fac, kinds in zip(*(batch.column(k + c).to_pylist() for c in range(3)), strict=True):
                if res is None:
                    out.append(None)
                    continue
                codes = assemble.unfold(res, [(f["a"], f["len"]) for f in fac], kinds)
                out.append("".join(map(chr, codes)) if as_text else codes)
            yield pa.RecordBatch.from_arrays([*batch.columns[:k], pa.array(out, pa.string() if as_text else pa.list_(pa.int32()))], [*ids, name])

    return df.select(*ids, "residual", "factors", "kinds").mapInArrow(run, schema)


def sizes(folded: DataFrame) -> DataFrame:
    """Each unit's ``n, residual_len, n_literals, n_marks, n_factors, steps`` beside its ids; column expressions only."""
    ids = [c for c in folded.columns if c not in {"residual", "factors", "kinds", "n", "steps"}]
    return folded.select(
        *ids, "n", F.size("residual").cast("long").alias("residual_len"), (F.size("residual") - F.size("kinds")).cast("long").alias("n_literals"),
        F.size("kinds").cast("long").alias("n_marks"), F.size("factors").cast("long").alias("n_factors"), F.col("steps").cast("long").alias("steps"),
    )


SIZES = "n bigint, residual_len bigint, n_literals bigint, n_marks bigint, n_factors bigint, steps bigint"


def fold_sizes(df: DataFrame, id_cols: Sequence[str], text_col: str = "text", *, engine: str = "reach", **options) -> DataFrame:
    """``sizes`` of the folds, counted where the units are; of a gated fold also ``refused`` and ``lost``, as ``measures.refusals``.

    ``ended``: a unit is an array of texts, as ``tables.grouped_texts`` has them.
    """
    if not on_jvm(df, text_col, engine, options):
        return sizes(_apply(df, id_cols, text_col, engine, False, options))
    if engine == "gated":
        return jvm.rows(df, id_cols, text_col, SIZES + ", refused bigint, lost bigint", "gated_sizes", engine, null_row=True, **options)
    return jvm.rows(df, id_cols, text_col, SIZES, "sizes", engine, null_row=True, **options)


TOTALS = (
    "n bigint, steps bigint, sum_d bigint, sort_work double, edges bigint, nodes_new bigint, bucket_ops bigint, select_work bigint, saved bigint, "
    "idle_steps bigint, taken bigint, grows boolean"
)


def step_totals(df: DataFrame, id_cols: Sequence[str], text_col: str = "text", *, engine: str = "tree") -> DataFrame:
    """``measures.step_stats`` of the folds and ``n``, summed where the units are: no row for each step, no shuffle. Units without a step have no row."""
    return jvm.rows(df, id_cols, text_col, TOTALS, "totals", engine)


def irreducible(folded: DataFrame) -> DataFrame:
    """ids and ``violations``: residuals that still hold a repeat of two literals (marks cut it apart)."""
    ids = [c for c in folded.columns if c not in {"residual", "factors", "kinds", "n", "steps"}]
    counted = jvm.rows(folded, ids, "residual", "violations bigint", "repeated_pairs", "none", null_row=True)
    return counted.select(*ids, F.coalesce("violations", F.lit(0).cast("long")).alias("violations"))
