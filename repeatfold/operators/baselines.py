"""Baselines on frames of units: LZ77, pair grammar, longest-first grammar, gzip, identity."""

from __future__ import annotations

import zlib
from collections.abc import Iterator, Sequence

import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StringType, StructField, StructType

from repeatfold.kernels import baselines, jvm
from repeatfold.model import GRAMMAR, LZ77
from repeatfold.operators.units import map_units


def lz77(df: DataFrame, id_cols: Sequence[str], text_col: str = "text", self_ref: bool = True) -> DataFrame:
    """Factors in order: ``idx, pos, src, len, literal`` (1-based; src null for a literal, literal null else)."""
    if self_ref and jvm.fits(df, text_col):
        return jvm.rows(df, id_cols, text_col, LZ77, "lz77", "lz77")

    def work(codes, sa, lcp):
        pos = 1
        for k, (src, length, literal) in enumerate(baselines.lz77(codes, sa, lcp) if self_ref else baselines.lz77_apart(codes)):
            yield k + 1, pos, src + 1 if src >= 0 else None, length, literal if src < 0 else None
            pos += length

    return map_units(df, id_cols, text_col, LZ77, work, need_order=self_ref)


def lz77_sizes(df: DataFrame, id_cols: Sequence[str], text_col: str = "text", self_ref: bool = True) -> DataFrame:
    """``n, factors`` of each unit, counted where the unit is."""
    if self_ref and jvm.fits(df, text_col):
        return jvm.rows(df, id_cols, text_col, "n bigint, factors bigint", "lz77_sizes", "lz77")
    work = lambda codes, sa, lcp: [(len(codes), len(baselines.lz77(codes, sa, lcp) if self_ref else baselines.lz77_apart(codes)))]
    return map_units(df, id_cols, text_col, "n bigint, factors bigint", work, need_order=self_ref)


def lz77_decode(factors: DataFrame, id_cols: Sequence[str]) -> DataFrame:
    """``ids, text`` from factor rows; a unit's factors meet in one group, bounded by the unit."""
    rows = factors.groupBy(*id_cols).agg(F.array_sort(F.collect_list(F.struct("idx", "src", "len", "literal"))).alias("f"))
    k = len(id_cols)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = ["".join(map(chr, baselines.lz77_decode([(-1 if x["src"] is None else x["src"] - 1, x["len"], x["literal"]) for x in fs]))) for fs in batch.column(k).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns[:k], pa.array(out, pa.string())], [*id_cols, "text"])

    return rows.mapInArrow(run, StructType([factors.schema[c] for c in id_cols] + [StructField("text", StringType())]))


def lz77_units(df: DataFrame, id_cols: Sequence[str], text_col: str = "text") -> DataFrame:
    """``ids, factors``: the rows of ``lz77`` in one array a unit; null for a null unit."""
    return jvm.rows(df, id_cols, text_col, f"factors array<struct<{LZ77.replace(' ', ':').replace(',:', ',')}>>", "lz77_units", "lz77", null_row=True)


def lz77_texts(units: DataFrame) -> DataFrame:
    """``ids, text`` from the arrays of ``lz77_units``, where they are."""
    return jvm.rows(units, [c for c in units.columns if c != "factors"], "factors", "text string", "lz77_text", "lz77", null_row=True)


def _grammar(df: DataFrame, id_cols: Sequence[str], text_col: str, build, need_order: bool, engine: str | None = None) -> DataFrame:
    if engine and jvm.fits(df, text_col):
        return jvm.rows(df, id_cols, text_col, GRAMMAR, "grammar", engine, null_row=True)

    def work(codes, sa, lcp):
        rules, start = build(codes, sa, lcp)
        yield list(rules.items()), start

    return map_units(df, id_cols, text_col, GRAMMAR, work, null_row=True, need_order=need_order)


def grammar_pairs(df: DataFrame, id_cols: Sequence[str], text_col: str = "text") -> DataFrame:
    """``rules, start``: the most frequent pair first; rule names are below -9."""
    return _grammar(df, id_cols, text_col, lambda codes, sa, lcp: baselines.pair_grammar(codes), False, "pairs")


def grammar_longest(df: DataFrame, id_cols: Sequence[str], text_col: str = "text", bodies: bool = False) -> DataFrame:
    """``rules, start``: the longest string with two disjoint copies first; with ``bodies`` rule bodies are searched too."""
    return _grammar(df, id_cols, text_col, baselines.longest_grammar_bodies if bodies else baselines.longest_grammar, True, None if bodies else "longest")


def grammar_size(g: DataFrame) -> DataFrame:
    """ids, ``n_rules, size``: symbols of all bodies and of the start sequence."""
    ids = [c for c in g.columns if c not in ("rules", "start")]
    body = F.aggregate(F.map_values("rules"), F.lit(0).cast("long"), lambda a, x: a + F.size(x))
    return g.select(*ids, F.size("rules").cast("long").alias("n_rules"), (body + F.size("start")).cast("long").alias("size"))


def expand_grammar(g: DataFrame) -> DataFrame:
    """``ids, text``."""
    ids = [c for c in g.columns if c not in ("rules", "start")]
    k = len(ids)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = [None if start is None else "".join(map(chr, baselines.expand(dict(rules), start))) for rules, start in zip(batch.column(k).to_pylist(), batch.column(k + 1).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:k], pa.array(out, pa.string())], [*ids, "text"])

    return g.select(*ids, "rules", "start").mapInArrow(run, StructType([g.schema[c] for c in ids] + [StructField("text", StringType())]))


@F.pandas_udf(LongType())
def _gzip(text: pd.Series) -> pd.Series:
    def one(t) -> int | None:
        if t is None:
            return None
        z = zlib.compressobj(9, zlib.DEFLATED, 31)
        return len(z.compress(t.encode())) + len(z.flush())

    return text.map(one).astype("Int64")


def gzip_size(text: Column | str) -> Column:
    """Bytes of a gzip stream of the text."""
    return _gzip(text)
