"""SQL surface: scalar, aggregate and table functions by name, and views of the tables."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import ArrayType, DoubleType, IntegerType, LongType, StringType, StructField, StructType

from repeatfold.kernels import assemble, baselines, reach, suffix
from repeatfold.operators.baselines import _gzip
from repeatfold.operators.fold import step_row
from repeatfold.operators.units import to_codes

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
_INTS = ArrayType(IntegerType())
# types as objects: workers import this module without a session that could parse them
TRIPLE = StructType([StructField("residual", _INTS), StructField("factors", ArrayType(StructType([StructField("a", LongType()), StructField("len", IntegerType())]))), StructField("kinds", _INTS)])


def _row(**fields) -> StructType:
    return StructType([StructField(k, t()) for k, t in fields.items()])


def _fold(text: str) -> assemble.Folded:
    codes = to_codes(text)
    return reach.run(codes.tolist(), *suffix.order_of(codes))


@pandas_udf(TRIPLE)
def fold_struct(text: pd.Series) -> pd.DataFrame:
    rows = [(None, None, None) if t is None else (f := _fold(t), (f.residual, [{"a": a, "len": n} for a, n in f.factors], f.kinds))[1] for t in text]
    return pd.DataFrame(rows, columns=["residual", "factors", "kinds"])


@pandas_udf(StringType())
def unfold_text(triple: pd.DataFrame) -> pd.Series:
    out = []
    for r, f, k in zip(triple["residual"], triple["factors"], triple["kinds"], strict=True):
        out.append(None if r is None else "".join(map(chr, assemble.unfold(list(r), [(x["a"], x["len"]) for x in f], list(k)))))
    return pd.Series(out, dtype=object)


@pandas_udf(IntegerType())
def longest_repeat_len(text: pd.Series) -> pd.Series:
    return text.map(lambda t: None if t is None else max(suffix.order_of(to_codes(t))[1], default=0)).astype("Int32")


@pandas_udf(IntegerType())
def lz77_count(text: pd.Series) -> pd.Series:
    return text.map(lambda t: None if t is None else len(baselines.lz77((c := to_codes(t)).tolist(), *suffix.order_of(c)))).astype("Int32")


@pandas_udf(IntegerType())
def fold_group(texts: pd.Series) -> int:
    """Length of the residual of a group's texts, each ended by its own terminator; the group is one unit in memory."""
    codes: list[int] = []
    for k, t in enumerate(sorted(x for x in texts if x is not None)):
        codes += [*to_codes(t).tolist(), 0x110000 + k]
    return len(reach.run(codes, *suffix.order_of(codes)).residual)


@pandas_udf(DoubleType())
def entropy_bits(symbols: pd.Series) -> float:
    import numpy as np

    p = symbols.value_counts(normalize=True).to_numpy()
    return float(-(p * np.log2(p)).sum()) if len(p) else 0.0


@udtf(returnType=_row(k=IntegerType, len=IntegerType, first=LongType, n1=IntegerType, n2=IntegerType, n3=IntegerType, n4=IntegerType))
class fold_steps:  # noqa: N801
    def eval(self, text: str) -> Iterator[tuple]:
        for s in _fold(text).steps if text is not None else ():
            r = step_row(s)
            yield r[0], r[1], r[2], *r[5:9]


@udtf(returnType=_row(idx=IntegerType, pos=LongType, src=LongType, len=IntegerType))
class lz77_factors:  # noqa: N801
    def eval(self, text: str) -> Iterator[tuple]:
        c = to_codes(text)
        pos = 1
        for k, (src, n, _) in enumerate(baselines.lz77(c.tolist(), *suffix.order_of(c)) if text is not None else ()):
            yield k + 1, pos, src + 1 if src >= 0 else None, n
            pos += n


@udtf(returnType=_row(rank=LongType, pos=LongType, lcp=IntegerType))
class suffix_rows:  # noqa: N801
    def eval(self, text: str) -> Iterator[tuple]:
        if text is not None:
            for r, (p, h) in enumerate(zip(*suffix.order_of(to_codes(text)), strict=True)):
                yield r + 1, p + 1, h


@udtf(returnType=_row(len=IntegerType, first=LongType, n_occ=LongType))
class maximal_repeat_rows:  # noqa: N801
    def eval(self, text: str) -> Iterator[tuple]:
        if text is not None:
            c = to_codes(text)
            sa, lcp = suffix.order_of(c)
            for p, lo, hi in suffix.maximal_repeats(c.tolist(), sa, lcp):
                yield p, min(sa[lo : hi + 1]) + 1, hi - lo + 1


def register_all(spark: SparkSession, sf_dir: str | None = None) -> None:
    """All functions by name, and with ``sf_dir`` a view for each table."""
    for name, f in {"fold_struct": fold_struct, "unfold_text": unfold_text, "longest_repeat_len": longest_repeat_len, "lz77_count": lz77_count, "gzip_size": _gzip, "fold_group": fold_group, "entropy_bits": entropy_bits}.items():
        spark.udf.register(name, f)
    for name, f in {"fold_steps": fold_steps, "lz77_factors": lz77_factors, "suffix_rows": suffix_rows, "maximal_repeat_rows": maximal_repeat_rows}.items():
        spark.udtf.register(name, f)
    for t in TABLES if sf_dir else ():
        spark.read.parquet(f"{sf_dir}/{t}.parquet").createOrReplaceTempView(t)


