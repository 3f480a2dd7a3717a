"""Running a kernel on every unit of a frame.

A unit is one row: its ids and one column of symbols (a string, bytes, integers, or strings that are coded by their order within the unit).
Units are independent, so nothing is shuffled; a batch is cut into slices of about ``SLICE`` symbols whose suffixes are ordered together.
A null unit gives nulls (or no rows), an empty one an empty result.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType, _parse_datatype_string

from repeatfold.kernels.suffix import Order

SLICE = 1_000_000


def to_codes(value) -> np.ndarray | None:
    """Symbols of one unit as integers."""
    if value is None:
        return None
    if isinstance(value, str):
        return np.frombuffer(value.encode("utf-32-le"), np.uint32).astype(np.int64)
    if isinstance(value, (bytes, bytearray)):
        return np.frombuffer(bytes(value), np.uint8).astype(np.int64)
    if len(value) and isinstance(value[0], str):
        place = {s: k for k, s in enumerate(sorted(set(value)))}
        return np.array([place[s] for s in value], np.int64)
    return np.asarray(value, np.int64)


def ordered(units: Sequence[np.ndarray]) -> Iterator[tuple[int, list[int], list[int], list[int]]]:
    """(unit, codes, suffix order, common prefixes) for each unit, ordering slices of them together."""
    a = 0
    while a < len(units):
        b, size = a + 1, len(units[a])
        while b < len(units) and size + len(units[b]) <= SLICE:
            size += len(units[b])
            b += 1
        starts = np.concatenate([[0], np.cumsum([len(u) for u in units[a:b]])]).astype(np.int64)
        order = Order(np.concatenate(units[a:b]), starts)
        lcp = order.lcp()
        for u in range(a, b):
            sa, h = order.unit(u - a, lcp)
            yield u, units[u].tolist(), sa, h
        a = b


def schema_of(df: DataFrame, id_cols: Sequence[str], fields: str) -> StructType:
    return StructType([df.schema[c] for c in id_cols] + _parse_datatype_string(fields).fields)


def map_units(df: DataFrame, id_cols: Sequence[str], col: str, fields: str, work: Callable, null_row: bool = False, need_order: bool = True) -> DataFrame:
    """Rows of ``work(codes, sa, lcp)`` (tuples in the order of ``fields``) beside the ids of each unit.

    Only the ids and the symbols are read. With ``null_row`` a null unit gives one row of nulls, else none.
    """
    schema = schema_of(df, id_cols, fields)
    arrow = to_arrow_schema(schema)
    width = len(schema) - len(id_cols)
    k = len(id_cols)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            values = [to_codes(v) for v in batch.column(k).to_pylist()]
            rows = [r for r, v in enumerate(values) if v is not None]
            units = [values[r] for r in rows]
            got: dict[int, list[tuple]] = {}
            todo = ordered(units) if need_order else ((u, x.tolist(), None, None) for u, x in enumerate(units))
            for u, codes, sa, lcp in todo:
                got[rows[u]] = list(work(codes, sa, lcp))
            owner, out = [], []
            for r in range(len(values)):
                for row in got.get(r, [(None,) * width] if null_row and values[r] is None else []):
                    owner.append(r)
                    out.append(row)
            ids = [batch.column(c).take(pa.array(owner, pa.int64())) for c in range(k)]
            cols = [pa.array([row[c] for row in out], arrow.field(k + c).type) for c in range(width)]
            yield pa.RecordBatch.from_arrays(ids + cols, names=arrow.names)

    return df.select(*(F.col(c) for c in id_cols), F.col(col)).mapInArrow(run, schema)
