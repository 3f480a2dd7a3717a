"""Packing by power-of-two decomposition.

A document's ids (its tokens and an end id) are cut into pieces whose lengths are powers of two: as many of the full length as fit, then
the binary digits of the rest, longest first. Each piece is a sequence of its own and goes to the bucket of its length, from which batches
of equal lengths are drawn, so no sequence crosses documents and nothing is padded.

A null or empty text still has its end id: one piece of length 1. Repeated rows are packed each for itself.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from repeatfold.llm.bpe import word_encoder
from repeatfold.llm.words import word_slices


def binary_lengths(n: int, longest: int) -> list[int]:
    """Powers of two, none over ``longest`` (itself one), longest first, that sum to ``n``."""
    return [longest] * (n // longest) + [1 << b for b in range(longest.bit_length() - 1, -1, -1) if (n % longest) >> b & 1]


def cut_lengths(counts: np.ndarray, longest: int) -> tuple[np.ndarray, np.ndarray]:
    """(owner, length) of the pieces of documents with ``counts`` ids, in order."""
    bits = longest.bit_length() - 1
    owner = [np.repeat(np.arange(len(counts)), counts // longest)]
    length = [np.full(len(owner[0]), longest, np.int64)]
    for b in range(bits - 1, -1, -1):
        has = np.flatnonzero((counts % longest) >> b & 1)
        owner.append(has)
        length.append(np.full(len(has), 1 << b, np.int64))
    o, n = np.concatenate(owner), np.concatenate(length)
    order = np.argsort(o, kind="stable")
    return o[order], n[order]


def pack(df: DataFrame, tokenizer: str, end_id: int = 2, longest: int = 4096, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = True) -> DataFrame:
    """One row a piece: id, ``piece, start, length, bucket, ids_crc32, doc_tokens`` and, with ``with_ids``, ``ids array<int>``. No shuffle.

    ``longest`` must be a power of two; ``bucket`` is the binary logarithm of the length.
    """
    if longest & (longest - 1) or longest < 1:
        raise ValueError("longest must be a power of two")
    kind = dict(df.dtypes)[id_col]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = word_encoder(tokenizer)
        for batch in batches:
            for s in word_slices(batch.column(1)):
                ids, sizes = encoder.encode(s.data, s.start, s.end)
                ends = np.concatenate([[0], np.cumsum(sizes)])[s.at].astype(np.int64)
                counts = np.diff(ends) + 1
                flat = np.insert(ids.astype("<u4"), ends[1:], end_id)
                owner, length = cut_lengths(counts, longest)
                stop = np.cumsum(length)
                begin = stop - length
                base = np.cumsum(counts) - counts
                start = begin - base[owner]
                raw = memoryview(flat.tobytes())
                crc = np.fromiter((zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(begin.tolist(), stop.tolist(), strict=True)), np.int64, len(begin))
                first = np.searchsorted(owner, np.arange(s.n))
                columns = [batch.column(0).take(pa.array(owner + s.first)), pa.array(np.arange(len(owner)) - first[owner]), pa.array(start), pa.array(length), pa.array(np.log2(length).astype(np.int32)), pa.array(crc), pa.array(counts[owner])]
                names = [id_col, "piece", "start", "length", "bucket", "ids_crc32", "doc_tokens"]
                if with_ids:
                    columns.append(pa.ListArray.from_arrays(pa.array(np.append(begin, stop[-1:]).astype(np.int32)), pa.array(flat.astype(np.int32))))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(columns, names)

    schema = f"`{id_col}` {kind}, piece long, start long, length long, bucket int, ids_crc32 long, doc_tokens long" + ", ids array<int>" * with_ids
    return df.select(F.col(id_col), F.col(text_col)).mapInArrow(run, schema)


def as_sequences(pieces: DataFrame) -> DataFrame:
    """``pieces`` with ``sequence_id`` (distinct for each piece) and ``offset`` (0: a sequence is one piece)."""
    return pieces.withColumns({"sequence_id": F.monotonically_increasing_id(), "offset": F.lit(0).cast("long")})
