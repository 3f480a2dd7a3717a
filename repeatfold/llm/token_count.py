"""Token counts by rank-synchronous merging of ragged numpy arrays (see ``bpe``).

A null or empty text has no bytes and no tokens. Repeated rows are counted alike; a very long text is one slice of its own.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from repeatfold.llm.bpe import piece_counter
from repeatfold.llm.words import text_slices


def count_tokens(df: DataFrame, model: str, id_col: str = "doc_id", text_col: str = "text", limit: int = 4096) -> DataFrame:
    """``(id, n_bytes, n_tokens, over_limit)`` of every row, as the library for the sentencepiece model at ``model`` counts them.

    ``model`` is a path every worker can read. No shuffle.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = piece_counter(model)
        for batch in batches:
            counts, sizes = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
            for first, data, offsets in text_slices(batch.column(1)):
                counts.append(counter.count(first, data, offsets))
                sizes.append(np.diff(offsets))
            n = np.concatenate(counts)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.concatenate(sizes)), pa.array(n), pa.array(n > limit)], [id_col, "n_bytes", "n_tokens", "over_limit"])

    kind = dict(df.dtypes)[id_col]
    return df.select(F.col(id_col), F.col(text_col)).mapInArrow(run, f"`{id_col}` {kind}, n_bytes long, n_tokens long, over_limit boolean")
