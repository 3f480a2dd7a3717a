"""Quality classifier: ordinal cumulative-link regression on graded ratings.

Grades: 0 toxic, 1 poor, 2 good. One weight vector over hashed words is shared by all grades; ordered thresholds turn a document's score into
P(grade > k) = sigmoid(score - threshold k), from which come the expected grade and the tail probability that selects.

A document's features are its distinct words (A-Z lower-cased), the distinct shapes of its words and the share of each shape, all hashed;
the whole text counts. A null or empty text has no feature and gets the prior's score; it is no good document only if the prior says so.
Repeated rows are scored alike. Without labels there is nothing to learn: every document is kept, with a tail probability of 1.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType, DoubleType, StructField, StructType

from repeatfold.llm.words import Slice, mix, word_slices

BITS = 18
GRADES = 3
#: Labelled documents the model is fitted on at most, chosen by a hash of the id.
MAX_TRAIN = 12_000
#: Words must stand in this many training documents to get a weight.
MIN_DOCS = 5
STRONG = 5.0
#: Tail probability from which a document is kept.
KEEP_FROM = 0.5

_CLASS = np.zeros(256, np.uint8)
_CLASS[97:123] = 1
_CLASS[65:91] = 2
_CLASS[48:58] = 4
_CLASS[128:] = 1
_CLASS[[ord(c) for c in "!?"]] = 8
_CLASS[[ord(c) for c in ".,;:"]] = 16
_CLASS[(_CLASS == 0) & (np.arange(256) > 32)] = 32


def features(s: Slice) -> tuple[np.ndarray, np.ndarray]:
    """(document, feature) pairs, distinct and sorted, of a slice; words are lower-cased, shapes are not."""
    doc = np.repeat(np.arange(s.n), np.diff(s.at))
    shape = np.bitwise_or.reduceat(_CLASS[s.data], s.start) if len(s.start) else np.zeros(0, np.uint8)
    # reduceat runs up to the next word's start; white space has class 0
    lower = Slice(s.first, s.n, np.where((s.data >= 65) & (s.data < 91), s.data + 32, s.data).astype(np.uint8), s.offsets, s.start, s.end, s.at)
    word = (lower.hashes() >> np.uint64(64 - BITS)).astype(np.int64) if len(s.start) else np.zeros(0, np.int64)
    pairs = [doc << BITS | word]
    if len(doc):
        count = np.bincount(doc * 64 + shape, minlength=s.n * 64).reshape(s.n, 64)
        d, k = np.nonzero(count)
        share = np.minimum(7, (8 * count[d, k]) // count.sum(1)[d])
        code = mix((k * 8 + share).astype(np.uint64) + np.uint64(1)) >> np.uint64(64 - BITS)
        pairs.append(d << BITS | code.astype(np.int64))
    both = np.unique(np.concatenate(pairs))
    return both >> BITS, (both & ((1 << BITS) - 1)).astype(np.int32)


@dataclass
class Ordinal:
    """``weight`` over hashed features and ``threshold`` of each step between grades, ascending."""

    weight: np.ndarray
    threshold: np.ndarray

    def tails(self, score: np.ndarray) -> np.ndarray:
        """P(grade > k) for each document and k."""
        return 1 / (1 + np.exp(-np.clip(score[:, None] - self.threshold[None, :], -40, 40)))


def fit(docs: list[np.ndarray], grades: np.ndarray, rounds: int = 300, rate: float = 0.5, l2: float = 1e-5) -> Ordinal | None:
    """Fits by adaptive gradient steps on the log likelihood of the grades; None without two grades."""
    if len(np.unique(grades)) < 2:
        return None
    n, size = len(docs), 1 << BITS
    owner = np.repeat(np.arange(n), [len(d) for d in docs])
    feature = np.concatenate(docs) if n else np.zeros(0, np.int64)
    df = np.bincount(feature, minlength=size)
    # only features whose mean grade is far from the rest's: a bag of invented words holds thousands that say nothing
    use = np.zeros(size, bool)
    for k in range(GRADES - 1):
        y = (grades > k).astype(float)
        p = y.mean()
        if 0 < p < 1:
            hit = np.bincount(feature, y[owner], size)
            z = (hit - df * p) / np.sqrt(np.maximum(df * p * (1 - p), 1e-9))
            use |= (np.abs(z) >= STRONG) & (df >= MIN_DOCS)
    live = use[feature]
    owner, feature = owner[live], feature[live]
    # without a feature a document has the prior's odds
    prior = np.clip([(grades > k).mean() for k in range(GRADES - 1)], 1e-3, 1 - 1e-3)
    model = Ordinal(np.zeros(size), np.sort(-np.log(prior / (1 - prior))))
    gw, gt = np.full(size, 1e-8), np.full(GRADES - 1, 1e-8)
    for _ in range(rounds):
        score = np.bincount(owner, model.weight[feature], n)
        tail = model.tails(score)
        # cumulative-link likelihood: P(grade) = tail[grade-1] - tail[grade]
        t = np.concatenate([np.ones((n, 1)), tail, np.zeros((n, 1))], 1)
        rows = np.arange(n)
        lo, hi = t[rows, grades], t[rows, grades + 1]
        p = np.maximum(lo - hi, 1e-9)
        d_score = (lo * (1 - lo) - hi * (1 - hi)) / p / n
        d_thr = np.zeros(GRADES - 1)
        for k in range(GRADES - 1):
            slope = tail[:, k] * (1 - tail[:, k]) / p / n
            d_thr[k] = (slope * ((grades == k).astype(float) - (grades == k + 1))).sum()
        g = np.bincount(feature, d_score[owner], size) - l2 * model.weight
        gw += g * g
        gt += d_thr * d_thr
        model.weight += rate * g / np.sqrt(gw)
        model.threshold = np.sort(model.threshold + rate * 0.1 * d_thr / np.sqrt(gt))
    return model


def training_rows(docs: DataFrame, labels: DataFrame, id_col: str, text_col: str, limit: int) -> tuple[list[np.ndarray], np.ndarray]:
    """Hashed features and grades of at most ``limit`` labelled documents, the ones with the smallest id hashes."""
    graded = labels.where("quality is not null").select(F.col(id_col).alias("_id"), F.when(F.coalesce("toxic", F.lit(0)) > 0, 0).when(F.col("quality") > 0, 2).otherwise(1).cast("int").alias("_grade"))
    graded = graded.where("_id is not null").groupBy("_id").agg(F.min("_grade").alias("_grade")).orderBy(F.xxhash64("_id"), "_id").limit(limit)
    rows = docs.select(F.col(id_col).alias("_id"), F.col(text_col).alias("_text")).join(F.broadcast(graded), "_id").select("_id", "_text", "_grade")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for s in word_slices(batch.column(1)):
                doc, feature = features(s)
                at = np.searchsorted(doc, np.arange(s.n + 1)).astype(np.int32)
                part = batch.slice(s.first, s.n)
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.ListArray.from_arrays(pa.array(at), pa.array(feature))], ["_id", "_grade", "f"])

    kind = dict(rows.dtypes)["_id"]
    got = rows.mapInArrow(run, f"_id {kind}, _grade int, f array<int>").toArrow()
    order = np.lexsort([got["_id"].to_numpy()]) if len(got) else []
    lists = got["f"].combine_chunks() if len(got) else None
    return [lists[int(i)].values.to_numpy().astype(np.int64) for i in order], got["_grade"].to_numpy()[order].astype(np.int64) if len(got) else np.zeros(0, np.int64)


def score_rows(docs: DataFrame, model: Ordinal | None, keep_from: int = 2, at_least: float = KEEP_FROM, text_col: str = "text") -> DataFrame:
    """Every row of ``docs`` with ``expected_grade, tail_probability, keep`` (columns of these names are replaced); ``tail_probability`` is P(grade >= keep_from). No shuffle."""
    own = ["expected_grade", "tail_probability", "keep"]
    docs = docs.drop(*own)
    place = docs.columns.index(text_col)
    weight = None if model is None else model.weight.astype(np.float32)
    steps = None if model is None else Ordinal(np.zeros(0), model.threshold)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = len(batch)
            expected, tail = np.full(n, float(GRADES - 1)), np.ones(n)
            if weight is not None:
                for s in word_slices(batch.column(place)):
                    doc, feature = features(s)
                    tails = steps.tails(np.bincount(doc, weight[feature], s.n))
                    expected[s.first : s.first + s.n], tail[s.first : s.first + s.n] = tails.sum(1), tails[:, keep_from - 1]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(expected), pa.array(tail), pa.array(tail >= at_least)], [*batch.schema.names, *own])

    schema = StructType([*docs.schema.fields, *(StructField(c, DoubleType()) for c in own[:2]), StructField("keep", BooleanType())])
    return docs.mapInArrow(run, schema)


def score(docs: DataFrame, model: Ordinal | None, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """``(id, expected_grade, tail_probability, keep)`` of every row."""
    return score_rows(docs.select(id_col, text_col), model, text_col=text_col, **options).drop(text_col)


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", limit: int = MAX_TRAIN) -> Ordinal | None:
    rows, grades = training_rows(docs, labels, id_col, text_col, limit)
    # copies of one text count once, or their words would look like signs of their grade
    once = list({(r.tobytes(), g): i for i, (r, g) in enumerate(zip(rows, grades.tolist(), strict=True))}.values())
    return fit([rows[i] for i in once], grades[once])
