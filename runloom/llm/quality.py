"""Quality classifier: naive Bayes support vectors over hashed word n-grams.

Indicators of words and word pairs are scaled by the log-count ratio of the two classes; a linear model with hinge loss is
fitted to them by dual coordinate descent, on a sample of labelled rows that is bounded in rows and in features, and its
margin is turned into a probability by a logistic curve fitted on labelled rows left out of the descent.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from runloom.llm.common import buffers, discard, pieces, settle, texts, tidy, written
from runloom.llm.textnum import SPACED, ngrams, same_text, words

#: Hashed n-gram features.
FEATURES = 1 << 20
#: Most labelled rows that the model is fitted on: the first in the order of a hash of the id.
SAMPLE_ROWS = 10_000
#: Most features of all those rows together: what the driver receives, 4 bytes each. A text has FEATURES at most.
SAMPLE_FEATURES = 40_000_000
#: Of the sample, every CALIBRATE-th row fits the logistic curve and not the descent.
CALIBRATE = 4
SMOOTHING = 1.0
COST = 1.0
EPOCHS = 12
THRESHOLD = 0.3


def held_out(doc_id: Column) -> Column:
    """crc32 of the id as text, mod 5, is 0. A null id: false."""
    return F.coalesce(F.crc32(F.encode(doc_id.cast("string"), "UTF-8")) % 5 == 0, F.lit(False))


def features(column: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """For pieces of a text column: first and last row, then text number and feature, each pair once, in order."""
    for lo, hi in pieces(column):
        w = words(*buffers(column.slice(lo, hi - lo)), SPACED)
        pairs = ngrams(w.hash, 2, 8)[(ok := same_text(w, 2))]
        grams, owner = np.concatenate([w.hash, pairs]), np.concatenate([w.text, w.text[: len(ok)][ok]])
        both = np.unique((owner.astype(np.int64) << 20) | (grams & np.uint64(FEATURES - 1)).astype(np.int64))
        yield lo, hi, both >> 20, both & (FEATURES - 1)


def _feature_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        column = texts(batch.column(2))
        for lo, hi, owner, feature in features(column):
            ends = np.searchsorted(owner, np.arange(hi - lo + 1))
            data = [feature[a:b].astype(np.int32).tobytes() for a, b in zip(ends[:-1], ends[1:])]
            yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), batch.column(1).slice(lo, hi - lo), pa.array(data, pa.binary())], ["doc_id", "label", "features"])
    tidy()


@dataclass
class Model:
    """margin = sum of weight over a text's features / sqrt(sum of scale over them) + bias; score = logistic(slope * margin + shift)."""

    weight: np.ndarray
    scale: np.ndarray
    bias: float
    slope: float
    shift: float

    def scores(self, n: int, owner: np.ndarray, feature: np.ndarray) -> np.ndarray:
        norm = np.sqrt(np.bincount(owner, self.scale[feature], n))
        margin = np.bincount(owner, self.weight[feature], n) / np.where(norm > 0, norm, 1) + self.bias
        return 1 / (1 + np.exp(-np.clip(self.slope * margin + self.shift, -500, 500)))


def costs(sign: np.ndarray) -> np.ndarray:
    """Cost of each row's loss: classes weigh alike in sum."""
    return COST * len(sign) / (2 * np.array([max(1, (sign == s).sum()) for s in sign]))


def descend(rows: list[np.ndarray], values: list[np.ndarray], sign: np.ndarray, seed: int = 1, epochs: int = EPOCHS) -> tuple[np.ndarray, float, np.ndarray]:
    """Dual coordinate descent for hinge loss: weights, bias (a constant feature of 1) and the dual variables, each from 0 to its row's cost."""
    rng, n, cost = np.random.default_rng(seed), len(rows), costs(sign)
    w, bias, alpha = np.zeros(FEATURES), 0.0, np.zeros(n)
    norm = np.array([v @ v + 1 for v in values])
    for _ in range(epochs):
        for i in rng.permutation(n):
            gradient = sign[i] * (w[rows[i]] @ values[i] + bias) - 1
            new = min(max(alpha[i] - gradient / norm[i], 0.0), cost[i])
            if step := (new - alpha[i]) * sign[i]:
                w[rows[i]] += step * values[i]
                bias += step
                alpha[i] = new
    return w, bias, alpha


def logistic(margin: np.ndarray, positive: np.ndarray) -> tuple[float, float]:
    """Slope and shift of the logistic curve by Newton steps, with targets drawn in from 0 and 1 by the class counts."""
    n1, n0 = positive.sum(), (~positive).sum()
    goal = np.where(positive, (n1 + 1) / (n1 + 2), 1 / (n0 + 2))
    x = np.stack([margin, np.ones_like(margin)], axis=1)
    b = np.array([1.0, 0.0])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ b, -500, 500)))
        step = np.linalg.solve(x.T @ (x * (p * (1 - p))[:, None]) + 1e-6 * np.eye(2), x.T @ (goal - p) - 1e-6 * b)
        b = b + step
        if np.abs(step).max() < 1e-9:
            break
    return float(b[0]), float(b[1])


def fit(docs: DataFrame, labels: DataFrame, text_col: str = "text", label_col: str = "quality") -> Model:
    """The model, from labelled rows that are not held out. No such rows, or one class only: a constant score.

    Repeated labels of an id count as the largest; of documents sharing an id, one is taken.
    """
    known = labels.filter(F.col(label_col).isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    known = known.groupBy("doc_id").agg(F.max(F.when(F.col(label_col) > 0, 1).otherwise(0)).alias("label"))
    known = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(SAMPLE_ROWS)  # bounded, so it may be broadcast
    texts_of = docs.select("doc_id", F.col(text_col).cast("string").alias("text"))
    rows = texts_of.join(F.broadcast(known), "doc_id").select("doc_id", "label", "text")
    kind = rows.schema["doc_id"].dataType.simpleString()
    found = rows.mapInArrow(_feature_rows, f"doc_id {kind}, label int, features binary").groupBy("doc_id").agg(F.min(F.struct("label", "features")).alias("x"))
    found = written(found.select(F.xxhash64("doc_id").alias("k"), "x.label", "x.features"), "quality-sample")
    sizes = found.select("k", (F.octet_length("features") / 4).cast("long").alias("n")).toArrow().sort_by("k")  # at most SAMPLE_ROWS rows
    fits = np.cumsum(sizes.column("n").to_numpy()) <= SAMPLE_FEATURES
    last = int(sizes.column("k")[int(fits.sum()) - 1].as_py()) if fits.any() else None
    table = found.filter(F.lit(False) if last is None else F.col("k") <= last).toArrow().sort_by("k")
    discard(found)
    label = table.column("label").to_numpy()
    grams = [np.frombuffer(x, np.int32) for x in table.column("features").to_pylist()]
    if not len(label) or label.min() == label.max():
        return Model(np.zeros(FEATURES), np.zeros(FEATURES), 0.0, 0.0, 0.0 if not len(label) else 6.0 if label[0] else -6.0)
    train = np.arange(len(label)) % CALIBRATE != 0 if len(label) >= 40 else np.ones(len(label), bool)
    if label[train].min() == label[train].max():
        train[:] = True
    counts = [np.full(FEATURES, SMOOTHING) for _ in range(2)]
    for i in np.flatnonzero(train):
        counts[label[i]][grams[i]] += 1
    ratio = np.log(counts[1] / counts[1].sum()) - np.log(counts[0] / counts[0].sum())
    ratio[(counts[0] + counts[1]) <= 2 * SMOOTHING] = 0.0  # unseen: no say
    values = [ratio[g] / max(1e-12, np.sqrt((ratio[g] ** 2).sum())) for g in grams]
    sign = np.where(label > 0, 1.0, -1.0)
    at = np.flatnonzero(train)
    w, bias, _ = descend([grams[i] for i in at], [values[i] for i in at], sign[at])
    test = ~train if (~train).any() and len(set(label[~train])) == 2 else train
    margin = np.array([w[grams[i]] @ values[i] + bias for i in np.flatnonzero(test)])
    slope, shift = logistic(margin, label[test] > 0)
    return Model((w * ratio).astype(np.float32), (ratio**2).astype(np.float32), bias, slope, shift)


def _scored(docs: DataFrame, model: Model, text_col: str) -> DataFrame:
    """docs and __score, in one pass over whole rows."""
    from pyspark.sql.types import DoubleType, StructField, StructType

    settle(docs.sparkSession)  # the sample is gone
    shared, at = docs.sparkSession.sparkContext.broadcast(model), docs.columns.index(text_col)

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column = texts(batch.column(at))
            out = np.zeros(len(column))
            for lo, hi, owner, feature in features(column):
                out[lo:hi] = shared.value.scores(hi - lo, owner, feature)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out)], schema=pa.schema([*batch.schema, pa.field("__score", pa.float64())]))
        tidy()

    return docs.mapInArrow(score, StructType([*docs.schema.fields, StructField("__score", DoubleType())]))


def classify(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted of every document.

    Null text counts as empty, which has a score too; repeated rows are scored each; an empty table gives no rows; other
    columns are not read.
    """
    source = docs.select("doc_id", F.col("text").cast("string").alias("text"))
    scored = _scored(source, fit(docs, labels), "text")
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), F.col("__score").alias("score"), (F.col("__score") >= THRESHOLD).cast("int").alias("predicted"))


def keep_good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """docs without those that the classifier rejects; same columns."""
    return _scored(docs, fit(docs, labels), "text").filter(F.col("__score") >= THRESHOLD).drop("__score")
