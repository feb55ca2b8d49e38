"""Quality classifier with supervised subword embeddings.

Hashed words, pairs of neighbouring words and character n-grams have learned
vectors; a document is their average, and a softmax layer gives the label's
probability. Vectors and layer are trained together by stochastic gradient descent
in numpy with a step that falls to zero. No feature is made by hand for a kind of
document: whatever tells the labels apart is learned from hashed n-grams alone.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import bounded_batches, code_points, field, lean, pieces, stratified

BITS = 15
BUCKETS = 1 << BITS
DIMENSIONS = 8
#: Lengths of character n-grams.
ORDERS = (2, 3, 4, 5)
#: Labelled documents used for fitting, about.
FIT_ROWS = 6000
#: Small samples are passed over more often, up to about so many documents.
LEAST_STEPS = 40_000
_P = np.uint64(0x100000001B3)
_K = np.uint64(0x9E3779B97F4A7C15)


def features(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(text, bucket) of every word, word pair and n-gram of characters, case and marks kept."""
    points, owner = code_points(texts)
    value = points.astype(np.uint64) + np.uint64(1)
    docs, slots = [], []
    gram = np.zeros(len(value), np.uint64)
    for n in range(1, max(ORDERS) + 1):
        size = len(value) - n + 1
        if size <= 0:
            break
        gram = gram[:size] * _P + value[n - 1 :]
        if n in ORDERS:
            ok = owner[:size] == owner[n - 1 :]
            docs.append(owner[:size][ok])
            slots.append((((gram + np.uint64(n)) * _K) >> np.uint64(64 - BITS))[ok])
    solid = ~(((points >= 9) & (points <= 13)) | (points == 32))  # each text ends in a line feed
    edge = np.diff(np.concatenate([[False], solid]).astype(np.int8))
    start = np.flatnonzero(edge == 1)
    stop = np.flatnonzero(edge == -1)
    if len(start):
        weighted = value * _K
        weighted = (weighted ^ (weighted >> np.uint64(29))) * _P
        where = np.arange(len(value), dtype=np.uint64)
        first = np.repeat(start, stop - start)
        inside = np.flatnonzero(solid)
        term = weighted[inside] * (np.uint64(2) * (where[inside] - first.astype(np.uint64)) + np.uint64(1))
        hashed = np.add.reduceat(term, np.concatenate([[0], np.cumsum(stop - start)[:-1]]))
        docs.append(owner[start])
        slots.append((hashed * _K) >> np.uint64(64 - BITS))
        pair = np.flatnonzero(owner[start[1:]] == owner[start[:-1]])
        docs.append(owner[start[pair]])
        slots.append(((hashed[pair] * _P + hashed[pair + 1]) * _K) >> np.uint64(64 - BITS))
    if not docs:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return np.concatenate(docs), np.concatenate(slots).astype(np.int64)


@dataclass
class Model:
    """Margin of label 1 per bucket (vector times the layer's difference), and bias."""

    margin: np.ndarray
    bias: float

    def score(self, texts: list[str]) -> np.ndarray:
        """Probability of label 1; a text without features gets the bias alone."""
        doc, slot = features(texts)
        total = np.bincount(doc, weights=self.margin[slot], minlength=len(texts))
        n = np.bincount(doc, minlength=len(texts))
        return 1 / (1 + np.exp(-np.clip(total / np.maximum(n, 1) + self.bias, -40, 40)))


def fit_rows(texts: list[str], labels: list[int], epochs: int, rate: float, seed: int) -> Model:
    """Train in memory on sparse rows of feature shares, one document a step.

    The step falls in a straight line to zero. A document's vectors share its
    gradient by their shares in the average.
    """
    rng = np.random.default_rng(seed)
    rows = []
    for at in range(0, len(texts), 64):
        part = texts[at : at + 64]
        doc, slot = features(part)
        code, n = np.unique(doc * BUCKETS + slot, return_counts=True)
        cut = np.searchsorted(code, np.arange(len(part) + 1) * BUCKETS)
        for a, b in zip(cut[:-1], cut[1:]):
            share = n[a:b].astype(np.float32)
            rows.append(((code[a:b] % BUCKETS).astype(np.int32), share / max(share.sum(), 1)))
    vec = rng.uniform(-1 / DIMENSIONS, 1 / DIMENSIONS, (BUCKETS, DIMENSIONS)).astype(np.float32)
    layer, bias = np.zeros((2, DIMENSIONS), np.float32), np.zeros(2, np.float32)
    epochs = max(epochs, math.ceil(LEAST_STEPS / len(rows)))
    steps, done = epochs * len(rows), 0
    for _ in range(epochs):
        for r in rng.permutation(len(rows)):
            at, share = rows[r]
            step, done = np.float32(rate * (1 - done / steps)), done + 1
            held = vec[at]
            hidden = share @ held
            z = layer @ hidden + bias
            p = np.exp(z - z.max())
            p /= p.sum()
            p[labels[r]] -= 1
            back = p @ layer
            layer -= step * p[:, None] * hidden
            bias -= step * p
            vec[at] = held - (step * share)[:, None] * back
    return Model((vec @ (layer[1] - layer[0])).astype(np.float64), float(bias[1] - bias[0]))


def fit(docs: DataFrame, labels: DataFrame, fit_total: int = FIT_ROWS, epochs: int = 6, rate: float = 0.5, seed: int = 5, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality") -> Model:
    """Fit on about `fit_total` labelled documents, half of each label, chosen by a hash of the id.

    Labels other than 0 and 1 (nulls too) are not used; of several labels of one id
    the smallest counts. The ids of the sample, bounded by `fit_total`, are
    broadcast to the scan of the texts; one task trains, the model comes to the
    driver. Without labelled documents the score is 0.5 for all.
    """
    bounded_batches(docs.sparkSession)
    ids = labels.filter(F.col(label_col).isin(0, 1)).groupBy(F.col(id_col).alias("_id")).agg(F.min(label_col).cast("int").alias("_label")).filter("_id IS NOT NULL")
    sample = stratified(ids, "_label", fit_total, seed, "_id")
    texts = docs.select(F.col(id_col).alias("_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("_text"))
    rows = texts.join(F.broadcast(sample), "_id").select(F.col("_id").cast("string").alias("_id"), "_label", "_text")

    def train(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = sorted({(r["_id"], r["_label"], r["_text"]) for b in batches for r in b.to_pylist()})
        if got:
            m = fit_rows([g[2] for g in got], [g[1] for g in got], epochs, rate, seed)
            yield pa.RecordBatch.from_arrays([pa.array([m.margin.tobytes()], pa.binary()), pa.array([m.bias])], names=["margin", "bias"])

    found = rows.repartition(1).mapInArrow(lean(train), "margin binary, bias double").collect()
    return Model(np.frombuffer(bytes(found[0].margin), np.float64), found[0].bias) if found else Model(np.zeros(BUCKETS), 0.0)


def score(docs: DataFrame, model: Model, threshold: float = 0.3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, score, predicted) per row; a null text counts as empty and gets the bias alone."""
    bounded_batches(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    base = docs.select(F.col(id_col).alias("_id"), F.col(text_col).cast("string").alias("_text"))
    out = T.StructType([T.StructField(id_col, field(base, "_id").dataType), T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for part in pieces(whole, "_text", limit=1 << 20):
                p = shared.value.score([t or "" for t in part.column(1).to_pylist()])
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(p, pa.float64()), pa.array((p >= threshold).astype(np.int32))], names=out.names)

    return base.mapInArrow(lean(run), out)
