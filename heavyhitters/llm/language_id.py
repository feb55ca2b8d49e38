"""Language identification by nearest centroids.

A document is a normalised TF-IDF vector of hashed character n-grams. Each
language has several centroids, found by spherical k-means over a bounded
sample of labelled documents; a document gets the language of the most similar
centroid, and is rejected when even that one is too far away. How far that is
depends on the number of letters: the limits lie between the similarities of
held-out documents to their own language and to the others.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import bounded_batches, code_points, field, lean, pieces, stratified

UNKNOWN = "und"
BITS = 13
BUCKETS = 1 << BITS
ORDERS = (1, 2, 3)
#: Texts of a dense block; bounds the memory of fitting and predicting.
ROWS = 128
#: Labelled documents used for fitting, over all languages, about.
FIT_ROWS = 6000
#: Held-out texts of a language whose beginnings set its limits, at most.
CALIBRATION = 500
#: Limits are for 1, 2, 4, ... letters.
CLASSES = 15
_SPACE = 32


@lru_cache(maxsize=1)
def _letters() -> np.ndarray:
    return np.fromiter((not 0xD800 <= i < 0xE000 and chr(i).isalpha() for i in range(0x110000)), bool, 0x110000)


def counts(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """n-gram counts (text, bucket) and the number of letters of each text.

    Texts are lower-cased; each run of other characters than letters is one space,
    which is part of n-grams with a letter.
    """
    points, owner = code_points([t.lower() for t in texts])
    letter = _letters()[points]
    keep = letter.copy()
    keep[1:] |= letter[:-1] | (owner[1:] != owner[:-1])  # the first of each run of others
    keep[:1] = True
    value = np.where(letter, points, _SPACE)[keep].astype(np.uint64)
    who, letter = owner[keep], letter[keep]
    out = np.zeros(len(texts) * BUCKETS, np.float32)
    gram = np.zeros(len(value), np.uint64)
    for n in range(1, max(ORDERS) + 1):
        size = len(value) - n + 1
        if size <= 0:
            break
        gram = gram[:size] * np.uint64(0x100000001B3) + value[n - 1 :]
        if n not in ORDERS:
            continue
        ok = who[:size] == who[n - 1 :]
        if n == 1:
            ok = letter
        slot = ((gram * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - BITS)).astype(np.int64)
        out += np.bincount((who[:size] * BUCKETS + slot)[ok], minlength=len(out)).astype(np.float32)
    return out.reshape(len(texts), BUCKETS), np.bincount(who[letter], minlength=len(texts))


def vectors(tf: np.ndarray, idf: np.ndarray) -> np.ndarray:
    """Normalised TF-IDF rows, with the square root of a count as its weight."""
    x = np.sqrt(tf) * idf
    return x / np.maximum(np.sqrt((x * x).sum(axis=1, keepdims=True)), 1e-12)


def letter_class(letters: np.ndarray) -> np.ndarray:
    """The class of a number of letters: 2**class is at most that number."""
    return np.minimum(np.log2(np.maximum(letters, 1)).astype(int), CLASSES - 1)


@dataclass
class Centroids:
    """The fitted model; its size is languages * clusters * buckets."""

    languages: list[str]  # of each centroid
    matrix: np.ndarray
    idf: np.ndarray
    least: np.ndarray  # similarity under which a centroid rejects, by class of letters

    def predict(self, texts: list[str]) -> tuple[list[str], np.ndarray, np.ndarray]:
        """Language, cosine similarity, rejected or not, of each text."""
        tf, letters = counts(texts)
        known = letters > 0
        if not self.languages:
            return [UNKNOWN] * len(texts), np.zeros(len(texts)), np.ones(len(texts), bool)
        near = vectors(tf, self.idf) @ self.matrix.T
        best = near.argmax(axis=1)
        score = np.clip(near[np.arange(len(texts)), best].astype(float), 0.0, 1.0)
        names = [self.languages[b] if k else UNKNOWN for b, k in zip(best, known)]
        return names, np.where(known, score, 0.0), ~known | (score < self.least[best, letter_class(letters)])


@dataclass
class _Packed:
    """A block of rows by their non-zero buckets, a small part of all."""

    size: int
    row: np.ndarray
    slot: np.ndarray
    value: np.ndarray

    def dense(self) -> np.ndarray:
        x = np.zeros((self.size, BUCKETS), np.float32)
        x[self.row, self.slot] = self.value
        return x

    def only_row(self, i: int) -> np.ndarray:
        x = np.zeros(BUCKETS, np.float32)
        x[self.slot[self.row == i]] = self.value[self.row == i]
        return x


def _pack(x: np.ndarray) -> _Packed:
    row, slot = np.nonzero(x)
    return _Packed(len(x), row.astype(np.uint16), slot.astype(np.uint16), x[row, slot])


def _near(x: list[_Packed], c: np.ndarray) -> np.ndarray:
    """Similarity of each row to each centre."""
    return np.concatenate([b.dense() @ c.T for b in x])


def _cluster(x: list[_Packed], k: int, rounds: int = 8) -> np.ndarray:
    """Spherical k-means; the first centres are each the row farthest from those before it."""
    mean = sum(b.dense().sum(axis=0) for b in x)
    centres = [mean / max(np.linalg.norm(mean), 1e-12)]
    starts = np.cumsum([0] + [b.size for b in x])
    near = _near(x, centres[0][None])[:, 0]
    while len(centres) < min(k, starts[-1]):
        far = int(near.argmin())
        at = int(np.searchsorted(starts, far, side="right")) - 1
        centres.append(x[at].only_row(far - int(starts[at])))
        near = np.maximum(near, _near(x, centres[-1][None])[:, 0])
    c = np.array(centres, np.float32)
    for _ in range(rounds):
        total, seen = np.zeros_like(c), np.zeros(len(c), bool)
        for b in x:
            dense = b.dense()
            own = (dense @ c.T).argmax(axis=1)
            total += (own == np.arange(len(c))[:, None]).astype(np.float32) @ dense
            seen[own] = True
        c[seen] = total[seen]
        c /= np.maximum(np.linalg.norm(c, axis=1, keepdims=True), 1e-12)
    return c


def _packed_rows(texts: list[str], languages: list[str]) -> tuple[dict[str, list[_Packed]], np.ndarray]:
    """Packed TF-IDF rows of each language, and the idf over all texts."""
    packed: dict[str, list[_Packed]] = {}
    having = np.zeros(BUCKETS)
    for name in sorted(set(languages)):
        own = [t for t, lang in zip(texts, languages) if lang == name]
        packed[name] = [_pack(counts(own[at : at + ROWS])[0]) for at in range(0, len(own), ROWS)]
        having += sum(np.bincount(b.slot, minlength=BUCKETS) for b in packed[name])
    idf = np.log((1 + len(texts)) / (1 + having)).astype(np.float32) + 1
    for blocks in packed.values():
        for b in blocks:
            b.value = vectors(b.dense(), idf)[b.row, b.slot]
    return packed, idf


def _beginnings(text: str) -> list[str]:
    """The text up to its first 1, 2, 4, ... letters, as far as it has so many."""
    at = np.flatnonzero(_letters()[code_points([text])[0]])
    return [text[: at[(1 << i) - 1] + 1] for i in range(CLASSES) if 1 << i <= len(at)]


def _limits(texts: list[str], languages: list[str], clusters: int, rejection: float) -> dict[str, np.ndarray]:
    """The limit of each language by class of letters.

    Each half of the texts is held against centroids of the other half. A limit lies
    `rejection` of the way from the similarity that 95 % of the other languages'
    beginnings stay under to the one that 99.5 % of its own reach. Classes that fewer
    than half of the texts reach take the limit of the class of fewer letters.
    """
    names = sorted(set(languages))
    own: dict[tuple[str, int], list[np.ndarray]] = {}
    other: dict[tuple[str, int], list[np.ndarray]] = {}
    order = {n: [t for t, lang in zip(texts, languages) if lang == n] for n in names}
    for half in (0, 1):
        # a language of one text stays in both halves
        train = [(t, n) for n in names for t in order[n][half::2] or order[n]]
        packed, idf = _packed_rows([t for t, _ in train], [n for _, n in train])
        centres = [_cluster(packed[n], clusters) for n in names]
        del packed
        every, starts = np.concatenate(centres), np.cumsum([0] + [len(c) for c in centres[:-1]])
        for n in names:
            held = [(i, part) for t in (order[n][1 - half :: 2] or order[n])[: CALIBRATION // 2] for i, part in enumerate(_beginnings(t))]
            held.sort(key=lambda x: x[0])
            for at in range(0, len(held), ROWS):
                size = np.array([i for i, _ in held[at : at + ROWS]])
                near = np.maximum.reduceat(vectors(counts([p for _, p in held[at : at + ROWS]])[0], idf) @ every.T, starts, axis=1)
                for i in set(size.tolist()):
                    for j, m in enumerate(names):
                        (own if m == n else other).setdefault((m, i), []).append(near[size == i, j])
    out = {}
    for n in names:
        limit = np.zeros(CLASSES)
        whole = sum(map(len, own[n, 0]))
        for i in range(CLASSES):
            inside = np.concatenate(own.get((n, i), [np.zeros(0)]))
            if len(inside) < max(1, whole / 2):
                limit[i] = limit[i - 1]
                continue
            low, outside = np.quantile(inside, 0.005), np.concatenate(other.get((n, i), [np.zeros(1)]))
            high = min(np.quantile(outside, 0.95), low)
            limit[i] = high + rejection * (low - high)
        out[n] = limit
    return out


def fit_rows(texts: list[str], languages: list[str], clusters: int, rejection: float) -> Centroids:
    """Fit in memory: centroids of all texts, limits of held-out halves."""
    limits = _limits(texts, languages, clusters, rejection)
    packed, idf = _packed_rows(texts, languages)
    names, rows = [], []
    for name, x in packed.items():
        c = _cluster(x, clusters)
        names += [name] * len(c)
        rows.append(c)
    return Centroids(names, np.concatenate(rows), idf, np.array([limits[n] for n in names]))


def fit(labelled: DataFrame, clusters: int = 4, fit_total: int = FIT_ROWS, rejection: float = 0.25, seed: int = 11, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> Centroids:
    """Fit on about `fit_total` rows, as many of each language, chosen by a hash of the id.

    `rejection` is where limits lie between the other languages' similarities (0) and the own ones (1).
    Rows with a null text or language are not used. The sample is gathered by one
    task; the model alone comes to the driver.
    """
    bounded_batches(labelled.sparkSession)
    rows = labelled.select(F.col(id_col).cast("string").alias("_id"), F.col(lang_col).cast("string").alias("_lang"), F.col(text_col).cast("string").alias("_text"))
    sample = stratified(rows.filter("_lang IS NOT NULL AND _text IS NOT NULL"), "_lang", fit_total, seed, "_id")

    def train(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = sorted({(r["_id"] or "", r["_lang"], r["_text"]) for b in batches for r in b.to_pylist()})
        got = [g for g in got if any(map(str.isalpha, g[2]))]
        if got:
            m = fit_rows([g[2] for g in got], [g[1] for g in got], clusters, rejection)
            yield pa.RecordBatch.from_arrays([pa.array([*m.languages, None]), pa.array([r.astype(np.float32).tobytes() for r in (*m.matrix, m.idf)], pa.binary()), pa.array([*m.least.tolist(), None], pa.list_(pa.float64()))], names=["name", "row", "least"])

    model = sample.repartition(1).mapInArrow(lean(train), "name string, row binary, least array<double>").collect()
    if not model:
        return Centroids([], np.zeros((0, BUCKETS), np.float32), np.ones(BUCKETS, np.float32), np.zeros((0, CLASSES)))
    row = lambda r: np.frombuffer(bytes(r.row), np.float32)
    named = [r for r in model if r.name is not None]
    return Centroids([r.name for r in named], np.array([row(r) for r in named]), row(next(r for r in model if r.name is None)), np.array([r.least for r in named]))


def predict(docs: DataFrame, model: Centroids, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, lang_pred, score, rejected) per row.

    `lang_pred` is a language of the model, `und` with score 0 for a text that is
    null or has no letter (or under a model fitted on nothing). `score` is the
    cosine similarity to the nearest centroid; `rejected` says that it is under the
    centroid's limit. Only id and text are read.
    """
    bounded_batches(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    base = docs.select(F.col(id_col).alias("_id"), F.col(text_col).cast("string").alias("_text"))
    out = T.StructType([T.StructField(id_col, field(base, "_id").dataType), T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType()), T.StructField("rejected", T.BooleanType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for part in pieces(whole, "_text", most_rows=ROWS):
                names, score, rejected = shared.value.predict([t or "" for t in part.column(1).to_pylist()])
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(names, pa.string()), pa.array(score, pa.float64()), pa.array(rejected, pa.bool_())], names=out.names)

    return base.mapInArrow(lean(run), out)


def keep_accepted(docs: DataFrame, model: Centroids, text_col: str = "text") -> DataFrame:
    """The rows, with all their columns, whose text the model does not reject."""
    bounded_batches(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            named = whole.rename_columns([f"c{i}" for i in range(whole.num_columns)])
            for part in pieces(named, f"c{at}", most_rows=ROWS):
                rejected = shared.value.predict([t or "" for t in part.column(at).to_pylist()])[2]
                yield part.filter(pa.array(~rejected)).rename_columns(whole.schema.names)

    return docs.mapInArrow(lean(run), docs.schema)
