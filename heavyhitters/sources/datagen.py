"""Synthetic items under power laws, reproducible in any SQL engine.

A row number and a seed give a hash in [0, M); it is looked up in the law's
cumulative integer weights. Exponents are multiples of one half, so that weights
need only square roots, products and quotients, which are rounded alike everywhere.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.sketches import PRIME, portable_hash, portable_hash_range, portable_hash_sql
from . import packed

#: Cumulative weights stay under this, so that hash * weight fits 64 bits.
TOTAL = 1 << 31


def exponent(rho: float, mode: str = "rho") -> float:
    """The law's exponent: the skew itself over a finite universe, or the skew + 1."""
    if mode not in ("rho", "rho_plus_1"):
        raise ValueError("mode must be rho or rho_plus_1")
    s = rho + (mode == "rho_plus_1")
    if (2 * s) % 1:
        raise ValueError("exponents are multiples of 0.5")
    return s


def powered(x: np.ndarray, s: float) -> np.ndarray:
    """x ** s for s a multiple of one half, by products and a square root."""
    out = np.ones_like(x)
    for _ in range(int(s)):
        out = out * x
    return out * np.sqrt(x) if s % 1 else out


def zeta(s: float, q: float = 1.0, terms: int = 100_000) -> float:
    """Sum of (j + q) ** -s over j >= 0: a partial sum and the integral of the rest."""
    if s <= 1:
        raise ValueError("the series diverges for s <= 1")
    j = np.arange(terms, dtype=float) + q
    last = terms + q
    return float((j**-s).sum()) + last ** (1 - s) / (s - 1) + last**-s / 2


def scale(s: float, universe: int, a: float) -> int:
    """A whole factor of the weights that keeps their sum under TOTAL."""
    j = np.arange(1, universe + 1, dtype=float)
    return int(TOTAL * 0.9 / float((1.0 / powered(j + a, s)).sum()))


@lru_cache(maxsize=4)
def cumulative(s: float, universe: int, a: float) -> np.ndarray:
    """Cumulative integer weights floor(factor / (j + a) ** s), j = 1..universe."""
    j = np.arange(1, universe + 1, dtype=float)
    out = np.cumsum(np.floor(scale(s, universe, a) / powered(j + a, s)).astype(np.int64))
    out.flags.writeable = False  # shared by all that a worker draws
    return out


def cdf(spark: SparkSession, s: float, universe: int, a: float = 0.0) -> DataFrame:
    """(item, lo, hi): the half-open range of each item, for lookups by a range join."""
    hi = cumulative(s, universe, a)
    table = pa.table({"item": np.arange(1, universe + 1), "lo": np.concatenate([[0], hi[:-1]]), "hi": hi})
    return spark.createDataFrame(table).filter("hi > lo")


class Law:
    """Draws items by cumulative weights; a guide says where to start for each 2**SHIFT hashes.

    A hash is compared with the first hash of the next item, so it is not scaled to the
    weights. Before, a small guide that a core's cache holds has the longer stretches of
    hashes that give one item.
    """

    #: Items that are tried from the guide's on, before a search.
    SHIFT, LONG, STEPS = 10, 14, 4

    def __init__(self, s: float, universe: int, a: float):
        self.bounds = cumulative(s, universe, a)
        self.ends = -(-self.bounds * PRIME // int(self.bounds[-1]))  # hashes from here on give later items
        at = lambda edges: np.searchsorted(self.ends, edges, side="right").astype(np.int32)
        self.guide = at(np.arange((PRIME >> self.SHIFT) + 1, dtype=np.int64) << self.SHIFT)
        edges = np.arange((PRIME >> self.LONG) + 2, dtype=np.int64) << self.LONG
        self.sure = np.where(at(edges[:-1]) == at(edges[1:] - 1), at(edges[:-1]), -1)

    def drawn(self, hashed: np.ndarray) -> np.ndarray:
        """Items of hashed row numbers."""
        found = self.sure[hashed >> self.LONG].astype(np.int64)
        rest = np.flatnonzero(found < 0)
        found[rest] = self.guide[hashed[rest] >> self.SHIFT]
        rest = rest[self.ends[found[rest]] <= hashed[rest]]
        for _ in range(self.STEPS):
            if not len(rest):
                break
            found[rest] += 1
            rest = rest[self.ends[found[rest]] <= hashed[rest]]
        found[rest] = np.searchsorted(self.ends, hashed[rest].astype(np.int64), side="right")
        return found + 1


@lru_cache(maxsize=4)
def law(s: float, universe: int, a: float) -> Law:
    """The law, kept by the worker for the next batches and tasks."""
    return Law(s, universe, a)


def drawn(bounds: np.ndarray, hashed: np.ndarray) -> np.ndarray:
    """Items of hashed row numbers by the law's cumulative weights."""
    return np.searchsorted(bounds, hashed * int(bounds[-1]) // PRIME, side="right") + 1


#: Items that are drawn at a time, and of these at once, as arrays that lie in a core's cache.
CHUNK, PIECE = 1 << 17, 1 << 15


def chunks(s: float, universe: int, a: float, seed: int, start: int, stop: int) -> Iterator[np.ndarray]:
    """Items of the row numbers start..stop - 1, in order, CHUNK at a time."""
    known = law(s, universe, a)
    for at in range(start, stop, CHUNK):
        end = min(at + CHUNK, stop)
        out = np.empty(end - at, np.int64)
        for x in range(at, end, PIECE):
            y = min(x + PIECE, end)
            out[x - at : y - at] = known.drawn(portable_hash_range(x, y, seed))
        yield out


def packed_power_law(spark: SparkSession, n: int, rho: float, universe: int, seed: int, a: float, partitions: int, narrow: bool = False) -> DataFrame:
    """(items): the items of shifted_power_law in their order, CHUNK to a row as unsigned 32-bit numbers.

    Partition b has the row numbers floor(b * n / p) and on, as a range of n has. With
    `narrow`, numbers below 255 take a byte (see packed.narrowed).
    """
    s = exponent(rho)
    if not 1 <= universe < 1 << 32:
        raise ValueError("items are unsigned 32-bit numbers")

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for b in batch.column(0).to_pylist():
                for items in chunks(s, universe, a, seed, b * n // partitions, (b + 1) * n // partitions):
                    row = packed.narrowed(items) if narrow else items.astype("<u4").tobytes()
                    yield pa.RecordBatch.from_arrays([pa.array([row], pa.binary())], names=["items"])

    return spark.range(0, partitions, 1, partitions).mapInArrow(make, "items binary")


def shifted_power_law(spark: SparkSession, n: int, rho: float, universe: int = 100_000, seeds: Sequence[int] = (1,), a: float = 0.5, mode: str = "rho", partitions: int | None = None) -> DataFrame:
    """(seed, id, item): n items per seed with probability proportional to (item + a) ** -s.

    Items are at most `universe`, within unsigned 32 bits. The same seed gives the
    same items to every method. The law's table, `universe` numbers, is rebuilt in
    each task; rows are made where they are used, without a shuffle.
    """
    s = exponent(rho, mode)
    if not 1 <= universe < 1 << 32:
        raise ValueError("items are unsigned 32-bit numbers")

    def look_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = law(s, universe, a)
        for batch in batches:
            item = known.drawn(batch.column(2).to_numpy())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(item, pa.int64())], names=["seed", "id", "item"])

    # per seed another mixing of the row number: the hash takes the seed as its offset
    rows = spark.range(0, n, 1, partitions).select(F.explode(F.array(*[F.struct(F.lit(int(x)).alias("seed"), portable_hash(F.col("id"), int(x)).alias("h")) for x in seeds])).alias("r"), "id")
    return rows.select("r.seed", "id", "r.h").mapInArrow(look_up, "seed int, id long, item long")


def power_law(spark: SparkSession, n: int, rho: float, universe: int = 100_000, seeds: Sequence[int] = (1,), mode: str = "rho") -> DataFrame:
    """The plain law: no shift."""
    return shifted_power_law(spark, n, rho, universe, seeds, 0.0, mode)


def sql_items(n: str, rho: float, universe: int, seeds: Sequence[int], a: float, mode: str = "rho", ids: str | None = None) -> str:
    """SQL of the same (seed, id, item); `n` is a scalar query, or `ids` a query of the ids instead."""
    ids = ids or f"SELECT range AS id FROM range(({n})::BIGINT)"
    s = exponent(rho, mode)
    x = f"(j + {a!r}::DOUBLE)"
    power = "*".join(["1.0::DOUBLE", *([x] * int(s)), *([f"sqrt({x})"] if s % 1 else [])])
    hashes = " UNION ALL ".join(f"SELECT {x} AS seed, id, ({portable_hash_sql('id', x)})::BIGINT AS h FROM ids" for x in map(int, seeds))
    return f"""SELECT seed, id, item FROM (
WITH ids AS ({ids}), hs AS ({hashes}),
w AS (SELECT j AS item, floor({scale(s, universe, a)} / ({power}))::BIGINT AS w FROM (SELECT range AS j FROM range(1, {universe + 1}))),
c AS (SELECT item, sum(w) OVER (ORDER BY item) - w AS lo FROM w WHERE w > 0), t AS (SELECT sum(w)::BIGINT AS total FROM w),
m AS (SELECT seed, id, h * total // {PRIME} AS x, NULL AS item FROM hs, t UNION ALL SELECT NULL, NULL, lo, item FROM c)
SELECT seed, id, item FROM (SELECT seed, id, max(item) OVER (ORDER BY x, id NULLS FIRST ROWS UNBOUNDED PRECEDING) AS item FROM m) WHERE id IS NOT NULL)"""
