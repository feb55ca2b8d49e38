"""Related counter methods and sketches.

Counter methods take null as an item. Count-min, count sketch and Spark's own
sketches do not count nulls; empty tables give no rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .baseline import shrink
from .kernels import DecrementKernel, LossyKernel
from ..sources.stores import kept
from .local import from_rows, in_partitions

#: The modulus of the portable hashes; multipliers and offsets follow from the row number.
PRIME = 2147483647


def portable_hash(x: Column, seed: int) -> Column:
    """Two multiplicative rounds on a bigint with the bits folded after each: the same in any SQL engine.

    Without the folds a hash of row numbers would be a lattice, far more even than chance.
    """
    a, c = 48271 + 2 * seed, 11 + 7919 * seed
    once = (F.pmod(x, F.lit(PRIME)) * a + c) % PRIME
    once = once.bitwiseXOR(F.shiftright(once, 13))
    twice = (once * 69621 + 13 * seed + 5) % PRIME
    return (twice.bitwiseXOR(F.shiftright(twice, 16)) * 40692 + seed) % PRIME


def _reduced(x: np.ndarray) -> np.ndarray:
    """x % PRIME for 0 <= x < 2**62, by shifts, as the modulus is 2**31 - 1."""
    x = (x & PRIME) + (x >> 31)
    x = (x & PRIME) + (x >> 31)
    return np.where(x >= PRIME, x - PRIME, x)


def portable_hash_of(x: np.ndarray, seed: int) -> np.ndarray:
    """The same on 64-bit integers in memory."""
    once = _reduced(x % PRIME * (48271 + 2 * seed) + 11 + 7919 * seed)
    once = once ^ (once >> 13)
    twice = _reduced(once * 69621 + 13 * seed + 5)
    return _reduced((twice ^ (twice >> 16)) * 40692 + seed)


@lru_cache(maxsize=4)
def _steps(a: int, count: int) -> np.ndarray:
    """i * a % PRIME for i from 0 to count - 1."""
    out = (np.arange(count, dtype=np.int64) * a % PRIME).astype(np.uint32)
    out.flags.writeable = False
    return out


def _once(x: np.ndarray) -> np.ndarray:
    """x % PRIME for 32-bit 0 <= x < 2 * PRIME: below zero wraps to the larger number."""
    return np.minimum(x, x - np.uint32(PRIME))


def portable_hash_range(start: int, stop: int, seed: int) -> np.ndarray:
    """portable_hash_of(np.arange(start, stop), seed) as 32-bit numbers, for start >= 0 and 0 <= seed < 2**31."""
    a, c = 48271 + 2 * seed, 11 + 7919 * seed
    x = _once(_steps(a, stop - start) + np.uint32((start * a + c) % PRIME))
    for by, factor, plus in ((13, 69621, 13 * seed + 5), (16, 40692, seed)):
        y = (x ^ (x >> by)).astype(np.uint64) * factor + plus
        x = _once(((y & PRIME) + (y >> 31)).astype(np.uint32))
    return x


def portable_hash_sql(x: str, seed: int) -> str:
    """The same as an SQL expression; x is from 0 on."""
    once = f"((({x}) % {PRIME}) * {48271 + 2 * seed} + {11 + 7919 * seed}) % {PRIME}"
    twice = f"(xor({once}, ({once}) >> 13) * 69621 + {13 * seed + 5}) % {PRIME}"
    return f"(xor({twice}, ({twice}) >> 16) * 40692 + {seed}) % {PRIME}"


def decrement(df: DataFrame, item: str, k: int) -> DataFrame:
    """(item, est): the decrement-all method per partition, merged by adding and cutting to k - 1.

    true - floor(n/k) <= est <= true for every item, 0 standing for a missing counter.
    """
    s = from_rows(in_partitions(df, item, k, DecrementKernel), k)
    added = s.counters.groupBy("item").agg(F.sum("est").alias("est")).withColumn("block_id", F.lit(0))
    return shrink(added, k, ["block_id"]).filter("est > 0").select("item", "est")


def lossy_counting(df: DataFrame, item: str, eps: float) -> DataFrame:
    """(item, est, deficit): est <= true <= est + deficit + what other partitions pruned.

    Per partition; merged, `deficit` sums the item's own and, for each partition that
    lacks it, that partition's whole bound floor(eps * n_i).
    """
    rows = kept(in_partitions(df, item, 2, lambda _: LossyKernel(eps)), "lossy")
    s = from_rows(rows, 2)
    bound = F.floor(F.col("n") * F.lit(eps)).cast("bigint")
    counters = s.counters.join(s.headers.select("block_id", bound.alias("own")), "block_id")
    total = s.headers.agg(F.sum(bound).alias("all_bounds"))
    merged = counters.groupBy("item").agg(F.sum("est").alias("est"), F.sum("err").alias("d"), F.sum("own").alias("own"))
    return merged.crossJoin(F.broadcast(total)).select("item", "est", (F.col("d") + F.col("all_bounds") - F.col("own")).alias("deficit"))


def _cells(df: DataFrame, item: str, depth: int, width: int) -> DataFrame:
    """(item, cnt, row, bucket, sign): each distinct item in its cell of every row."""
    counts = df.filter(F.col(item).isNotNull()).groupBy(F.col(item).cast("bigint").alias("item")).agg(F.count("*").alias("cnt"))
    rows = [F.struct(F.lit(r).alias("row"), (portable_hash(F.col("item"), 2 * r) % width).alias("bucket"), (F.lit(1) - 2 * (portable_hash(F.col("item"), 2 * r + 1) % 2)).alias("sign")) for r in range(depth)]
    return counts.select("item", "cnt", F.explode(F.array(*rows)).alias("c")).select("item", "cnt", "c.*")


def count_min(df: DataFrame, item: str, eps: float, confidence: float) -> DataFrame:
    """(item, est) by a count-min sketch: true <= est, and est <= true + eps * n with the confidence.

    Items are integers. The sketch is ceil(e / eps) by ceil(ln(1 / (1 - confidence))) cells.
    """
    width, depth = math.ceil(math.e / eps), math.ceil(math.log(1 / (1 - confidence)))
    cells = _cells(df, item, depth, width)
    sketch = cells.groupBy("row", "bucket").agg(F.sum("cnt").alias("total"))
    return cells.join(sketch, ["row", "bucket"]).groupBy("item").agg(F.min("total").alias("est"))


def count_sketch(df: DataFrame, item: str, width: int, depth: int) -> DataFrame:
    """(item, est) by a signed sketch: the median over rows of sign * cell."""
    cells = _cells(df, item, depth, width)
    sketch = cells.groupBy("row", "bucket").agg(F.sum(F.col("cnt") * F.col("sign")).alias("total"))
    return cells.join(sketch, ["row", "bucket"]).groupBy("item").agg(F.median(F.col("total") * F.col("sign")).alias("est"))


def builtin_top_k(df: DataFrame, item: str, k: int, counters: int) -> DataFrame:
    """(item, est) of Spark's own approximate top-k."""
    top = df.agg(F.expr(f"approx_top_k({item}, {k}, {counters})").alias("t"))
    return top.select(F.explode("t").alias("c")).select(F.col("c.item").alias("item"), F.col("c.count").alias("est"))


def builtin_top_k_of_parts(df: DataFrame, part: str, item: str, k: int, counters: int) -> DataFrame:
    """(item, est): Spark's own sketches accumulated for each part, combined, then estimated.

    Its sketches of parts can be stored and combined later. Nulls are not counted;
    an empty table gives none.
    """
    parts = df.filter(F.col(item).isNotNull()).groupBy(part).agg(F.expr(f"approx_top_k_accumulate({item}, {counters})").alias("s"))
    top = parts.agg(F.expr(f"approx_top_k_estimate(approx_top_k_combine(s, {counters}), {k})").alias("t"))
    return top.select(F.explode("t").alias("c")).select(F.col("c.item").alias("item"), F.col("c.count").alias("est"))


def builtin_count_min(df: DataFrame, item: str, eps: float, confidence: float, seed: int) -> DataFrame:
    """(item, est) of every distinct bigint item, by Spark's own count-min sketch.

    The sketch is one binary row of fixed size; it is read with each row's own hash,
    item * a, folded to 31 bits, modulo the width. Nulls are not counted.
    """
    rows = df.filter(F.col(item).isNotNull())
    sketch = rows.agg(F.count_min_sketch(F.col(item).cast("bigint"), F.lit(eps), F.lit(confidence), F.lit(seed)).alias("sketch"))
    items = rows.select(F.col(item).cast("bigint").alias("item")).distinct()

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells = None
        for batch in batches:
            if not batch.num_rows:
                continue
            if cells is None:
                depth, width, factors, cells = read_count_min(batch.column(1)[0].as_py())
            x = batch.column(0).to_numpy()
            at = [hashed_row(x, a) % width for a in factors]
            least = np.min([cells[r, at[r]] for r in range(depth)], axis=0)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(least, pa.int64())], names=["item", "est"])

    return items.crossJoin(F.broadcast(sketch)).mapInArrow(read, "item long, est long")


def read_count_min(raw: bytes) -> tuple[int, int, np.ndarray, np.ndarray]:
    """(depth, width, factors, cells) of the binary form: version, total, depth, width, factors, cells, big-endian."""
    depth, width = (int(x) for x in np.frombuffer(raw, ">i4", 2, 12))
    factors = np.frombuffer(raw, ">i8", depth, 20).astype(np.int64)
    return depth, width, factors, np.frombuffer(raw, ">i8", depth * width, 20 + 8 * depth).reshape(depth, width)


def hashed_row(x: np.ndarray, factor: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        h = x * np.int64(factor)
        h = h + (h >> np.int64(32))
    return h & np.int64(0x7FFFFFFF)


def builtin_freq_items(df: DataFrame, item: str, support: float) -> DataFrame:
    """(item): Spark's own superset of the items over the support."""
    return df.freqItems([item], support).select(F.explode(F.col(f"{item}_freqItems")).alias("item"))
