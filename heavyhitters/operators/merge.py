"""Merging summaries: pairwise, in a tree, or all at once.

Empty summaries (a header without counters) change nothing. Of equal estimates the
smaller items stay, null before all others and NaN after them.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..model import Summaries, as_column, match
from .local import keep_largest, with_headers

#: A summary's smallest estimate, or 0 if it is not full.
Minimum = Column | DataFrame | int


def combine(one: DataFrame, other: DataFrame, min_one: Minimum, min_other: Minimum) -> DataFrame:
    """(item, est, err) of both summaries: where an item is missing, that side's minimum stands in.

    At most twice k rows; not cut yet. Minima are numbers, columns, or frames of one
    row with the column min_est (a block's header). An empty summary has minimum 0;
    null is an item that both sides may have.
    """
    a = one.select("item", F.col("est").alias("e1"), F.col("err").alias("r1"))
    b = other.select("item", F.col("est").alias("e2"), F.col("err").alias("r2"))
    both = match(a, b, ["item"], "full_outer")
    minima = []
    for side, m in enumerate((min_one, min_other)):
        if isinstance(m, DataFrame):
            both, m = both.crossJoin(F.broadcast(m.select(F.col("min_est").alias(f"_m{side}")))), F.col(f"_m{side}")  # one row
        minima.append(m if isinstance(m, Column) else F.lit(m))
    m1, m2 = minima
    return both.select("item", (F.coalesce("e1", m1) + F.coalesce("e2", m2)).cast("bigint").alias("est"), (F.coalesce("r1", m1) + F.coalesce("r2", m2)).cast("bigint").alias("err"))


def combine_cols(map_one: str, min_one: str, map_other: str, min_other: str) -> Column:
    """The same within a row: maps item -> struct(est, err), for stored summaries side by side."""
    pad = lambda x, m: F.coalesce(x, F.struct(F.col(m).alias("est"), F.col(m).alias("err")))

    def add(_, x: Column, y: Column) -> Column:
        a, b = pad(x, min_one), pad(y, min_other)
        return F.struct((a.est + b.est).alias("est"), (a.err + b.err).alias("err"))

    return F.map_zip_with(map_one, map_other, add)


def truncate_map(counters: Column, k: int) -> Column:
    """The k largest entries of a map of counters, as an array of (est, item, err), largest first."""
    rows = F.transform(F.map_entries(counters), lambda e: F.struct(e.value.est.alias("est"), e.key.alias("item"), e.value.err.alias("err")))
    before = lambda a, b: F.when(a.est > b.est, -1).when(a.est < b.est, 1).when(a.item < b.item, -1).when(a.item > b.item, 1).otherwise(0)
    return F.slice(F.array_sort(rows, before), 1, k)


def truncate(counters: DataFrame, k: int, partition: Sequence[str] = ()) -> DataFrame:
    """The k largest counters, ties to smaller items (of each partition)."""
    return keep_largest(counters, k, partition)


def merge_pair(one: DataFrame, other: DataFrame, min_one: Minimum, min_other: Minimum, k: int) -> DataFrame:
    """One reduction step: combine, then keep the k largest."""
    return truncate(combine(one, other, min_one, min_other), k)


def _level(s: Summaries, parent: Column) -> Summaries:
    """Merge the blocks of each parent at once.

    Every missing counter is padded with its block's minimum, so an item's
    estimate is the sum of all minima plus what its counters exceed theirs by: one
    aggregation by item, whatever the number of blocks.
    """
    keys = s.keys
    group = [*keys, "block_id"]
    totals = s.headers.withColumn("block_id", parent).groupBy(*group).agg(F.sum("n").alias("n"), F.sum("min_est").alias("pad"))
    over = s.counters.withColumn("block_id", parent).groupBy(*group, "item").agg(F.sum(F.col("est") - F.col("min_est")).alias("_e"), F.sum(F.col("err") - F.col("min_est")).alias("_r"))
    padded = over.join(totals.select(*group, "pad"), group).select(*group, "item", (F.col("_e") + F.col("pad")).alias("est"), (F.col("_r") + F.col("pad")).alias("err"))
    return with_headers(keep_largest(padded, s.k, group, most=s.most), totals.drop("pad"), s.k, keys, s.most)


def tree(s: Summaries, blocks: int, fan_in: int = 2) -> Summaries:
    """Reduce blocks 0..blocks-1 level by level, `fan_in` neighbours at a time.

    An unpaired block passes through. The plan is static and grows by one aggregation
    and one ranking a level, ceil(log(blocks)) in all: a block's minimum travels in its
    first counter, so a level reads nothing but the counters of the level below. The
    number of items of the root comes from the headers of the blocks.
    """
    keys, group = s.keys, s.block
    whole = Window.partitionBy(*group)
    order = whole.orderBy(F.desc("est"), F.asc("item"))
    first = lambda rows: rows.withColumn("_pad", F.when(F.col("_rank") == 1, F.col("min_est")).otherwise(F.lit(0)))
    up = lambda c: F.call_function("div", c.cast("bigint"), F.lit(fan_in).cast("bigint")).cast("int")
    rows = first(s.counters.withColumn("_rank", F.row_number().over(order)))
    root, size = F.col("block_id"), as_column(s.k)
    while blocks > 1:
        over = rows.withColumn("block_id", up(F.col("block_id"))).groupBy(*group, "item")
        over = over.agg(F.sum(F.col("est") - F.col("min_est")).alias("_e"), F.sum(F.col("err") - F.col("min_est")).alias("_r"), F.sum("_pad").alias("_p")).withColumn("_d", F.sum("_p").over(whole))
        padded = over.select(*group, "item", (F.col("_e") + F.col("_d")).alias("est"), (F.col("_r") + F.col("_d")).alias("err"))
        kept = padded.withColumn("_rank", F.row_number().over(order)).filter(F.col("_rank") <= size)
        full = F.count("*").over(whole) == size
        rows = first(kept.withColumn("min_est", F.when(full, F.min("est").over(whole)).otherwise(F.lit(0)).cast("bigint")))
        root, blocks = up(root), -(-blocks // fan_in)
    totals = s.headers.withColumn("block_id", root).groupBy(*group).agg(F.sum("n").cast("bigint").alias("n"))
    return with_headers(rows.select(*group, "item", "est", "err"), totals, s.k, keys, s.most)


def flat(s: Summaries) -> Summaries:
    """Merge all blocks in one aggregation; never a larger estimate than the tree's.

    Without keys, counters carry `n` along, so that a report reads nothing but them.
    """
    if s.keys:
        return _level(s, F.lit(0))
    totals = s.headers.agg(F.sum("n").alias("n"), F.coalesce(F.sum("min_est"), F.lit(0)).alias("pad"))
    over = s.counters.groupBy("item").agg(F.sum(F.col("est") - F.col("min_est")).alias("_e"), F.sum(F.col("err") - F.col("min_est")).alias("_r"))
    padded = over.crossJoin(F.broadcast(totals)).select("item", (F.col("_e") + F.col("pad")).alias("est"), (F.col("_r") + F.col("pad")).alias("err"), F.coalesce("n", F.lit(0)).cast("bigint").alias("n"))
    zero, size = F.lit(0).cast("bigint"), as_column(s.k)
    kept = keep_largest(padded, s.k, [])
    whole = Window.partitionBy("block_id")  # at most k rows
    full = F.count("*").over(whole) == size
    counters = kept.withColumn("block_id", F.lit(0)).withColumn("min_est", F.when(full, F.min("est").over(whole)).otherwise(zero))
    stats = kept.agg(F.coalesce(F.max("n"), zero).alias("n"), F.count("*").alias("nz"), F.min("est").alias("_low"), F.coalesce(F.sum("est"), zero).alias("total_est"))
    least = F.when(F.col("nz") == size, F.col("_low")).otherwise(zero)
    headers = stats.select(F.lit(0).alias("block_id"), "n", size.cast("bigint").alias("k"), "nz", least.alias("min_est"), "total_est")
    return Summaries(counters.select("block_id", "item", "est", "err", "min_est", "n"), headers, s.k, [], s.most)


def disjoint(s: Summaries) -> Summaries:
    """Merge summaries whose items are disjoint (dealt by item): nothing to pad.

    An item without a counter is in one block only, so the largest minimum bounds it.
    """
    group = [*s.keys, "block_id"]
    zero = F.lit(0)
    totals = s.headers.withColumn("block_id", zero).groupBy(*group).agg(F.sum("n").alias("n"), F.max("min_est").alias("_bound"))
    kept = keep_largest(s.counters.drop("min_est").withColumn("block_id", zero), s.k, group, most=s.most)
    merged = with_headers(kept, totals.drop("_bound"), s.k, s.keys, s.most)
    bound = totals.select(*group, "_bound")
    raise_min = lambda df: df.join(bound, group).withColumn("min_est", F.greatest("min_est", "_bound")).drop("_bound")
    return Summaries(raise_min(merged.counters), raise_min(merged.headers), s.k, s.keys, s.most)


def from_counters(counters: DataFrame, n: Column | int, k: int) -> Summaries:
    """A summary of its own from (item, est, err) and the number of items."""
    n = n if isinstance(n, Column) else F.lit(n)
    spark = counters.sparkSession
    total = spark.range(1).select(F.lit(0).alias("block_id"), n.cast("bigint").alias("n"))
    return with_headers(counters.withColumn("block_id", F.lit(0)), total, k, [])
