"""Dealing a bag into disjoint blocks; any disjoint split sums to the same bag."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..model import as_item, unused
from ..sources.stores import kept


def block_of(position: Column, p: int, n: Column | int) -> Column:
    """Block of a 0-based position such that block b starts at floor(b * n / p)."""
    n = n if isinstance(n, Column) else F.lit(n)
    return F.call_function("div", (position + 1) * F.lit(p) - 1, n.cast("bigint")).cast("int")


def positions(df: DataFrame, order_by: Sequence[str]) -> DataFrame:
    """Adds the 0-based `pos` in the order, without bringing all rows to one task.

    Rows are range-partitioned, sorted and written once to the shared folder, as the
    bounds of the ranges must not be drawn twice; each range's offset is the number of
    rows before it. Rows that are equal in the order stand in any order, the same for
    all readers. A column `pos` of the input is replaced; others keep their names.
    """
    place, part, before = (unused(x, df.columns) for x in ("place", "range", "before"))
    ordered = df.repartitionByRange(*order_by).sortWithinPartitions(*order_by).withColumn(place, F.monotonically_increasing_id())
    ordered = kept(ordered, "ordered").withColumn(part, F.shiftright(place, 33))
    earlier = Window.orderBy(part).rowsBetween(Window.unboundedPreceding, -1)  # one row per range
    offsets = ordered.groupBy(part).agg(F.count("*").alias("c")).select(part, F.coalesce(F.sum("c").over(earlier), F.lit(0)).alias(before))
    row = F.col(place).bitwiseAND(F.lit((1 << 33) - 1))
    return ordered.join(F.broadcast(offsets), part).withColumn("pos", F.col(before) + row).drop(place, part, before)


def contiguous(df: DataFrame, p: int, order_by: Sequence[str]) -> DataFrame:
    """p contiguous blocks of floor(n/p) or ceil(n/p) rows in the given order; adds pos and block_id.

    Columns of these names are replaced. An empty table has no blocks; with p > n some stay empty.
    """
    placed = positions(df, order_by)
    size = unused("size", placed.columns)
    total = placed.agg(F.count("*").alias(size))
    return placed.crossJoin(F.broadcast(total)).withColumn("block_id", block_of(F.col("pos"), p, F.col(size))).drop(size)


def room(item: Column, count: int) -> Column:
    """The room of an item, 0 to count - 1, by its hash: all rows of an item share one."""
    return F.pmod(F.xxhash64(item), F.lit(count)).cast("int")


def rooms(df: DataFrame, item: str, k: int, by: Sequence[str] = ()) -> int:
    """How many rooms the items need so that none, of any group, has more than k different items.

    A pass with k counters then is exact in each room, and the rooms' counters together
    are all items. One room if k items are not exceeded. The distinct items are
    written once; their number in the fullest room is counted for each trial.
    """
    distinct = kept(df.select(*by, as_item(df, item).alias("_item")).distinct(), "distinct")
    count = 1
    while True:
        most = distinct.groupBy(*by, room(F.col("_item"), count).alias("_room")).count().agg(F.max("count")).first()[0]
        if most is None or most <= k:
            return count
        count *= max(2, -(-5 * most // (4 * k)))


def assign(df: DataFrame, p: int, mode: str = "natural", order_by: Sequence[str] = ()) -> DataFrame:
    """Adds block_id.

    natural: the input's own partitions, no shuffle (p is not used);
    round_robin: p even partitions; range: p ranges of the order columns;
    contiguous: p exact contiguous blocks; hash_row: by a hash of the order columns;
    key: the first order column, an integer, modulo p.
    """
    if mode == "natural":
        return df.withColumn("block_id", F.spark_partition_id())
    if mode == "round_robin":
        return df.repartition(p).withColumn("block_id", F.spark_partition_id())
    if mode == "range":
        return df.repartitionByRange(p, *order_by).withColumn("block_id", F.spark_partition_id())
    if mode == "contiguous":
        return contiguous(df, p, order_by).drop("pos")
    if mode == "hash_row":
        return df.withColumn("block_id", F.pmod(F.xxhash64(*order_by), F.lit(p)).cast("int"))
    if mode == "key":
        return df.withColumn("block_id", F.pmod(F.col(order_by[0]), F.lit(p)).cast("int"))
    raise ValueError(f"unknown block mode {mode!r}")
