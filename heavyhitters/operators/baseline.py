"""The deficit-merge baseline: summaries of at most k - 1 under-estimating counters.

A full local summary loses its minimum; two summaries are added up without
padding; what exceeds k - 1 counters is cut by subtracting the k-th largest. The
amounts subtracted on the way (`delta`) are carried along for the ablation that
puts them back. Null is an item; an empty block has no counters and nothing to
subtract; counters that equal the cut become zero and go.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..model import Summaries, as_column, threshold_col


def localize(s: Summaries) -> Summaries:
    """Subtract each block's minimum and drop the zeros; the header gains `delta`."""
    counters = s.counters.select(*s.block, "item", (F.col("est") - F.col("min_est")).alias("est")).filter("est > 0")
    return Summaries(counters, s.headers.withColumn("delta", F.col("min_est")), s.k, s.keys, s.most)


def combine(one: DataFrame, other: DataFrame) -> DataFrame:
    """(item, est): counts of common items added, others copied; at most 2k - 2 rows."""
    return one.select("item", "est").unionByName(other.select("item", "est")).groupBy("item").agg(F.sum("est").alias("est"))


def shrink(counters: DataFrame, k: int | str, group: list[str], most: int | None = None) -> DataFrame:
    """If a group has k counters or more, subtract the k-th largest from those above it, drop the rest.

    Adds `_cut`, the amount subtracted (0 if none). Equal counters at the cut become zero and go.
    """
    size = as_column(k)
    order = Window.partitionBy(*group).orderBy(F.desc("est"), F.asc("item"))
    ranked = counters.withColumn("_rank", F.row_number().over(order)).filter((F.col("_rank") <= size) & (F.lit(True) if most is None else F.col("_rank") <= most))
    cut = F.max(F.when(F.col("_rank") == size, F.col("est")).otherwise(F.lit(0))).over(Window.partitionBy(*group))
    ranked = ranked.withColumn("_cut", F.greatest(cut, F.lit(0)))
    return ranked.withColumn("est", F.col("est") - F.col("_cut")).drop("_rank")


def _level(s: Summaries, parent: Column) -> Summaries:
    group = s.block
    added = s.counters.withColumn("block_id", parent).groupBy(*group, "item").agg(F.sum("est").alias("est"))
    cut = shrink(added, s.k, group, s.most)
    amount = cut.groupBy(*group).agg(F.max("_cut").alias("_cut"))
    headers = s.headers.withColumn("block_id", parent).groupBy(*group).agg(F.sum("n").alias("n"), F.sum("delta").alias("delta"))
    headers = headers.join(amount, group, "left").select(*group, "n", (F.col("delta") + F.coalesce("_cut", F.lit(0))).alias("delta"))
    return Summaries(cut.filter("est > 0").drop("_cut"), headers, s.k, s.keys, s.most)


def tree(s: Summaries, blocks: int, fan_in: int = 2) -> Summaries:
    """Reduce localized summaries level by level; an unpaired block passes through unchanged."""
    parent = F.call_function("div", F.col("block_id").cast("bigint"), F.lit(fan_in).cast("bigint")).cast("int")
    while blocks > 1:
        s = _level(s, parent)
        blocks = -(-blocks // fan_in)
    return s


def deficit_merge(s: Summaries, blocks: int, fan_in: int = 2, p1_passthrough: bool = False) -> DataFrame:
    """(keys, item, est): all counters that the reduction leaves, without a threshold.

    With `p1_passthrough`, a single block returns its plain summary pruned by the threshold.
    """
    if blocks == 1 and p1_passthrough:
        from .report import prune

        return prune(s).select(*s.keys, "item", "est")
    return tree(localize(s), blocks, fan_in).counters.select(*s.keys, "item", "est")


def pruned(s: Summaries, blocks: int, fan_in: int = 2) -> DataFrame:
    """(keys, item, est): with the subtracted amounts put back and the threshold applied."""
    end = tree(localize(s), blocks, fan_in)
    head = end.headers.select(*s.block, "n", "delta")
    rows = end.counters.join(head, s.block) if s.keys else end.counters.drop("block_id").crossJoin(F.broadcast(head.drop("block_id")))
    whole = rows.select(*s.keys, "item", (F.col("est") + F.col("delta")).alias("est"), "n")
    return whole.filter(F.col("est") >= threshold_col("n", as_column(s.k))).select(*s.keys, "item", "est")
