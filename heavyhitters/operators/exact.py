"""Exact frequent items, the reference of every measure."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import check_item_type, check_k, threshold_col, weighted


def frequencies(df: DataFrame, item: str, by: Sequence[str] = (), weight: str | None = None) -> DataFrame:
    """(by, item, cnt): the frequency of every distinct item.

    Null is an item like others; an empty table has none. Weights that are null or 0
    count nothing, a negative one fails the query.
    """
    check_item_type(df.schema[item].dataType)
    count = F.sum(F.col(weight).cast("bigint")) if weight else F.count("*")
    return weighted(df, weight).groupBy(*by, F.col(item).alias("item")).agg(count.alias("cnt"))


def k_majority(df: DataFrame, item: str, k: int, by: Sequence[str] = (), weight: str | None = None, strict: bool = False) -> DataFrame:
    """(by, item, cnt) of items with cnt >= floor(n/k) + 1, n the size of the bag (of each group).

    With `strict`, a bag of fewer than k items (but not an empty one) fails the query;
    without, its threshold is 1.
    n is the sum of the counts, so the input is read once and both uses share one shuffle.
    """
    check_k(k)
    counts = frequencies(df, item, by, weight)
    totals = counts.groupBy(*by).agg(F.sum("cnt").alias("n")) if by else counts.agg(F.sum("cnt").alias("n"))
    rows = counts.join(totals, list(by)) if by else counts.crossJoin(F.broadcast(totals))
    return rows.filter(F.col("cnt") >= threshold_col("n", F.lit(k), strict)).select(*by, "item", "cnt")


def majority(df: DataFrame, item: str) -> DataFrame:
    """The item that is more than half of the bag, if there is one."""
    return k_majority(df, item, 2)
