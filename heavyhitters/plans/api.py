"""Frequent items end to end."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import Summaries, check_k
from ..operators import blocks as deal
from ..operators import local, merge, report


def clean(df: DataFrame, item: str, nulls: str = "drop", fill: object = None, sentinels: Sequence[object] = ()) -> DataFrame:
    """Missing values before counting: dropped, replaced by `fill`, or kept as an item; sentinels go."""
    if nulls == "fill":
        df = df.withColumn(item, F.coalesce(F.col(item), F.lit(fill)))
    elif nulls == "drop":
        df = df.filter(F.col(item).isNotNull())
    elif nulls != "keep":
        raise ValueError("nulls must be drop, fill or keep")
    return df.filter(~F.col(item).isin(*sentinels) | F.col(item).isNull()) if sentinels else df


def summarise(df: DataFrame, item: str, k: int, p: int = 8, builder: str = "chunked", blocks: str = "natural", order_by: Sequence[str] = (), weight: str | None = None, by: Sequence[str] = ()) -> Summaries:
    """The local phase: deal into blocks, then one summary each."""
    ordered = builder != "histogram" and bool(order_by)
    if builder == "histogram" or ordered or blocks != "natural":
        df = deal.assign(df, p, blocks, order_by)
    if builder != "histogram" and not ordered and blocks in ("key", "hash_row", "contiguous"):
        df = df.repartition(p, "block_id")  # a kernel reads partitions, so blocks become partitions
    if by:
        return local.histogram(df, item, k, by, weight)
    return local.per_block(df, item, k, builder, weight, order_by if ordered else ())


def merged(s: Summaries, how: str = "flat", p: int = 8, fan_in: int = 2) -> Summaries:
    """One summary of all blocks. A tree is for blocks 0..p-1; blocks beyond are merged at its root."""
    return merge.flat(s) if how == "flat" else merge.flat(merge.tree(s, p, fan_in))


def frequent_items(df: DataFrame, item: str, k: int, p: int = 8, builder: str = "chunked", how: str = "flat", blocks: str = "natural", order_by: Sequence[str] = (), nulls: str = "drop", fill: object = None, sentinels: Sequence[object] = (), verify: bool = False, weight: str | None = None, by: Sequence[str] = (), fan_in: int = 2, strict: bool = True) -> DataFrame:
    """Items that may occur floor(n/k) + 1 times or more, none of those that do missing.

    (by, item, est, err, lower, status), or with `verify` exactly the frequent items
    (item, cnt) after a second scan. The default reads the item column once, shuffles at
    most k counters per input partition and sorts nothing. `builder="histogram"` trades a
    shuffle of each block's distinct items for exact local counts. Groups (`by`) have
    thresholds of their own and use the histogram builder. A tree needs blocks 0..p-1.

    k must be from 2 to the number of items: a larger one fails the query when it runs,
    unless `strict` is off (the threshold then is 1) or the table is empty, which has
    no frequent items. Groups are never too small. With nulls="keep" null is an item;
    NaN is one item and so are both zeros. Rows of weight 0 or null count nothing; a
    negative weight fails the query. Other columns are not read, whatever their names.
    """
    check_k(k)
    rows = clean(df, item, nulls, fill, sentinels)
    top = merged(summarise(rows, item, k, p, builder, blocks, order_by, weight, by), how, p, fan_in)
    if verify:
        if by:
            raise ValueError("verification takes one bag")
        return report.verify(rows, item, report.prune(top, strict), weight=weight, most=k)
    return report.report(top, strict and not by)


def iceberg(df: DataFrame, item: str | Sequence[Column], k: int, **options) -> DataFrame:
    """(item, cnt): GROUP BY item HAVING count(*) > n / k without shuffling every group.

    Composite keys are given as columns and become one struct as JSON text.
    """
    if not isinstance(item, str):
        df, item = df.select(F.to_json(F.struct(*item)).alias("item")), "item"
    return frequent_items(df, item, k, verify=True, **options)
