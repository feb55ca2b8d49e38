"""From a merged summary to frequent items."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import Summaries, as_column, match, threshold_col, weighted

#: Candidates that may be broadcast; each is an item and its threshold.
BROADCAST_ITEMS = 1_000_000


def _with_header(s: Summaries) -> DataFrame:
    """Counters with n and k of their summary; a header is one row per key."""
    rows = s.counters.drop("min_est", "block_id")
    if "n" in rows.columns:
        return rows.withColumn("k", as_column(s.k).cast("bigint"))
    head = s.headers.select(*s.keys, "n", *([] if "k" in s.keys else ["k"]))
    return rows.join(head, s.keys) if s.keys else rows.crossJoin(F.broadcast(head))


def prune(s: Summaries, strict: bool = False) -> DataFrame:
    """(keys, item, est, err, n, k) of counters that reach floor(n/k) + 1; no frequent item is missing.

    `strict`: a bag of fewer than k items, but not an empty one, fails the query.
    """
    return _with_header(s).filter(F.col("est") >= threshold_col(strict=strict))


def classify(candidates: DataFrame) -> DataFrame:
    """Adds `lower` = est - err and status: guaranteed if `lower` reaches the threshold, else potential."""
    lower = F.col("est") - F.col("err")
    status = F.when(lower >= threshold_col(), F.lit("guaranteed")).otherwise(F.lit("potential"))
    return candidates.select("*", lower.alias("lower"), status.alias("status"))


def report(s: Summaries, strict: bool = False) -> DataFrame:
    """(keys, item, est, err, lower, status)."""
    return classify(prune(s, strict)).select(*s.keys, "item", "est", "err", "lower", "status")


def verify(df: DataFrame, item: str, candidates: DataFrame, n: int | None = None, k: int | None = None, weight: str | None = None, most: int = BROADCAST_ITEMS) -> DataFrame:
    """(item, cnt) of the candidates that are frequent, by a second scan of the item column.

    Candidates are at most `most`; up to BROADCAST_ITEMS they are broadcast, and each
    task sends one count for each at most. More are joined as the optimizer sees fit.
    `n` and `k` default to the columns of the candidates. A null candidate matches
    null items, NaN matches NaN, and the zeros each other.
    """
    limits = candidates.select("item", *([] if n is not None else [threshold_col().alias("_t")]))
    if n is not None:
        limits = limits.withColumn("_t", F.lit(n // k + 1))
    count = F.sum(F.col(weight).cast("bigint")) if weight else F.count("*")
    rows = weighted(df, weight).select(F.col(item).alias("item"), *([weight] if weight else []))
    return match(rows, F.broadcast(limits) if most <= BROADCAST_ITEMS else limits, ["item"]).groupBy("item", "_t").agg(count.alias("cnt")).filter(F.col("cnt") >= F.col("_t")).select("item", "cnt")


def bounds(s: Summaries, probe: DataFrame) -> DataFrame:
    """(keys, item, lo, hi) for any items: of an item without a counter lo = 0, hi = the smallest estimate."""
    head = s.headers.select(*s.keys, F.col("min_est").alias("_m"))
    at = probe.join(head, s.keys) if s.keys else probe.crossJoin(F.broadcast(head))
    found = match(at, s.counters.select(*s.keys, "item", "est", "err"), [*s.keys, "item"], "left")
    return found.select(*s.keys, "item", F.coalesce(F.col("est") - F.col("err"), F.lit(0)).alias("lo"), F.coalesce("est", "_m").alias("hi"))


def missed(truth: DataFrame, reported: DataFrame, on: Sequence[str] = ("item",)) -> DataFrame:
    """Frequent items that were not reported; always empty for counter summaries."""
    return match(truth, reported.select(*on), on, "left_anti")
