"""Accuracy measures of a report against exact counts.

Null is an item as any other. Bags without items have no row; a bag in which nothing
is reported has total error 0, no relative error and no precision.
"""

from __future__ import annotations

import math
from collections.abc import Mapping, Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import as_column, match, threshold_col

#: Degrees of freedom up to which quantiles are tabulated; beyond, a series in 1 / degrees is as exact.
TABLED = 200
#: The 97.5 % quantile of the normal distribution.
Z = 1.959963984540054


def t_tail(t: float, degrees: int) -> float:
    """P(|T| > t) of Student's t, by the finite sum over cosines for whole degrees of freedom."""
    angle = math.atan2(t, math.sqrt(degrees))
    c, term, total = math.cos(angle), 1.0, 0.0
    first = degrees % 2
    term = c if first else 1.0
    for j in range(first + 1, degrees, 2):
        total += term
        term *= c * c * j / (j + 1)
    inside = math.sin(angle) * total
    return 1 - (2 / math.pi * (angle + inside) if first else inside)


def t95(degrees: int) -> float:
    """The two-sided 95 % quantile of Student's t: for whole degrees up to TABLED by halving, else by the series."""
    if degrees > TABLED:
        return t_series(float(degrees))
    low, high = 1.0, 20.0
    while high - low > 1e-13 * high:
        mid = (low + high) / 2
        low, high = (mid, high) if t_tail(mid, degrees) > 0.05 else (low, mid)
        if mid in (low, high) and high - low < 1e-12:
            break
    return (low + high) / 2


def t_series(v):
    """The quantile as a series in 1 / v around the normal one, for a number or a column."""
    one = (Z**3 + Z) / 4
    two = (5 * Z**5 + 16 * Z**3 + 3 * Z) / 96
    three = (3 * Z**7 + 19 * Z**5 + 17 * Z**3 - 15 * Z) / 384
    four = (79 * Z**9 + 776 * Z**7 + 1482 * Z**5 - 1920 * Z**3 - 945 * Z) / 92160
    return Z + (one + (two + (three + four / v) / v) / v) / v


def per_item(reported: DataFrame, truth: DataFrame, keys: Sequence[str] = (), truth_keys: Sequence[str] | None = None) -> DataFrame:
    """(keys, item, est, cnt, abs_error, rel_error) of each reported item.

    `truth_keys` are those of the keys that the exact counts depend on (all by default).
    Null is an item; one that never occurs has cnt 0 and no relative error.
    """
    on = [*(keys if truth_keys is None else truth_keys), "item"]
    rows = match(reported.select(*keys, "item", "est"), truth.select(*on, "cnt"), on, "left").withColumn("cnt", F.coalesce("cnt", F.lit(0)))
    error = F.abs(F.col("cnt") - F.col("est"))
    return rows.select(*keys, "item", "est", "cnt", error.alias("abs_error"), (error / F.nullif("cnt", F.lit(0))).alias("rel_error"))


def summary(reported: DataFrame, truth: DataFrame, k: int | str, keys: Sequence[str] = (), truth_keys: Sequence[str] | None = None, ks: Sequence[int] = (), spread: Mapping[str, Sequence[int]] | None = None) -> DataFrame:
    """One row per bag: n_true, n_reported, n_hit, total_error, are, precision, recall.

    Total error sums |true - est| and `are` averages |true - est| / true over reported
    items (null if none). Precision is null if nothing is reported; recall is 1 if
    nothing is frequent. `k` may be a key, its values then are `ks`; `spread` has the
    values of other keys that the exact counts do not depend on. Bags are those that
    the truth has.
    """
    base = [x for x in (keys if truth_keys is None else truth_keys)]
    totals = truth.groupBy(*base).agg(F.sum("cnt").alias("n")) if base else truth.agg(F.sum("cnt").alias("n"))
    frequent = truth.join(totals, base) if base else truth.crossJoin(F.broadcast(totals))
    # with the largest k the threshold is least: few items are left before anything is repeated for each k
    frequent = frequent.filter(F.col("cnt") >= threshold_col("n", F.lit(max(ks)) if isinstance(k, str) else F.lit(k)))
    values = {**({k: ks} if isinstance(k, str) else {}), **(spread or {})}
    for name, each in values.items():
        column = F.explode(F.array(*[F.lit(int(x)) for x in each])).alias(name)
        totals, frequent = totals.select("*", column), frequent.select("*", column)
    frequent = frequent.filter(F.col("cnt") >= threshold_col("n", as_column(k)))
    n_true = frequent.groupBy(*keys).agg(F.count("*").alias("n_true"))
    items = per_item(reported, truth, keys, truth_keys)
    items = items.join(totals, list(keys)) if keys else items.crossJoin(F.broadcast(totals))
    hit = F.col("cnt") >= threshold_col("n", as_column(k))
    scored = items.groupBy(*keys).agg(F.count("*").alias("n_reported"), F.count_if(hit).alias("n_hit"), F.sum("abs_error").alias("total_error"), F.avg("rel_error").alias("are"))
    heads = totals.select(*keys, "n")
    rows = heads.join(n_true, list(keys), "left").join(scored, list(keys), "left") if keys else heads.crossJoin(n_true).crossJoin(scored)
    zero = lambda c: F.coalesce(F.col(c), F.lit(0)).cast("bigint")
    rows = rows.select(*keys, "n", *[zero(c).alias(c) for c in ("n_true", "n_reported", "n_hit", "total_error")], "are")
    return rows.withColumn("precision", F.col("n_hit") / F.nullif("n_reported", F.lit(0))).withColumn("recall", F.coalesce(F.col("n_hit") / F.nullif("n_true", F.lit(0)), F.lit(1.0)))


def t_quantile(degrees: Column) -> Column:
    """The 95 % quantile for any whole number of degrees of freedom; null below 1."""
    table = F.get(F.array(*[F.lit(t95(v)) for v in range(1, TABLED + 1)]), degrees.cast("int") - 1)
    return F.when(degrees > TABLED, t_series(degrees.cast("double"))).when(degrees >= 1, table)


def mean_ci(df: DataFrame, by: Sequence[str], value: str) -> DataFrame:
    """(by, runs, mean, half_width) of the 95 % Student-t interval over repeated runs."""
    stats = df.groupBy(*by).agg(F.count(value).alias("runs"), F.avg(value).alias("mean"), F.stddev_samp(value).alias("sd"))
    half = t_quantile(F.col("runs") - 1) * F.col("sd") / F.sqrt("runs")
    return stats.select(*by, "runs", "mean", F.when(F.col("runs") > 1, half).alias("half_width"))


def intervals(runs: DataFrame, by: Sequence[str], measures: Sequence[str] = ("total_error", "are", "precision", "recall")) -> DataFrame:
    """(by, measure, runs, mean, half_width): `mean_ci` of several measures; runs in which one is null do not count for it."""
    each = F.explode(F.array(*[F.struct(F.lit(m).alias("measure"), F.col(m).cast("double").alias("value")) for m in measures])).alias("m")
    return mean_ci(runs.select(*by, each).select(*by, "m.measure", "m.value"), [*by, "measure"], "value")


def describe(df: DataFrame, item: str) -> DataFrame:
    """Statistics of a numeric item column: count, distinct, min, max, mean, median, std, skewness.

    Skewness is the third standardised moment of the population.
    """
    x = F.col(item).cast("double")
    return df.agg(
        F.count(item).alias("n"), F.count_distinct(item).alias("n_distinct"), F.min(item).alias("min_item"), F.max(item).alias("max_item"),
        F.avg(x).alias("mean_item"), F.median(x).alias("median_item"), F.stddev_samp(x).alias("std_item"), F.skewness(x).alias("skew_item"),
    )
