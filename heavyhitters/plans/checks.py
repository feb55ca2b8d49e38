"""The invariants of summaries, as tables of booleans."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import Summaries, as_column, match


def invariants(s: Summaries, truth: DataFrame) -> DataFrame:
    """One row: n, nz and whether each relation holds for a merged (one-block) summary.

    sum_ok: sum(est) <= n; monitored_ok: est - min_est <= est - err <= true <= est;
    unmonitored_ok: true <= min_est; bound_ok: min_est <= floor(n/k); full_ok: min_est = 0
    exactly if fewer than k counters are in use; space_ok: at most k counters.
    """
    head = s.headers.select("n", F.col("nz"), F.col("min_est").alias("m"), as_column(s.k).alias("kk"))
    both = match(truth, s.counters.select("item", "est", "err"), ["item"], "full_outer").crossJoin(F.broadcast(head))
    true = F.coalesce("cnt", F.lit(0))
    seen = F.col("est").isNotNull()
    holds = (F.col("est") - F.col("m") <= F.col("est") - F.col("err")) & (F.col("est") - F.col("err") <= true) & (true <= F.col("est"))
    row = both.agg(
        F.bool_and(~seen | holds).alias("monitored_ok"), F.bool_and(seen | (true <= F.col("m"))).alias("unmonitored_ok"),
        F.sum(F.coalesce("est", F.lit(0))).alias("_sum"), F.count("est").alias("_used"),
    )
    return row.crossJoin(F.broadcast(head)).select(
        "n", "nz", (F.col("_sum") <= F.col("n")).alias("sum_ok"), "monitored_ok", "unmonitored_ok", (F.col("m") <= F.call_function("div", F.col("n"), F.col("kk").cast("bigint"))).alias("bound_ok"),
        ((F.col("m") == 0) == (F.col("_used") < F.col("kk"))).alias("full_ok"), (F.col("_used") <= F.col("kk")).alias("space_ok"),
    )


def combine_identity(one: Summaries, other: Summaries, combined: DataFrame) -> DataFrame:
    """One row: whether sum(est) of the combination is both sums plus (items - k) times both minima."""
    head = lambda s, x: s.headers.agg(F.first("total_est").alias(f"s{x}"), F.first("min_est").alias(f"m{x}"))
    row = combined.agg(F.sum("est").alias("total"), F.count("*").alias("items"), F.min("est").alias("least"))
    row = row.crossJoin(head(one, 1)).crossJoin(head(other, 2))
    pad = F.col("m1") + F.col("m2")
    return row.select("items", "total", (F.col("total") == F.col("s1") + F.col("s2") + (F.col("items") - as_column(one.k)) * pad).alias("identity_ok"), (F.col("least") >= pad).alias("least_ok"), (F.col("items") <= 2 * as_column(one.k)).alias("space_ok"))
