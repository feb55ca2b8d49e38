"""The cost model: communication, depth, time, isoefficiency, memory."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def processors(spark: SparkSession, ps: Sequence[int]) -> DataFrame:
    """(p) as bigint."""
    return spark.range(1).select(F.explode(F.array(*[F.lit(int(p)).cast("bigint") for p in ps])).alias("p"))


def daily(rows: DataFrame, day: str) -> DataFrame:
    """(p, n): a worker for each day that has rows, p of them up to a day, and all rows.

    Days are few whatever the number of rows; they are counted before they are numbered.
    """
    per = rows.filter(F.col(day).isNotNull()).groupBy(F.to_date(day).alias("day")).agg(F.count("*").alias("c"))
    every = Window.orderBy("day").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)  # one row per day
    return per.select(F.row_number().over(Window.orderBy("day")).cast("bigint").alias("p"), F.sum("c").over(every).alias("n"))


def levels(p: Column, fan_in: int = 2) -> Column:
    """Reduction levels for p summaries, by repeated integer division (no logarithm to round)."""
    out = F.lit(0)
    for d in range(1, 40):
        if fan_in ** (d - 1) > 1 << 40:
            break
        out = out + F.when(p > fan_in ** (d - 1), 1).otherwise(0)
    return out


def communication(ps: DataFrame, k: int) -> DataFrame:
    """(p, counters): (p - 1) * k counters move in the reduction."""
    return ps.select("p", ((F.col("p") - 1) * k).alias("counters"))


def depth(ps: DataFrame, fan_in: int = 2) -> DataFrame:
    return ps.select("p", levels(F.col("p"), fan_in).cast("int").alias("depth"))


def time_model(ps: DataFrame, n: int | Column) -> DataFrame:
    """(p, model_time, speedup, efficiency, cost_optimal) of n / p + log2 p with constant k.

    Cost-optimal where n is at least p log2 p.
    """
    log = F.log2(F.col("p").cast("double"))
    n = (n if isinstance(n, Column) else F.lit(n)).cast("double")
    t = n / F.col("p") + log
    return ps.select("p", t.alias("model_time"), (n / t).alias("speedup"), (n / t / F.col("p")).alias("efficiency"), (n >= F.col("p") * log).alias("cost_optimal"))


def isoefficiency(ps: DataFrame) -> DataFrame:
    """(p, overhead, least_n): p * T_p - T_1 = p log2 p items keep the efficiency."""
    over = F.col("p") * F.log2(F.col("p").cast("double"))
    return ps.select("p", over.alias("overhead"), F.ceil(over).cast("bigint").alias("least_n"))


def scalability(ps: DataFrame) -> DataFrame:
    """(p, memory_per_worker, growth): log2 p items per worker; constant, at most as p, or beyond."""
    m = F.log2(F.col("p").cast("double"))
    return ps.select("p", m.alias("memory_per_worker"), F.when(m == 0, "constant").when(m <= F.col("p"), "at most p").otherwise("beyond").alias("growth"))


def speedup(timings: DataFrame, by: Sequence[str] = ("method",)) -> DataFrame:
    """(by, p, seconds, speedup, efficiency, superlinear) from (by, p, seconds) of repeated runs.

    Means over runs are set against the mean at p = 1.
    """
    mean = timings.groupBy(*by, "p").agg(F.avg("seconds").alias("seconds"))
    one = mean.filter("p = 1").select(*by, F.col("seconds").alias("one"))
    ratio = F.col("one") / F.col("seconds")
    return mean.join(one, list(by)).select(*by, "p", "seconds", ratio.alias("speedup"), (ratio / F.col("p")).alias("efficiency"), (ratio / F.col("p") > 1).alias("superlinear"))
