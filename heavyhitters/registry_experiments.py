"""The synthetic experiments with item-at-a-time summaries, twenty seeds and intervals; run times.

Rows of lineitem are the number of items. Results depend on the order of the items,
which SQL cannot express over whole tables; the invariants of the runs can be stated.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import registry_sql as R
from .functions import cost, metrics
from .operators import baseline, exact, local
from .plans import api, experiments
from .plans.experiments import Case
from .registry import P, add
from .sources import datagen
from .sources.workloads import table

SEEDS = tuple(range(1, 21))
#: The published grids: ten k, ten sizes, six skews, up to eight workers.
LARGE_KS = tuple(range(1000, 10_001, 1000))
RHOS = (0.5, 1.0, 1.5, 2.0, 2.5, 3.0)
K, RHO = 2000, 1.5
LAWS = {"plain": 0.0, "shifted": 0.5}


def vary_k(n: int, a: float) -> tuple[list[Case], Sequence[int]]:
    return [Case(P, n, RHO, a)], (*experiments.KS[:-1], *LARGE_KS)


def vary_n(n: int, a: float) -> tuple[list[Case], Sequence[int]]:
    return [Case(P, n * i // 10, RHO, a) for i in range(1, 11)], (K,)


def vary_rho(n: int, a: float) -> tuple[list[Case], Sequence[int]]:
    return [Case(P, n, rho, a) for rho in RHOS], (K,)


def vary_p(n: int, a: float) -> tuple[list[Case], Sequence[int]]:
    return [Case(p, n, RHO, a) for p in range(1, P + 1)], (K,)


GRIDS: dict[str, Callable] = {"exp1_vary_k": vary_k, "exp2_vary_n": vary_n, "exp3_vary_rho": vary_rho, "exp6_vary_p": vary_p}


def runs(spark: SparkSession, d: str, grid: Callable, a: float, seeds: Sequence[int] = SEEDS) -> DataFrame:
    """(method, seed, p, size, rho, k, measures) of each run; k up to the number of items."""
    n = table(spark, d, "lineitem").count()
    cases, ks = grid(n, a)
    return experiments.literal_runs(spark, cases, [k for k in ks if k <= min(c.n for c in cases)] or [min(c.n for c in cases)], seeds)


def measured(df: DataFrame) -> DataFrame:
    return metrics.intervals(df, ["method", "p", "size", "rho", "k"])


def held(df: DataFrame) -> DataFrame:
    """Whether recall is 1 in every run, and our total error and precision are never worse than the baseline's."""
    side = lambda m: df.filter(F.col("method") == m).select(*experiments.RUN, *[F.col(c).alias(f"{m}_{c}") for c in ("total_error", "precision", "recall")])
    both = side("summary").join(side("deficit"), experiments.RUN)
    full = (F.col("summary_recall") == 1) & (F.col("deficit_recall") == 1)
    return both.agg(
        F.count_distinct("seed").alias("seeds"), F.bool_and(full).alias("recall_ok"), F.bool_and(F.col("summary_total_error") <= F.col("deficit_total_error")).alias("error_ok"),
        F.bool_and(F.coalesce("summary_precision", F.lit(1.0)) >= F.coalesce("deficit_precision", F.lit(0.0))).alias("precision_ok"),
    )


for _name, _grid in GRIDS.items():
    for _law, _a in LAWS.items():
        add(f"{_name}_sequential_{_law}", lambda spark, d, g=_grid, a=_a: measured(runs(spark, d, g, a)))
for _name in ("exp1_vary_k", "exp3_vary_rho"):
    add(f"inv_{_name}_sequential", lambda spark, d, g=GRIDS[_name]: held(runs(spark, d, g, 0.5, (1, 2, 3))), "SELECT 3::BIGINT AS seeds, true AS recall_ok, true AS error_ok, true AS precision_ok")

#: Where the summaries are to win over counting every distinct item: long sequences with many of them.
LONG = 20
_LONG_SQL = R.exact(f"SELECT item FROM ({datagen.sql_items(f'SELECT {LONG} * count(*) FROM lineitem', 1.0, 1_100_000, (1,), 0.5)})", K)


def long_sequence(spark: SparkSession, d: str) -> DataFrame:
    return datagen.shifted_power_law(spark, table(spark, d, "lineitem").count() * LONG, 1.0, 1_100_000, (1,), 0.5)


add("exact_synthetic_long", lambda spark, d: exact.k_majority(long_sequence(spark, d), "item", K), _LONG_SQL)
add("ss_synthetic_long_verified", lambda spark, d: api.frequent_items(long_sequence(spark, d), "item", K, verify=True), _LONG_SQL)
add("ss_synthetic_long", lambda spark, d: api.frequent_items(long_sequence(spark, d), "item", K))
add("dm_synthetic_long", lambda spark, d: baseline.deficit_merge(local.per_block(long_sequence(spark, d), "item", K), 64))


#: Items are the rows of lineitem this many times, so that counting outweighs starting tasks; runs of each setting.
REPLICAS, RUNS = 50, 3


def _timed(rho: float, k: int, count: int = RUNS) -> Callable:
    def run(spark: SparkSession, d: str) -> DataFrame:
        n = table(spark, d, "lineitem").count() * REPLICAS
        return cost.speedup(experiments.runtimes(spark, n, rho, k, runs=count), ["law", "method"])

    return run


add("exp4_runtime", _timed(1.5, 2000))
add("exp5_runtime", _timed(3.0, 3000))
