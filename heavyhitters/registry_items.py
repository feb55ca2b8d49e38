"""Queries over items of awkward kinds: NaN, both zeros, kept nulls, weights; every builder and merge."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import metrics
from .operators import exact, local, merge, report, sketches
from .plans import api, checks
from .registry import P, add
from .sources.workloads import table

_FLOATS = "SELECT CASE WHEN event_id % 5 = 0 THEN 'NaN'::DOUBLE WHEN event_id % 7 = 0 OR event_id % 11 = 0 THEN 0.0::DOUBLE ELSE floor(value) END AS item, event_id AS key FROM events"
_NULLED = "SELECT CASE WHEN event_id % 3 = 0 THEN NULL ELSE floor(value)::BIGINT END AS item, event_id AS key FROM events"
_K = 60


def floats(spark: SparkSession, d: str) -> DataFrame:
    """Whole values as doubles, with NaN and zeros of both signs."""
    i = F.col("event_id")
    item = F.when(i % 5 == 0, F.lit(float("nan"))).when(i % 7 == 0, F.lit(-0.0)).when(i % 11 == 0, F.lit(0.0)).otherwise(F.floor("value").cast("double"))
    return table(spark, d, "events").select(item.alias("item"), i.alias("key"))


def nulled(spark: SparkSession, d: str) -> DataFrame:
    """Values of which every third is null."""
    return table(spark, d, "events").select(F.when(F.col("event_id") % 3 != 0, F.floor("value").cast("bigint")).alias("item"), F.col("event_id").alias("key"))


def _named(df: DataFrame, *rest: str) -> DataFrame:
    """The item as text, NaN by name."""
    return df.select(F.when(F.isnan("item"), "NaN").otherwise(F.col("item").cast("bigint").cast("string")).alias("item"), *rest)


_LABEL = "CASE WHEN isnan(item) THEN 'NaN' ELSE item::BIGINT::VARCHAR END AS item"


def _exact_sql(source: str, label: str, k: int) -> str:
    return f"WITH c AS (SELECT item, count(*) AS cnt FROM ({source}) GROUP BY item) SELECT {label}, cnt FROM c WHERE cnt >= (SELECT sum(cnt)::BIGINT FROM c) // {k} + 1"


_FLOAT_SQL = _exact_sql(_FLOATS + " WHERE value IS NOT NULL OR event_id % 5 = 0 OR event_id % 7 = 0 OR event_id % 11 = 0", _LABEL, _K)
_NULL_SQL = _exact_sql(_NULLED, "item", _K)
_OPTIONS = {"chunked": {}, "sequential": {"builder": "sequential"}, "histogram": {"builder": "histogram", "blocks": "key", "order_by": ["key"]}, "tree": {"how": "tree", "blocks": "key", "order_by": ["key"]}}

for _b, _o in _OPTIONS.items():
    _tail = "" if _b == "chunked" else f"_{_b}"
    add(f"ss_pipeline_float_verified{_tail}", lambda spark, d, o=_o: _named(api.frequent_items(floats(spark, d), "item", _K, P, verify=True, **o), "cnt"), _FLOAT_SQL)
    add(f"ss_pipeline_nulls_keep_verified{_tail}", lambda spark, d, o=_o: api.frequent_items(nulled(spark, d), "item", _K, P, nulls="keep", verify=True, **o), _NULL_SQL)
add("exact_kmajority_floats", lambda spark, d: _named(exact.k_majority(api.clean(floats(spark, d), "item"), "item", _K), "cnt"), _FLOAT_SQL)
add("exact_kmajority_nulls_keep", lambda spark, d: exact.k_majority(nulled(spark, d), "item", _K), _NULL_SQL)

_TRUE = "true AS sum_ok, true AS monitored_ok, true AS unmonitored_ok, true AS bound_ok, true AS full_ok, true AS space_ok"


def _invariants(source, builder: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        rows = source(spark, d)
        s = local.histogram(rows.withColumn("block_id", F.pmod("key", F.lit(P)).cast("int")), "item", 20) if builder == "histogram" else local.per_block(rows.repartition(P), "item", 20, builder)
        return checks.invariants(merge.flat(s), exact.frequencies(rows, "item"))

    return run


for _b in ("histogram", "sequential", "chunked"):
    add(f"inv_summary_{_b}_flat_nulls", _invariants(nulled, _b), f"SELECT count(*) AS n, 20::BIGINT AS nz, {_TRUE} FROM ({_NULLED})")
    add(f"inv_summary_{_b}_flat_floats", _invariants(lambda spark, d: api.clean(floats(spark, d), "item"), _b), f"SELECT count(*) AS n, 20::BIGINT AS nz, {_TRUE} FROM ({_FLOATS}) WHERE item IS NOT NULL")


def _null_measures(spark: SparkSession, d: str) -> DataFrame:
    """Measures of a report in which null is an item; the bounds of the null item."""
    rows = nulled(spark, d)
    top = merge.flat(local.histogram(rows.withColumn("block_id", F.pmod("key", F.lit(P)).cast("int")), "item", _K))
    truth = exact.frequencies(rows, "item")
    at_null = report.bounds(top, spark.range(1).select(F.lit(None).cast("bigint").alias("item"))).select(F.col("lo").alias("null_lo"), F.col("hi").alias("null_hi"))
    return metrics.summary(report.prune(top), truth, _K).select("n", "n_true", "n_hit", "recall").crossJoin(F.broadcast(at_null))


add("acc_summary_nulls_keep", _null_measures, f"WITH c AS (SELECT item, count(*) AS cnt FROM ({_NULLED}) GROUP BY item), f AS (SELECT * FROM c WHERE cnt >= (SELECT sum(cnt)::BIGINT FROM c) // {_K} + 1) SELECT (SELECT sum(cnt)::BIGINT FROM c) AS n, (SELECT count(*) FROM f) AS n_true, (SELECT count(*) FROM f) AS n_hit, 1.0::DOUBLE AS recall, (SELECT cnt FROM c WHERE item IS NULL) AS null_lo, (SELECT cnt FROM c WHERE item IS NULL) AS null_hi")


# ---- Spark's own sketches in full ------------------------------------------------------------


def _from_parts(spark: SparkSession, d: str) -> DataFrame:
    """Spark's top-k sketches of each lang's words, combined; all words have counters, so counts are exact."""
    words = table(spark, d, "events").select(F.pmod("event_id", F.lit(P)).alias("part"), "event_type")
    return sketches.builtin_top_k_of_parts(words, "part", "event_type", 10, 100)


add("sk_builtin_topk_parts", _from_parts, "SELECT event_type AS item, count(*) AS est FROM events WHERE event_type IS NOT NULL GROUP BY ALL")


def _builtin_count_min(spark: SparkSession, d: str) -> DataFrame:
    """Spark's own count-min sketch, read item by item: never under the count."""
    rows = table(spark, d, "lineitem").select(F.col("l_suppkey").alias("item"))
    found = sketches.builtin_count_min(rows, "item", 0.01, 0.99, 7)
    both = exact.frequencies(rows, "item").join(found, "item", "left")
    return both.agg(F.count("est").alias("items"), F.bool_and(F.col("est") >= F.col("cnt")).alias("never_under"))


add("sk_builtin_countmin", _builtin_count_min, "SELECT count(DISTINCT l_suppkey) AS items, true AS never_under FROM lineitem")
