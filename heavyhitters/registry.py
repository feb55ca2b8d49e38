"""Registered queries of the frequent-item engine: name -> callable, and name -> SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import registry_sql as R
from .functions import cost, metrics
from .model import match, threshold_col
from .operators import baseline, blocks, exact, local, merge, report, sketches
from .plans import api, checks, experiments
from .sources import datagen
from .sources.workloads import NUMERIC, WORKLOADS, table
from .sources.workloads import SQL as W

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}
P = 8


def add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        SQL[name] = sql


def blocked(w: str, p: int = P) -> Query:
    return lambda spark, d: experiments.by_key(WORKLOADS[w](spark, d), p)


def summaries(w: str, k: int, p: int = P, every: bool = False) -> Callable[[SparkSession, str], object]:
    return lambda spark, d: local.histogram(blocked(w, p)(spark, d), "item", k, blocks=p if every else None)


def chain(w: str, k: int, p: int = P, every: bool = False) -> R.Chain:
    return R.Chain(R.workload(w, p), [k], blocks=p if every else 0)


# ---- exact ----------------------------------------------------------------------------

for _w, _k in (("suppliers", 100), ("values", 100), ("words", 400), ("gaps", 400), ("two_attributes", 1000), ("clicks", 400), ("customers", 1000)):
    add(f"exact_kmajority_{_w}", lambda spark, d, w=_w, k=_k: exact.k_majority(api.clean(WORKLOADS[w](spark, d), "item"), "item", k), R.exact(W[_w], _k))
add("exact_majority_lang", lambda spark, d: exact.majority(table(spark, d, "documents").select(F.col("lang").alias("item")).filter("item IS NOT NULL"), "item"), R.exact("SELECT lang AS item FROM documents", 2))
add(
    "exact_threshold",
    lambda spark, d: spark.range(1).select(F.explode(F.array(*[F.lit(x) for x in experiments.KS])).alias("k")).crossJoin(F.broadcast(table(spark, d, "lineitem").agg(F.count("*").alias("n")))).select("k", "n", threshold_col().alias("t")),
    f"SELECT k::INTEGER AS k, n, n // k + 1 AS t FROM (SELECT unnest({list(experiments.KS)}) AS k), (SELECT count(*) AS n FROM lineitem)",
)


# ---- sequential summaries, in order ------------------------------------------------------


def _first_values(spark: SparkSession, d: str, least: int = 0, below: int = 300) -> DataFrame:
    """The events' values in serial order, positions least..below-1 (ids are in time order)."""
    rows = table(spark, d, "events").filter(f"event_id >= {least} AND event_id < {below}")
    return rows.select(F.floor("value").cast("bigint").alias("item"), "event_id").filter("item IS NOT NULL")


def _all_values(spark: SparkSession, d: str) -> DataFrame:
    """The values of all events, in serial order by id."""
    return table(spark, d, "events").select(F.floor("value").cast("bigint").alias("item"), "event_id").filter("item IS NOT NULL")


def _pass_sql(where: str, k: int, cols: str = "item, est, err") -> str:
    """One pass as a recursion over positions; the state is a list of counters."""
    return f"""WITH RECURSIVE src AS (SELECT row_number() OVER (ORDER BY event_id) AS pos, floor(value)::BIGINT AS item FROM events WHERE {where} AND value IS NOT NULL),
run AS (SELECT 0::BIGINT AS pos, []::STRUCT(est BIGINT, item BIGINT, err BIGINT)[] AS st
UNION ALL
SELECT s.pos, CASE
  WHEN len(list_filter(r.st, lambda c: c.item = s.item)) > 0 THEN list_transform(r.st, lambda c: {{'est': c.est + (c.item = s.item)::BIGINT, 'item': c.item, 'err': c.err}})
  WHEN len(r.st) < {k} THEN list_append(r.st, {{'est': 1::BIGINT, 'item': s.item, 'err': 0::BIGINT}})
  ELSE list_append(list_sort(r.st)[2:], {{'est': list_min(r.st).est + 1, 'item': s.item, 'err': list_min(r.st).est}}) END
FROM run r JOIN src s ON s.pos = r.pos + 1)
SELECT {cols} FROM (SELECT unnest(st) AS c FROM (SELECT st FROM run ORDER BY pos DESC LIMIT 1)), LATERAL (SELECT c.item AS item, c.est AS est, c.err AS err)"""


add("ss_sequential_events_k10", lambda spark, d: local.sequential(_first_values(spark, d), "item", 10, ["event_id"]), _pass_sql("event_id >= 0 AND event_id < 300", 10))
add("ss_sequential_range", lambda spark, d: local.sequential(_all_values(spark, d), "item", 20, ["event_id"], 100, 399, "event_id"), _pass_sql("event_id BETWEEN 100 AND 399", 20))
add("ss_sequential_exactfit", lambda spark, d: local.sequential_exact(blocked("suppliers", 1)(spark, d).withColumn("o", F.lit(0)), "item", 2000, ["o"]), f"SELECT item, count(*)::BIGINT AS est, 0::BIGINT AS err FROM ({W['suppliers']}) GROUP BY item")
add("ss_sequential_noerr", lambda spark, d: local.sequential(_first_values(spark, d), "item", 10, ["event_id"], track_error=False).select("item", "est"), _pass_sql("event_id >= 0 AND event_id < 300", 10, "item, est"))
add(
    "ss_local_sequential",
    lambda spark, d: local.in_order(_first_values(spark, d, 0, 200).withColumn("block_id", blocks.block_of(F.col("event_id"), 1, 200)), "item", 12, ["event_id"]).select("block_id", "n", "k", "nz", "min_est", "total_est"),
    f"SELECT 0::INTEGER AS block_id, sum(est)::BIGINT AS n, 12::BIGINT AS k, count(*) AS nz, (CASE WHEN count(*) = 12 THEN min(est) ELSE 0 END)::BIGINT AS min_est, sum(est)::BIGINT AS total_est FROM ({_pass_sql('event_id >= 0 AND event_id < 200', 12)})",
)

# The queries above with SQL read the first events alone, as the recursion is slow. These read all of them, without SQL.
add("ss_sequential_events_k10_whole", lambda spark, d: local.sequential(_all_values(spark, d), "item", 10, ["event_id"]))
add("ss_sequential_noerr_whole", lambda spark, d: local.sequential(_all_values(spark, d), "item", 10, ["event_id"], track_error=False).select("item", "est"))
add(
    "ss_local_sequential_whole",
    lambda spark, d: local.in_order(blocks.contiguous(_all_values(spark, d), P, ["event_id"]), "item", 12, ["event_id"]).select("block_id", "n", "k", "nz", "min_est", "total_est"),
)

# ---- local phase, blocks ------------------------------------------------------------------

add("ss_local_histogram", lambda spark, d: summaries("suppliers", 50)(spark, d).counters.select("block_id", "item", "est", "err"), chain("suppliers", 50).select("SELECT block_id, item, est, err FROM l0"))
add("ss_header", lambda spark, d: summaries("suppliers", 100)(spark, d).headers, chain("suppliers", 100).select("SELECT block_id, n, k::BIGINT AS k, nz, m AS min_est, te AS total_est FROM h0"))
add(
    "blk_contiguous",
    lambda spark, d: blocks.contiguous(table(spark, d, "orders").select("o_orderkey", "o_orderdate"), 7, ["o_orderdate", "o_orderkey"]).groupBy("block_id").agg(F.count("*").alias("rows"), F.min("pos").alias("first"), F.max("pos").alias("last")),
    "WITH o AS (SELECT row_number() OVER (ORDER BY o_orderdate, o_orderkey) - 1 AS pos, count(*) OVER () AS n FROM orders) SELECT (((pos + 1) * 7 - 1) // n)::INTEGER AS block_id, count(*) AS rows, min(pos) AS first, max(pos) AS last FROM o GROUP BY 1",
)
add("blk_mod", lambda spark, d: blocks.assign(table(spark, d, "orders"), 8, "key", ["o_orderkey"]).groupBy("block_id").agg(F.count("*").alias("rows")), "SELECT (o_orderkey % 8)::INTEGER AS block_id, count(*) AS rows FROM orders GROUP BY 1")
add(
    "blk_range_sizes",
    lambda spark, d: blocks.assign(table(spark, d, "orders"), 6, "range", ["o_orderkey"]).groupBy("block_id").agg(F.count("*").alias("c"), F.min("o_orderkey").alias("lo"), F.max("o_orderkey").alias("hi")).agg(F.sum("c").alias("rows"), F.min("lo").alias("lo"), F.max("hi").alias("hi"), (F.count("*") <= 6).alias("at_most_p")),
    "SELECT count(*)::BIGINT AS rows, min(o_orderkey) AS lo, max(o_orderkey) AS hi, true AS at_most_p FROM orders",
)
add(
    "blk_disjoint_modes",
    lambda spark, d: _modes(spark, d),
    "SELECT m AS mode, count(*) AS rows FROM lineitem, (SELECT unnest(['natural', 'round_robin', 'range', 'hash_row', 'key']) AS m) GROUP BY m",
)


def _modes(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for mode in ("natural", "round_robin", "range", "hash_row", "key"):
        part = blocks.assign(table(spark, d, "lineitem").select("l_orderkey", "l_partkey"), 5, mode, ["l_orderkey"]).groupBy("block_id").count()
        part = part.agg(F.sum("count").alias("rows")).select(F.lit(mode).alias("mode"), "rows")
        out = part if out is None else out.unionByName(part)
    return out


# ---- merging -------------------------------------------------------------------------------


def _two(w: str, k: int) -> Callable[[SparkSession, str], tuple]:
    """Counters and minima of the two blocks of a workload."""

    def parts(spark: SparkSession, d: str) -> tuple:
        s = summaries(w, k, 2)(spark, d)
        side = lambda b: s.counters.filter(f"block_id = {b}").select("item", "est", "err")
        low = lambda b: s.headers.filter(f"block_id = {b}").select("min_est")
        return side(0), side(1), low(0), low(1), s

    return parts


_COMBINED = "z AS (SELECT coalesce(a.item, b.item) AS item, (coalesce(a.est, (SELECT m FROM h0 WHERE block_id = 0)) + coalesce(b.est, (SELECT m FROM h0 WHERE block_id = 1)))::BIGINT AS est, (coalesce(a.err, (SELECT m FROM h0 WHERE block_id = 0)) + coalesce(b.err, (SELECT m FROM h0 WHERE block_id = 1)))::BIGINT AS err, CASE WHEN b.item IS NULL THEN 'first' WHEN a.item IS NULL THEN 'second' ELSE 'both' END AS side FROM (SELECT * FROM l0 WHERE block_id = 0) a FULL JOIN (SELECT * FROM l0 WHERE block_id = 1) b ON a.item = b.item)"


def _combined_sql(select: str, k: int = 60) -> str:
    c = chain("suppliers", k, 2)
    c.ctes.append(_COMBINED)
    return c.select(select)


def _combine_pair(spark: SparkSession, d: str) -> DataFrame:
    one, two, m0, m1, _ = _two("suppliers", 60)(spark, d)
    return merge.combine(one, two, m0, m1)


def _combine_cases(spark: SparkSession, d: str) -> DataFrame:
    one, two, m0, m1, _ = _two("suppliers", 60)(spark, d)
    both = merge.combine(one, two, m0, m1)
    sides = match(match(both, one.select("item", F.lit(True).alias("a")), ["item"], "left"), two.select("item", F.lit(True).alias("b")), ["item"], "left")
    return sides.select("item", "est", "err", F.when(F.col("b").isNull(), "first").when(F.col("a").isNull(), "second").otherwise("both").alias("side"))


def _map_form(spark: SparkSession, d: str) -> DataFrame:
    """Both summaries as one row of maps, merged and cut within the row."""
    one, two, m0, m1, _ = _two("suppliers", 60)(spark, d)
    packed = lambda s, c: s.agg(F.map_from_entries(F.collect_list(F.struct("item", F.struct("est", "err")))).alias(c))
    row = packed(one, "a").crossJoin(packed(two, "b")).crossJoin(m0.toDF("m0")).crossJoin(m1.toDF("m1"))
    top = merge.truncate_map(merge.combine_cols("a", "m0", "b", "m1"), 60)
    return row.select(F.inline(top)).select("item", "est", "err")


add("ss_combine_pair", _combine_pair, _combined_sql("SELECT item, est, err FROM z"))
add("ss_combine_cases", _combine_cases, _combined_sql("SELECT item, est, err, side FROM z"))
add("ss_combine_mapform", _map_form, _combined_sql("SELECT item, est, err FROM z ORDER BY est DESC, item LIMIT 60"))
add("ss_truncate", lambda spark, d: merge.truncate(_combine_pair(spark, d), 30), _combined_sql("SELECT item, est, err FROM z ORDER BY est DESC, item LIMIT 30"))
add("ss_merge_pair", lambda spark, d: merge.truncate(_combine_pair(spark, d), 60), chain("suppliers", 60, 2).flat().select("SELECT item, est, err FROM l1"))


def _top(how: str, w: str, k: int, p: int, fan_in: int = 2, every: bool = False) -> Query:
    return lambda spark, d: api.merged(summaries(w, k, p, every)(spark, d), how, p, fan_in).counters.select("item", "est", "err")


for _p in (8, 7, 5, 1):
    _c = chain("suppliers", 90, _p).tree(_p)
    add(f"ss_tree_p{_p}", _top("tree", "suppliers", 90, _p), _c.select(f"SELECT item, est, err FROM l{_c.level}"))
_c = chain("suppliers", 90, 8).tree(8, 4)
add("ss_tree_fanin4", _top("tree", "suppliers", 90, 8, 4), _c.select(f"SELECT item, est, err FROM l{_c.level}"))
add("ss_flat_p8", _top("flat", "suppliers", 90, 8), chain("suppliers", 90, 8).flat().select("SELECT item, est, err FROM l1"))


def _empty_block(spark: SparkSession, d: str) -> DataFrame:
    """Only blocks 0, 2, 4 and 6 of 8 have rows; the others merge as empty summaries."""
    rows = blocked("suppliers")(spark, d).filter("block_id % 2 = 0")
    return merge.tree(local.histogram(rows, "item", 90, blocks=P), P).counters.select("item", "est", "err")


_c = R.Chain(R.workload("suppliers", P) + f" AND key % {P} % 2 = 0", [90], blocks=P).tree(P)
add("ss_tree_emptyblock", _empty_block, _c.select(f"SELECT item, est, err FROM l{_c.level}"))


def _flat_vs_tree(spark: SparkSession, d: str) -> DataFrame:
    s = summaries("words", 100)(spark, d)
    f, t = report.prune(merge.flat(s)), report.prune(merge.tree(s, P))
    both = match(f.select("item", F.col("est").alias("fe")), t.select("item", F.col("est").alias("te")), ["item"], "full_outer")
    return both.agg(F.count("fe").alias("n_flat"), F.count("te").alias("n_tree"), F.coalesce(F.bool_and(F.col("fe").isNull() | (F.col("fe") <= F.col("te"))), F.lit(True)).alias("flat_ok"))


_c = chain("words", 100).tree(P)
_c.ctes.append(f"tt AS (SELECT item, est AS te FROM l{_c.level} JOIN h{_c.level} USING (k, block_id) WHERE est >= n // k + 1)")
_f = chain("words", 100).flat()
add("ss_flat_vs_tree", _flat_vs_tree, f"SELECT (SELECT count(*) FROM ({_f.report().select('SELECT * FROM rep')})) AS n_flat, (SELECT count(*) FROM ({_c.select('SELECT * FROM tt')})) AS n_tree, true AS flat_ok")

# ---- reports, end to end ------------------------------------------------------------------

add("ss_prune", lambda spark, d: report.prune(merge.flat(summaries("words", 400)(spark, d))).select("item", "est", "err"), chain("words", 400).flat().report().select("SELECT item, est, err FROM rep"))
add("ss_classify", lambda spark, d: report.report(merge.tree(summaries("words", 1000)(spark, d), P)), chain("words", 1000).tree(P).report().select("SELECT item, est, err, lower, status FROM rep"))

PIPELINES = {"clicks": 1000, "values": 100, "parts": 1000, "suppliers": 50, "gaps": 400, "labelled_sizes": 400, "two_attributes": 1000, "thousandths": 100, "words": 400, "word_pairs": 1000, "chat_words": 1000, "lines": 400, "hosts": 100, "tags": 100, "flows": 100, "customers": 1000, "nations": 40, "ship_days": 1000, "brand_pairs": 400, "classes": 100}
for _w, _k in PIPELINES.items():
    add(f"ss_pipeline_{_w}", lambda spark, d, w=_w, k=_k: api.frequent_items(WORKLOADS[w](spark, d), "item", k, P, "histogram", blocks="key", order_by=["key"], strict=False), chain(_w, _k).flat().report().select("SELECT item, est, err, lower, status FROM rep"))
    if _w in ("values", "words", "lines"):
        add(f"dm_pipeline_{_w}", lambda spark, d, w=_w, k=_k: baseline.deficit_merge(summaries(w, k)(spark, d), P), chain(_w, _k).deficit(P).select("SELECT item, est FROM dm"))

for _w, _k in (("words", 400), ("lines", 400), ("chat_words", 1000)):
    add(f"ss_pipeline_chunked_verified_{_w}", lambda spark, d, w=_w, k=_k: api.frequent_items(WORKLOADS[w](spark, d), "item", k, verify=True), R.exact(W[_w], _k))
add("ss_pipeline_sequential_verified", lambda spark, d: api.frequent_items(WORKLOADS["values"](spark, d), "item", 100, builder="sequential", verify=True), R.exact(W["values"], 100))
add("ss_pipeline_roundrobin_verified", lambda spark, d: api.frequent_items(WORKLOADS["values"](spark, d), "item", 200, 5, blocks="round_robin", verify=True), R.exact(W["values"], 200))
add(
    "iceberg_returnflag_shipdate",
    lambda spark, d: api.iceberg(table(spark, d, "lineitem"), [F.col("l_returnflag").alias("f"), F.col("l_linestatus").alias("s"), F.year("l_shipdate").alias("y")], 100),
    R.exact("SELECT '{\"f\":\"' || l_returnflag || '\",\"s\":\"' || l_linestatus || '\",\"y\":' || year(l_shipdate) || '}' AS item FROM lineitem", 100),
)
add("iceberg_token", lambda spark, d: api.iceberg(WORKLOADS["words"](spark, d), "item", 1000), R.exact(W["words"], 1000))

_PROBE = 200
add(
    "ss_bounds_probe",
    lambda spark, d: report.bounds(merge.flat(summaries("values", 100)(spark, d)), spark.range(_PROBE).select(F.col("id").alias("item"))),
    chain("values", 100).flat().select(f"SELECT p.range AS item, coalesce(est - err, 0)::BIGINT AS lo, coalesce(est, (SELECT m FROM h1))::BIGINT AS hi FROM range({_PROBE}) p LEFT JOIN l1 ON l1.item = p.range"),
)

# ---- invariants -----------------------------------------------------------------------------

_OK = "true AS sum_ok, true AS monitored_ok, true AS unmonitored_ok, true AS bound_ok, true AS full_ok, true AS space_ok"


def _invariants(w: str, k: int, builder: str, how: str) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        df = blocked(w)(spark, d)
        if builder == "histogram":
            s = local.histogram(df, "item", k)
        else:
            # natural partitions, each read in its own order; a tree needs them numbered 0..p-1
            s = local.per_block(WORKLOADS[w](spark, d).filter("item IS NOT NULL").select("item").repartition(P), "item", k, builder)
        return checks.invariants(api.merged(s, how, P), exact.frequencies(df, "item"))

    return run


for _b in ("histogram", "sequential", "chunked"):
    for _how in ("flat", "tree"):
        for _w, _k in (("words", 400), ("values", 100)):
            if _b == "sequential" and _w == "words":
                continue
            # n and the number of counters are the same whatever the order: k, as there are more distinct items
            add(f"inv_summary_{_b}_{_how}_{_w}", _invariants(_w, _k, _b, _how), f"SELECT count(*)::BIGINT AS n, {_k}::BIGINT AS nz, {_OK} FROM ({W[_w]}) WHERE item IS NOT NULL")


def _identity(spark: SparkSession, d: str) -> DataFrame:
    one, two, m0, m1, s = _two("suppliers", 60)(spark, d)
    side = lambda b: type(s)(s.counters.filter(f"block_id = {b}"), s.headers.filter(f"block_id = {b}"), 60)
    return checks.combine_identity(side(0), side(1), merge.combine(one, two, m0, m1))


add("inv_combine_identity", _identity, _combined_sql("SELECT count(*) AS items, sum(est)::BIGINT AS total, true AS identity_ok, true AS least_ok, true AS space_ok FROM z"))


def _space(spark: SparkSession, d: str) -> DataFrame:
    """Counters in use, before and after a merge, against their limits."""
    k = 60
    one, two, m0, m1, s = _two("suppliers", k)(spark, d)
    ours = merge.combine(one, two, m0, m1).agg(F.count("*").alias("combined"))
    low = baseline.localize(s).counters
    theirs = baseline.combine(low.filter("block_id = 0"), low.filter("block_id = 1")).agg(F.count("*").alias("deficit_combined"))
    return ours.crossJoin(theirs).select("combined", "deficit_combined", (F.col("combined") <= 2 * k).alias("ours_ok"), (F.col("deficit_combined") <= 2 * k - 2).alias("deficit_ok"))


_c = chain("suppliers", 60, 2).deficit(1)
_c.ctes.append(_COMBINED)
add("inv_space", _space, _c.select("SELECT (SELECT count(*) FROM z) AS combined, (SELECT count(DISTINCT item) FROM d0) AS deficit_combined, true AS ours_ok, true AS deficit_ok"))

# ---- extensions: weights, disjoint blocks, groups -----------------------------------------------

_CENTS = f"SELECT item, (key % {P})::INTEGER AS block_id, cents FROM ({W['customers']})"
add(
    "ss_weighted_revenue",
    lambda spark, d: api.frequent_items(WORKLOADS["customers"](spark, d), "item", 1000, P, "histogram", blocks="key", order_by=["key"], weight="cents"),
    chain("customers", 1000).flat().report().select("SELECT item, est, err, lower, status FROM rep").replace("SELECT block_id, item, count(*)::BIGINT AS est FROM s", "SELECT block_id, item, sum(cents)::BIGINT AS est FROM s").replace(R.workload("customers", P), _CENTS),
)
add(
    "ss_weighted_chunked_verified",
    lambda spark, d: api.frequent_items(WORKLOADS["customers"](spark, d), "item", 1000, weight="cents", verify=True),
    f"WITH c AS (SELECT item, sum(cents)::BIGINT AS cnt FROM ({W['customers']}) GROUP BY item) SELECT item, cnt FROM c WHERE cnt >= (SELECT sum(cnt)::BIGINT FROM c) // 1000 + 1",
)


def _disjoint(spark: SparkSession, d: str) -> DataFrame:
    rows = WORKLOADS["suppliers"](spark, d).withColumn("block_id", F.pmod("item", F.lit(P)).cast("int"))
    s = merge.disjoint(local.histogram(rows, "item", 10))
    return s.counters.select("item", "est", "err", "min_est")


_c = R.Chain(f"SELECT item, (item % {P})::INTEGER AS block_id FROM ({W['suppliers']})", [10])
add("ss_disjoint_hash", _disjoint, _c.select("SELECT item, est, err, greatest((SELECT max(m) FROM h0), min(est) OVER ())::BIGINT AS min_est FROM (SELECT * FROM l0 ORDER BY est DESC, item LIMIT 10)"))


def _grouped_sql(source: str, group: str, k: int) -> str:
    c = R.Chain(source, [k], [group]).flat().report()
    return c.select(f"SELECT {group}, item, est, err, lower, status FROM rep")


add(
    "ss_by_group_lang",
    lambda spark, d: api.frequent_items(WORKLOADS["words"](spark, d).join(table(spark, d, "documents").select(F.col("doc_id").alias("key"), "lang").filter("lang IS NOT NULL"), "key"), "item", 200, P, "histogram", blocks="key", order_by=["key"], by=["lang"]),
    _grouped_sql(f"SELECT lang, item, (key % {P})::INTEGER AS block_id FROM ({W['words']}) JOIN (SELECT doc_id AS key, lang FROM documents WHERE lang IS NOT NULL) USING (key) WHERE item IS NOT NULL", "lang", 200),
)
add(
    "ss_by_group_event_type",
    lambda spark, d: api.frequent_items(WORKLOADS["flows"](spark, d), "item", 100, P, "histogram", blocks="key", order_by=["key"], by=["event_type"]),
    _grouped_sql(f"SELECT event_type, item, (key % {P})::INTEGER AS block_id FROM ({W['flows']}) WHERE item IS NOT NULL", "event_type", 100),
)

# ---- baseline ---------------------------------------------------------------------------------

add("dm_localize", lambda spark, d: baseline.localize(summaries("suppliers", 50)(spark, d)).counters, chain("suppliers", 50).deficit(1).select("SELECT block_id, item, est FROM d0"))
add("dm_combine", lambda spark, d: _dm_combine(spark, d), chain("suppliers", 50, 2).deficit(2).select("SELECT item, est FROM a1"))
add("dm_shrink", lambda spark, d: baseline.shrink(_dm_combine(spark, d).withColumn("block_id", F.lit(0)), 50, ["block_id"]).filter("est > 0").select("item", "est"), chain("suppliers", 50, 2).deficit(2).select("SELECT item, est FROM d1"))
for _p in (8, 5):
    add(f"dm_tree_p{_p}", lambda spark, d, p=_p: baseline.deficit_merge(summaries("words", 100, p)(spark, d), p), chain("words", 100, _p).deficit(_p).select("SELECT item, est FROM dm"))
add("dm_p1_passthrough", lambda spark, d: baseline.deficit_merge(summaries("words", 100, 1)(spark, d), 1, p1_passthrough=True), chain("words", 100, 1).report().select("SELECT item, est FROM rep"))
add("dm_pruned", lambda spark, d: baseline.pruned(summaries("words", 400)(spark, d), P), chain("words", 400).tree(P).report().select("SELECT item, est FROM rep"))


def _dm_combine(spark: SparkSession, d: str) -> DataFrame:
    low = baseline.localize(summaries("suppliers", 50, 2)(spark, d)).counters
    return baseline.combine(low.filter("block_id = 0"), low.filter("block_id = 1"))


# ---- sketches --------------------------------------------------------------------------------


def _within(df: DataFrame, truth: DataFrame, ok) -> DataFrame:
    size = truth.agg(F.sum("cnt").alias("n_items"))
    rows = match(truth, df, ["item"], "left").crossJoin(F.broadcast(size))  # one row
    return rows.agg(F.count("*").alias("n_distinct"), F.sum("cnt").alias("n"), F.bool_and(ok).alias("ok"))


_DISTINCT = "SELECT count(DISTINCT item) AS n_distinct, count(*)::BIGINT AS n, true AS ok FROM ({}) WHERE item IS NOT NULL"


def _decrement(spark: SparkSession, d: str) -> DataFrame:
    df = WORKLOADS["values"](spark, d).filter("item IS NOT NULL")
    truth = exact.frequencies(df, "item")
    est = F.coalesce("est", F.lit(0))
    limit = F.call_function("div", F.col("n_items"), F.lit(100).cast("bigint"))
    return _within(sketches.decrement(df, "item", 100), truth, (est <= F.col("cnt")) & (est >= F.col("cnt") - limit))


def _lossy(spark: SparkSession, d: str) -> DataFrame:
    df = WORKLOADS["values"](spark, d).filter("item IS NOT NULL")
    found = sketches.lossy_counting(df, "item", 0.005)
    est = F.coalesce("est", F.lit(0))
    limit = F.floor(F.col("n_items") * 0.005)
    return _within(found, exact.frequencies(df, "item"), (est <= F.col("cnt")) & (F.col("cnt") <= est + F.coalesce("deficit", limit)))


add("sk_frequent_inv", _decrement, _DISTINCT.format(W["values"]))
add("sk_lossy_inv", _lossy, _DISTINCT.format(W["values"]))


def _sketch_sql(w: str, depth: int, width: int, final: str) -> str:
    h = lambda s: sketches.portable_hash_sql("item", s)
    cells = " UNION ALL ".join(f"SELECT item, cnt, {r} AS row, {h(2 * r)} % {width} AS bucket, 1 - 2 * ({h(2 * r + 1)} % 2) AS sign FROM c" for r in range(depth))
    return f"WITH c AS (SELECT item, count(*)::BIGINT AS cnt FROM ({W[w]}) GROUP BY item), x AS ({cells}) {final}"


add("sk_countmin", lambda spark, d: sketches.count_min(WORKLOADS["suppliers"](spark, d), "item", 0.02, 0.98), _sketch_sql("suppliers", 4, 136, "SELECT item, min(total)::BIGINT AS est FROM x JOIN (SELECT row, bucket, sum(cnt) AS total FROM x GROUP BY ALL) USING (row, bucket) GROUP BY item"))
add("sk_countsketch", lambda spark, d: sketches.count_sketch(WORKLOADS["suppliers"](spark, d), "item", 64, 5), _sketch_sql("suppliers", 5, 64, "SELECT item, median(total * sign)::DOUBLE AS est FROM x JOIN (SELECT row, bucket, sum(cnt * sign)::BIGINT AS total FROM x GROUP BY ALL) USING (row, bucket) GROUP BY item"))
add("sk_builtin_topk", lambda spark, d: sketches.builtin_top_k(WORKLOADS["words"](spark, d), "item", 20, 5000))
add("sk_freqitems", lambda spark, d: sketches.builtin_freq_items(WORKLOADS["values"](spark, d), "item", 0.01))
add(
    "basket_pairs",
    lambda spark, d: api.iceberg(WORKLOADS["brand_pairs"](spark, d), "item", 1000),
    R.exact(W["brand_pairs"], 1000),
)


def _fpgrowth(spark: SparkSession, d: str) -> DataFrame:
    from pyspark.ml.fpm import FPGrowth

    p = table(spark, d, "part").select("p_partkey", "p_brand")
    baskets = table(spark, d, "lineitem").select("l_orderkey", "l_partkey").join(p, F.col("l_partkey") == F.col("p_partkey")).groupBy("l_orderkey").agg(F.collect_set("p_brand").alias("items"))
    return FPGrowth(itemsCol="items", minSupport=0.01).fit(baskets).freqItemsets.select(F.array_join(F.array_sort("items"), "+").alias("items"), "freq")


add("basket_fpgrowth", _fpgrowth)

# ---- measures -----------------------------------------------------------------------------------

_GRID = {w: experiments.KS for w in WORKLOADS}
for _w, _ks in _GRID.items():
    add(f"acc_sweep_k_{_w}", lambda spark, d, w=_w, ks=_ks: experiments.accuracy(blocked(w)(spark, d), ks, P), R.accuracy(R.workload(_w, P), _ks, P))


def _in_order(spark: SparkSession, d: str) -> DataFrame:
    """The events' values in serial order, with the columns that order them."""
    return table(spark, d, "events").select(F.floor("value").cast("bigint").alias("item"), "ts", "event_id").filter("item IS NOT NULL")


for _how in ("tree", "flat"):
    add(f"acc_sequential_{_how}_values", lambda spark, d, how=_how: experiments.sequential_accuracy(_in_order(spark, d), ["ts", "event_id"], (100, 200), (1, 2, 4, 8), how))


def _acc(method: str, w: str, k: int) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        df = blocked(w)(spark, d)
        reported = experiments.reports(df, [k], P)[method].drop("k")
        return metrics.summary(reported, exact.frequencies(df, "item"), k)

    return run


for _m in ("summary", "deficit"):
    for _w, _k in (("words", 400), ("values", 200)):
        _c = chain(_w, _k).flat().report().deficit(P).truth()
        add(f"acc_summary_{_m}_{_w}", _acc(_m, _w, _k), _c.select(f"SELECT * EXCLUDE (method, k) FROM ({_c.metrics(_m, 'rep' if _m == 'summary' else 'dm')})"))
_c = chain("values", 100).flat().report().truth()
add(
    "acc_per_item",
    lambda spark, d: metrics.per_item(report.prune(merge.flat(summaries("values", 100)(spark, d))), exact.frequencies(blocked("values")(spark, d), "item")),
    _c.select("SELECT item, est, cnt, abs(cnt - est) AS abs_error, (abs(cnt - est) / cnt)::DOUBLE AS rel_error FROM rep JOIN tr USING (item)"),
)


def _recall(spark: SparkSession, d: str) -> DataFrame:
    """Frequent items that the default method (chunked, natural blocks) did not report: none."""
    out = None
    for w, k in (("values", 100), ("words", 400), ("chat_words", 1000)):
        df = api.clean(WORKLOADS[w](spark, d), "item")
        truth = exact.k_majority(df, "item", k)
        lost = report.missed(truth, api.frequent_items(df, "item", k).select("item"))
        part = truth.agg(F.count("*").alias("n_true")).crossJoin(lost.agg(F.count("*").alias("n_missed"))).select(F.lit(w).alias("workload"), "n_true", "n_missed")
        out = part if out is None else out.unionByName(part)
    return out


add("acc_recall", _recall, " UNION ALL ".join(f"SELECT '{w}' AS workload, count(*) AS n_true, 0::BIGINT AS n_missed FROM ({R.exact(W[w], k)})" for w, k in (("values", 100), ("words", 400), ("chat_words", 1000))))

for _w in NUMERIC:
    _x = "item::DOUBLE"
    add(
        f"stats_{_w}",
        lambda spark, d, w=_w: metrics.describe(api.clean(WORKLOADS[w](spark, d), "item"), "item"),
        f"""WITH s AS (SELECT item FROM ({W[_w]}) WHERE item IS NOT NULL), m AS (SELECT avg({_x}) AS mu FROM s)
SELECT count(*) AS n, count(DISTINCT item) AS n_distinct, min(item) AS min_item, max(item) AS max_item, avg({_x}) AS mean_item, median({_x}) AS median_item, stddev_samp({_x}) AS std_item,
(avg(({_x} - mu) ** 3) / (avg(({_x} - mu) ** 2) ** 1.5)) AS skew_item FROM s, m""",
    )

# ---- synthetic data and experiments ------------------------------------------------------------

_N = "SELECT count(*) FROM lineitem"
_SEEDS = (1, 2, 3)
_U = 20_000
#: Universe of the experiments: with skew 0.5 no item then reaches a 2000th of a long sequence.
_WIDE = 1_100_000
_TENTHS = range(1, 11)


def _n(spark: SparkSession, d: str) -> int:
    return table(spark, d, "lineitem").count()


def _frequencies_sql(a: float, mode: str) -> str:
    return f"SELECT seed::INTEGER AS seed, item::BIGINT AS item, count(*) AS cnt FROM ({R_items(a, mode=mode)}) GROUP BY ALL"


def R_items(a: float, rho: float = 1.5, n: str = _N, seeds=(1, 2), universe: int = _U, mode: str = "rho") -> str:
    return datagen.sql_items(n, rho, universe, seeds, a, mode)


add("gen_powerlaw", lambda spark, d: datagen.power_law(spark, _n(spark, d), 1.5, _U, (1, 2)).groupBy("seed", "item").agg(F.count("*").alias("cnt")), _frequencies_sql(0.0, "rho"))
add("gen_powerlaw_plus1", lambda spark, d: datagen.power_law(spark, _n(spark, d), 1.5, _U, (1, 2), "rho_plus_1").groupBy("seed", "item").agg(F.count("*").alias("cnt")), _frequencies_sql(0.0, "rho_plus_1"))
add("gen_shifted", lambda spark, d: datagen.shifted_power_law(spark, _n(spark, d), 1.5, _U, (1, 2)).groupBy("seed", "item").agg(F.count("*").alias("cnt")), _frequencies_sql(0.5, "rho"))


def _range_join(spark: SparkSession, d: str) -> DataFrame:
    """The same look-up for the ids of events, as a range join with the law's table, counted."""
    s = 1.5
    law = F.broadcast(datagen.cdf(spark, s, 500, 0.5))  # 500 rows
    rows = table(spark, d, "events").select(F.call_function("div", sketches.portable_hash(F.col("event_id"), 1) * F.lit(int(datagen.cumulative(s, 500, 0.5)[-1])), F.lit(sketches.PRIME).cast("bigint")).alias("x"))
    return rows.join(law, (F.col("x") >= F.col("lo")) & (F.col("x") < F.col("hi"))).groupBy("item").agg(F.count("*").alias("cnt"))


add("gen_range_join", _range_join, f"SELECT item::BIGINT AS item, count(*) AS cnt FROM ({datagen.sql_items('', 1.5, 500, [1], 0.5, ids='SELECT event_id AS id FROM events')}) GROUP BY ALL")

for _name, _a in (("plain", 0.0), ("shifted", 0.5)):
    _src = f"SELECT seed::INTEGER AS seed, item, (((id + 1) * {P} - 1) // ({_N}))::INTEGER AS block_id FROM ({R_items(_a, seeds=_SEEDS, universe=_WIDE)})"
    add(f"exp1_vary_k_{_name}", lambda spark, d, a=_a: experiments.vary_k(spark, _n(spark, d), experiments.KS, 1.5, a, P, _SEEDS, _WIDE), R.accuracy(_src, experiments.KS, P, ["seed"]))
    _sizes = " UNION ALL ".join(f"SELECT ((({_N}) * {i}) // 10)::BIGINT AS size" for i in _TENTHS)
    _src = f"SELECT seed::INTEGER AS seed, size, item, (((id + 1) * {P} - 1) // size)::INTEGER AS block_id FROM ({R_items(_a, seeds=(1,), universe=_WIDE)}), ({_sizes}) z WHERE id < size"
    add(f"exp2_vary_n_{_name}", lambda spark, d, a=_a: experiments.vary_n(spark, [_n(spark, d) * i // 10 for i in _TENTHS], 2000, 1.5, a, P, (1,), _WIDE), R.accuracy(_src, [2000], P, ["seed", "size"]))
    _rhos = (0.5, 1.0, 1.5, 2.0, 2.5, 3.0)
    _src = " UNION ALL ".join(f"SELECT seed::INTEGER AS seed, {r}::DOUBLE AS rho, item, (((id + 1) * {P} - 1) // ({_N}))::INTEGER AS block_id FROM ({R_items(_a, r, seeds=(1,), universe=_WIDE)})" for r in _rhos)
    add(f"exp3_vary_rho_{_name}", lambda spark, d, a=_a: experiments.vary_skew(spark, _n(spark, d), _rhos, 2000, a, P, (1,), _WIDE), R.accuracy(_src, [2000], P, ["seed", "rho"]))


def _vary_p(a: float) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        """The same items over 1 to 8 blocks, p as a key: blocks that have no pair pass through the tree."""
        n = _n(spark, d)
        rows = datagen.shifted_power_law(spark, n, 1.0, _U, (1,), a).select("item", "id", F.explode(F.sequence(F.lit(1), F.lit(P))).alias("p"))
        block = F.call_function("div", (F.col("id") + 1) * F.col("p") - 1, F.lit(n).cast("bigint")).cast("int")
        return experiments.accuracy(rows.withColumn("block_id", block), [400], P, ["p"])

    return run


for _name, _a in (("plain", 0.0), ("shifted", 0.5)):
    _src = f"SELECT p::INTEGER AS p, item, (((id + 1) * p - 1) // ({_N}))::INTEGER AS block_id FROM ({R_items(_a, 1.0, seeds=(1,))}), (SELECT range AS p FROM range(1, {P + 1}))"
    add(f"exp6_vary_p_{_name}", _vary_p(_a), R.accuracy(_src, [400], P, ["p"]))


def _ci(spark: SparkSession, d: str) -> DataFrame:
    runs = experiments.vary_k(spark, _n(spark, d) // 10, (100,), 1.5, 0.5, P, tuple(range(1, 21)), 2000)
    return metrics.mean_ci(runs, ["method", "k"], "total_error")


_src = f"SELECT seed::INTEGER AS seed, item, (((id + 1) * {P} - 1) // (({_N}) // 10))::INTEGER AS block_id FROM ({R_items(0.5, n=f'({_N}) // 10', seeds=tuple(range(1, 21)), universe=2000)})"
add("acc_ci", _ci, f"SELECT method, k, count(*) AS runs, avg(total_error)::DOUBLE AS mean, ({metrics.t95(19)!r} * stddev_samp(total_error) / sqrt(count(*)))::DOUBLE AS half_width FROM ({R.accuracy(_src, [100], P, ['seed'])}) GROUP BY ALL")

# ---- cost model ---------------------------------------------------------------------------------

def _daily(spark: SparkSession, d: str) -> DataFrame:
    """Workers that grow with the days of shipment in lineitem."""
    return cost.daily(table(spark, d, "lineitem"), "l_shipdate")


_PV = "(SELECT row_number() OVER (ORDER BY day) AS p, sum(c) OVER ()::DOUBLE AS n FROM (SELECT l_shipdate::DATE AS day, count(*) AS c FROM lineitem WHERE l_shipdate IS NOT NULL GROUP BY 1))"
add("cost_comm", lambda spark, d: cost.communication(_daily(spark, d), 2000), f"SELECT p, (p - 1) * 2000 AS counters FROM {_PV}")
add("cost_depth", lambda spark, d: cost.depth(_daily(spark, d)), f"SELECT p, ceil(round(log2(p), 9))::INTEGER AS depth FROM {_PV}")
add("cost_time_model", lambda spark, d: cost.time_model(_daily(spark, d), F.col("n")), f"SELECT p, t AS model_time, n / t AS speedup, n / t / p AS efficiency, n >= p * (ln(p) / ln(2)) AS cost_optimal FROM (SELECT p, n, n / p + (ln(p) / ln(2)) AS t FROM {_PV})")
add("cost_isoefficiency", lambda spark, d: cost.isoefficiency(_daily(spark, d)).withColumn("overhead", F.round("overhead", 6)), f"SELECT p, round(p * log2(p), 6) AS overhead, ceil(p * log2(p))::BIGINT AS least_n FROM {_PV}")
add("cost_scalability", lambda spark, d: cost.scalability(_daily(spark, d)).withColumn("memory_per_worker", F.round("memory_per_worker", 9)), f"SELECT p, round(log2(p), 9) AS memory_per_worker, CASE WHEN log2(p) = 0 THEN 'constant' WHEN log2(p) <= p THEN 'at most p' ELSE 'beyond' END AS growth FROM {_PV}")


def _moved(spark: SparkSession, d: str) -> DataFrame:
    """Counters that really reach the merge, against the model's limit p * k."""
    s = summaries("suppliers", 50)(spark, d)
    return s.counters.agg(F.count("*").alias("moved"), F.count_distinct("block_id").alias("blocks")).select("moved", "blocks", (F.col("moved") <= F.col("blocks") * 50).alias("within"))


add("cost_comm_measured", _moved, chain("suppliers", 50).select("SELECT count(*) AS moved, count(DISTINCT block_id) AS blocks, true AS within FROM l0"))


def _speedup(spark: SparkSession, d: str) -> DataFrame:
    """Speedup of the model's times plus a fixed share that does not scale, per order priority."""
    t = table(spark, d, "orders").groupBy(F.col("o_orderpriority").alias("method")).agg(F.count("*").alias("c"))
    runs = t.crossJoin(cost.processors(spark, (1, 2, 4, 8))).select("method", "p", (F.col("c") / F.col("p") + 0.25).alias("seconds"))
    return cost.speedup(runs)


add("bench_speedup_table", _speedup, "WITH o AS (SELECT o_orderpriority AS method, count(*) AS c FROM orders GROUP BY 1), t AS (SELECT method, p, c / p + 0.25::DOUBLE AS seconds FROM o, (SELECT unnest([1, 2, 4, 8])::BIGINT AS p)) SELECT t.method, t.p, t.seconds::DOUBLE AS seconds, (o.seconds / t.seconds)::DOUBLE AS speedup, (o.seconds / t.seconds / t.p)::DOUBLE AS efficiency, o.seconds / t.seconds / t.p > 1 AS superlinear FROM t JOIN t o ON o.method = t.method AND o.p = 1")
