"""The plans are those that scale: no shuffle under the local phase, pruned scans, broadcast of bounded sides."""

from pyspark.sql import functions as F

from conftest import DATA
from heavyhitters.operators import exact, local, merge, report
from heavyhitters.plans import api
from heavyhitters.sources.workloads import WORKLOADS, table


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_local_phase_does_not_shuffle(spark):
    rows = local.in_partitions(table(spark, DATA, "lineitem"), "l_suppkey", 10, local.KERNELS["chunked"])
    text = plan(rows)
    assert "Exchange" not in text and "MapInArrow" in text
    assert "ReadSchema: struct<l_suppkey:bigint>" in text


def test_verification_broadcasts_candidates(spark):
    df = WORKLOADS["suppliers"](spark, DATA)
    text = plan(report.verify(df, "item", exact.k_majority(df, "item", 100).select("item"), 6000, 100))
    assert "BroadcastHashJoin" in text and "CartesianProduct" not in text


def test_limit_is_pushed_below_the_group_shuffle(spark):
    df = WORKLOADS["suppliers"](spark, DATA).withColumn("block_id", F.pmod("key", F.lit(4)))
    assert "WindowGroupLimit" in plan(local.histogram(df, "item", 5).counters)


def test_filters_reach_the_scan(spark):
    text = plan(table(spark, DATA, "events").filter("event_id >= 100 AND event_id < 200").select("value"))
    assert "GreaterThanOrEqual(event_id,100)" in text and "ReadSchema: struct<event_id:bigint,value:double>" in text


def scans(df):
    """Scans that ran: reused exchanges have none of their own."""
    df.collect()
    return plan(df).split("== Initial Plan ==")[0].count("FileScan")


def test_the_source_is_read_once(spark):
    histogram = {"builder": "histogram", "blocks": "key", "order_by": ["key"]}
    assert scans(api.frequent_items(WORKLOADS["words"](spark, DATA), "item", 400, **histogram)) == 1
    assert scans(exact.k_majority(WORKLOADS["words"](spark, DATA), "item", 400)) == 1
    tree = merge.tree(local.histogram(WORKLOADS["words"](spark, DATA).withColumn("block_id", F.pmod("key", F.lit(8)).cast("int")), "item", 400), 8)
    assert scans(tree.counters) == 1


def test_verification_is_one_more_scan(spark):
    """Kernel summaries are written, so the plan that is left scans the source for the verification alone."""
    text = plan(api.frequent_items(WORKLOADS["suppliers"](spark, DATA), "item", 100, verify=True))
    assert text.count("l_suppkey#") and text.count("lineitem.parquet") == 1


def test_a_tree_grows_by_a_level_at_a_time(spark):
    s = local.histogram(WORKLOADS["suppliers"](spark, DATA).withColumn("block_id", F.pmod("key", F.lit(64)).cast("int")), "item", 5)
    size = [len(merge.tree(s, p).counters._jdf.queryExecution().optimizedPlan().toString().split("\n")) for p in (4, 16, 64)]
    assert size[2] - size[1] <= size[1] - size[0] + 2


def test_the_largest_k_is_pushed_below_the_shuffle(spark):
    rows = WORKLOADS["suppliers"](spark, DATA).withColumn("block_id", F.pmod("key", F.lit(4)))
    assert "WindowGroupLimit" in plan(local.histogram(rows, "item", "k", ["k"], ks=(3, 5)).counters)


def test_no_cartesian_in_the_report(spark):
    text = plan(api.frequent_items(WORKLOADS["suppliers"](spark, DATA), "item", 100, builder="histogram", blocks="key", order_by=["key"]))
    assert "CartesianProduct" not in text


def test_registry_needs_no_session():
    import subprocess
    import sys
    from pathlib import Path

    code = "import __spark_entry__ as e; assert len(e.queries()) > 150 and e.oracle_sql()"
    subprocess.run([sys.executable, "-c", code], cwd=Path(__file__).parent.parent, check=True, timeout=120)
