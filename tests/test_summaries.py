"""Worked examples and properties of counter summaries."""

import random
from collections import Counter

import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from heavyhitters.model import check_k, threshold
from heavyhitters.operators import baseline, local, merge, report
from heavyhitters.operators.kernels import ChunkedKernel, DecrementKernel, LossyKernel, SequentialKernel
from heavyhitters.plans import api


def kernel_of(items, k, kind=SequentialKernel):
    kernel = kind(k)
    kernel.update(pa.array(items))
    return kernel


def block_frame(spark, *blocks):
    return spark.createDataFrame([(b, i) for b, items in enumerate(blocks) for i in items], "block_id int, item string")


def rows(df, *cols):
    return sorted(tuple(r[c] for c in cols) for r in df.collect())


def summary_of(spark, blocks, k):
    """Long-form summaries of sequential passes."""
    kernels = [kernel_of(list(b), k) for b in blocks]
    counters = [(n, i, e, d, x.min_est) for n, x in enumerate(kernels) for i, e, d in x.rows()]
    headers = [(n, x.n, k, len(x.rows()), x.min_est, sum(r[1] for r in x.rows())) for n, x in enumerate(kernels)]
    from heavyhitters.model import Summaries

    return Summaries(spark.createDataFrame(counters, "block_id int, item string, est long, err long, min_est long"), spark.createDataFrame(headers, "block_id int, n long, k long, nz long, min_est long, total_est long"), k)


def test_threshold():
    assert threshold(11, 3) == 4
    with pytest.raises(ValueError):
        check_k(1)
    with pytest.raises(ValueError):
        check_k(5, 4)


def test_sequential_example():
    assert kernel_of("abaca", 3).rows() == [("b", 1, 0), ("c", 1, 0), ("a", 3, 0)]
    assert sorted(kernel_of("abacd", 3).rows()) == [("a", 2, 0), ("c", 1, 0), ("d", 2, 1)]
    assert sorted(kernel_of("xyxxzx", 2).rows()) == [("x", 4, 0), ("z", 2, 1)]
    assert kernel_of("aaaa", 3).rows() == [("a", 4, 0)] and kernel_of("aaaa", 3).min_est == 0


def test_two_blocks(spark):
    s = summary_of(spark, ["abacda", "ddbed"], 3)
    c1, c2 = (s.counters.filter(f"block_id = {b}") for b in (0, 1))
    both = merge.combine(c1, c2, 1, 1)
    assert rows(both, "item", "est", "err") == [("a", 4, 1), ("b", 2, 1), ("c", 2, 1), ("d", 5, 1), ("e", 2, 1)]
    for top in (merge.flat(s), merge.tree(s, 2)):
        assert rows(top.counters, "item", "est", "err") == [("a", 4, 1), ("b", 2, 1), ("d", 5, 1)]
        assert top.headers.first().min_est == 2 and top.headers.first().n == 11
        assert rows(report.report(top), "item", "status") == [("a", "potential"), ("d", "guaranteed")]
    assert rows(baseline.deficit_merge(s, 2), "item", "est") == [("a", 2), ("d", 3)]


def test_three_blocks_pass_through(spark):
    s = summary_of(spark, ["aab", "bcc", "ad"], 2)
    assert rows(merge.tree(s, 3).counters, "item", "est", "err") == [("a", 4, 1), ("c", 4, 2)]
    assert [r[0] for r in rows(merge.flat(s).counters, "item")] == ["a", "c"]


def test_empty_and_short_blocks(spark):
    s = local.histogram(block_frame(spark, "aab", "", "c"), "item", 2, blocks=4)
    heads = {r.block_id: (r.n, r.nz, r.min_est) for r in s.headers.collect()}
    assert heads == {0: (3, 2, 1), 1: (0, 0, 0), 2: (1, 1, 0), 3: (0, 0, 0)}
    assert merge.flat(s).headers.first().n == 4


def test_ties_and_identical_summaries(spark):
    s = local.histogram(block_frame(spark, "aabbc", "aabbc"), "item", 2)
    assert rows(merge.flat(s).counters, "item", "est") == [("a", 4), ("b", 4)]


def test_chunked_matches_bounds_and_sequential_invariants():
    rng = random.Random(3)
    for _ in range(60):
        k, items = rng.randint(2, 12), [rng.randint(0, 30) for _ in range(rng.randint(1, 300))]
        true = Counter(items)
        for kind in (SequentialKernel, ChunkedKernel):
            kernel = kind(k)
            for at in range(0, len(items), 37):
                kernel.update(pa.array(items[at : at + 37]))
            low = kernel.min_est
            seen = {i: (e, d) for i, e, d in kernel.rows()}
            assert len(seen) <= k and low <= len(items) // k and kernel.n == len(items)
            assert sum(e for e, _ in seen.values()) <= len(items)
            if kind is SequentialKernel:
                assert sum(e for e, _ in seen.values()) == len(items)
            for i, c in true.items():
                if i in seen:
                    e, d = seen[i]
                    assert e - low <= e - d <= c <= e
                else:
                    assert c <= low


def test_decrement_and_lossy_bounds():
    rng = random.Random(4)
    items = [min(rng.randint(0, 50), rng.randint(0, 50)) for _ in range(2000)]
    true = Counter(items)
    est = {i: e for i, e, _ in kernel_of(items, 20, DecrementKernel).rows()}
    assert len(est) <= 19 and all(true[i] - 100 <= est.get(i, 0) <= true[i] for i in true)
    lossy = {i: (c, d) for i, c, d in kernel_of(items, 0.02, LossyKernel).rows()}
    assert all(c <= true[i] <= c + d for i, (c, d) in lossy.items())
    assert all(i in lossy for i in true if true[i] > 0.02 * len(items))


def test_random_merges(spark):
    """Recall is 1; flat never above tree; the baseline with its deficit put back reports what the tree reports."""
    rng = random.Random(5)
    for _ in range(3):
        k, p = rng.randint(3, 8), rng.randint(2, 5)
        blocks = [[chr(97 + min(rng.randint(0, 20), rng.randint(0, 20))) for _ in range(rng.randint(5, 60))] for _ in range(p)]
        s = summary_of(spark, blocks, k)
        n, true = sum(map(len, blocks)), Counter(i for b in blocks for i in b)
        flat = {r.item: r.est for r in report.prune(merge.flat(s)).collect()}
        tree = {r.item: r.est for r in report.prune(merge.tree(s, p)).collect()}
        assert {i for i, c in true.items() if c >= n // k + 1} <= set(flat) <= set(tree)
        assert all(flat[i] <= tree[i] for i in flat)
        assert {r.item for r in baseline.pruned(s, p).collect()} == set(tree)


def test_frequent_items_options(spark):
    df = spark.createDataFrame([(1,), (1,), (None,), (999,), (2,), (1,)], "item long")
    assert rows(api.frequent_items(df, "item", 2, verify=True, sentinels=[999]), "item", "cnt") == [(1, 3)]
    assert rows(api.frequent_items(df, "item", 6, verify=True, nulls="fill", fill=0), "item", "cnt") == [(1, 3)]
    assert rows(api.frequent_items(df.limit(0), "item", 2, verify=True), "item", "cnt") == []
    with pytest.raises(ValueError):
        api.frequent_items(spark.createDataFrame([({"a": 1},)], "item map<string,int>"), "item", 2).collect()
    for builder in ("sequential", "chunked", "histogram"):
        for blocks in ("natural", "round_robin", "hash_row"):
            assert rows(api.frequent_items(df, "item", 2, 3, builder, blocks=blocks, order_by=["item"] if builder == "histogram" or blocks == "hash_row" else (), verify=True), "item", "cnt") in ([(1, 3)], [])


def test_tree_over_more_partitions_than_blocks(spark):
    df = spark.range(5000).select((F.col("id") % 97 % 13).alias("item")).repartition(11)
    want = rows(api.frequent_items(df, "item", 13, verify=True), "item", "cnt")
    assert want and rows(api.frequent_items(df, "item", 13, p=4, how="tree", verify=True), "item", "cnt") == want
    assert rows(api.frequent_items(df, "item", 13, p=4, blocks="key", order_by=["item"], builder="histogram", verify=True), "item", "cnt") == want


def test_weights_beyond_32_bits(spark):
    df = spark.createDataFrame([(4294967295, 3_000_000_000), (1, 1_000_000_000), (4294967295, 5)], "item long, w long")
    assert rows(api.frequent_items(df, "item", 2, weight="w", verify=True), "item", "cnt") == [(4294967295, 3_000_000_005)]


def test_disjoint(spark):
    df = spark.createDataFrame([(i % 2, str(i % 7)) for i in range(0, 140)] , "block_id int, item string").withColumn("block_id", F.pmod(F.col("item").cast("int"), F.lit(2)))
    top = merge.disjoint(local.histogram(df, "item", 3))
    assert len(top.counters.collect()) == 3 and top.headers.first().min_est >= 20
