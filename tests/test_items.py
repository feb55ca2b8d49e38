"""Items of every kind, and what is rejected: null, NaN, both zeros, weights, k beyond n, clashing names."""

import math
import random
from collections import Counter

import pyarrow as pa
import pytest
from pyspark.errors import PySparkException
from pyspark.sql import functions as F
from test_summaries import block_frame, rows, summary_of

from heavyhitters.functions import metrics, udfs
from heavyhitters.model import as_item, match, unused
from heavyhitters.operators import baseline, blocks, exact, local, merge, report
from heavyhitters.operators.kernels import ChunkedKernel, DecrementKernel, LossyKernel, SequentialKernel
from heavyhitters.plans import api

NAN = float("nan")
BUILDERS = {"sequential": {}, "chunked": {}, "histogram": {"blocks": "hash_row", "order_by": ["key"]}}


def named(values):
    return ["NaN" if isinstance(x, float) and math.isnan(x) else x for x in values]


def test_floats_are_one_nan_and_one_zero(spark):
    values = [NAN] * 5 + [0.0] * 3 + [-0.0] * 3 + [1.0]
    df = spark.createDataFrame([(v, i) for i, v in enumerate(values)], "item double, key int")
    want = [("0.0", 6), ("NaN", 5)]
    for builder, options in BUILDERS.items():
        for how in ("flat", "tree"):
            got = api.frequent_items(df, "item", 3, 2, builder, how, verify=True, **options).collect()
            assert sorted((str(x), c) for x, c in zip(named(r.item for r in got), (r.cnt for r in got))) == want, builder
    assert {(str(r.item), r.cnt) for r in exact.k_majority(df, "item", 3).collect()} == {("nan", 5), ("0.0", 6)}
    small = df.select(F.col("item").cast("float").alias("item"), "key")
    assert {str(r.item) for r in api.frequent_items(small, "item", 3, verify=True).collect()} == {"nan", "0.0"}


def test_kept_nulls(spark):
    values = [None] * 6 + [1, 1, 2]
    random.Random(1).shuffle(values)
    df = spark.createDataFrame([(v, i) for i, v in enumerate(values)], "item long, key int")
    for builder, options in BUILDERS.items():
        for k in (2, 3, 4):
            truth = sorted(((r.item, r.cnt) for r in exact.k_majority(df, "item", k).collect()), key=repr)
            got = api.frequent_items(df, "item", k, 3, builder, nulls="keep", verify=True, **options)
            assert sorted(((r.item, r.cnt) for r in got.collect()), key=repr) == truth and (None, 6) in truth
    assert rows(api.frequent_items(df, "item", 2, nulls="drop", verify=True), "item", "cnt") == [(1, 2)]


def test_merges_of_null_items(spark):
    kernels = [["a", None, None, "b"], [None, "c", "c", "d"]]
    s = summary_of(spark, kernels, 2)
    one, other = (s.counters.filter(f"block_id = {b}") for b in (0, 1))
    low = [s.headers.filter(f"block_id = {b}").select("min_est") for b in (0, 1)]
    both = {r.item: (r.est, r.err) for r in merge.combine(one, other, *low).collect()}
    assert len(both) == len(set(both)) and both[None][0] >= 3
    for top in (merge.flat(s), merge.tree(s, 2)):
        probe = spark.createDataFrame([(None,), ("z",)], "item string")
        bounds = {r.item: (r.lo, r.hi) for r in report.bounds(top, probe).collect()}
        assert bounds[None][0] <= 3 <= bounds[None][1] and bounds["z"][0] == 0
    truth = spark.createDataFrame([(None, 3), ("c", 2), ("a", 1), ("b", 1), ("d", 1)], "item string, cnt long")
    measured = metrics.summary(merge.flat(s).counters, truth, 4).first()
    assert measured.recall == 1 and measured.n_true == 1
    assert report.missed(truth.filter("item IS NULL"), truth.select("item")).count() == 0


@pytest.mark.parametrize("kind", [SequentialKernel, ChunkedKernel, DecrementKernel, lambda k: LossyKernel(1 / k)])
def test_kernels_take_null_and_nan(kind):
    rng = random.Random(2)
    items = [rng.choice([None, None, NAN, 0.0, -0.0, *map(float, range(30))]) for _ in range(600)]
    true = Counter("NaN" if i is not None and i != i else None if i is None else i + 0.0 for i in items)
    kernel = kind(12)
    for at in range(0, 600, 70):
        kernel.update(pa.array([None if i is None else i + 0.0 for i in items[at : at + 70]], pa.float64()))
    got = kernel.rows()
    names = named(r[0] for r in got)
    assert len(names) == len(set(names)) and None in names
    if isinstance(kernel, (SequentialKernel, ChunkedKernel)):
        low = kernel.min_est
        assert all(e - d <= true[n] <= e for n, (_, e, d) in zip(names, got)) and all(c <= low for n, c in true.items() if n not in names)


def test_weighted_kernel_with_nulls():
    kernel = ChunkedKernel(3)
    kernel.update(pa.array([None, 1, None, 2]), pa.array([5, 1, 2, 1]))
    assert kernel.rows() == [(1, 1, 0), (2, 1, 0), (None, 7, 0)]


def test_k_beyond_the_items_is_rejected(spark):
    df = spark.createDataFrame([(1,), (2,), (1,)], "item long")
    for verify in (False, True):
        with pytest.raises(PySparkException, match="k must not exceed"):
            api.frequent_items(df, "item", 100, verify=verify).collect()
    with pytest.raises(PySparkException, match="k must not exceed"):
        exact.k_majority(df, "item", 4, strict=True).collect()
    with pytest.raises(ValueError):
        api.frequent_items(df, "item", 1)
    assert rows(api.frequent_items(df, "item", 100, strict=False), "item") == [(1,), (2,)]
    assert rows(api.frequent_items(df, "item", 3), "item", "est") == [(1, 2)]
    assert api.frequent_items(df.limit(0), "item", 100).collect() == [] and exact.k_majority(df.limit(0), "item", 9, strict=True).collect() == []


def test_weights(spark):
    df = spark.createDataFrame([("a", 5, 0), ("b", 0, 1), ("c", None, 2), ("a", 1, 3), ("d", 2, 4)], "item string, w long, key int")
    for builder, options in BUILDERS.items():
        assert rows(api.frequent_items(df, "item", 2, 2, builder, weight="w", verify=True, **options), "item", "cnt") == [("a", 6)]
        assert {r.item for r in api.summarise(df, "item", 5, 2, builder, weight="w", **options).counters.collect()} == {"a", "d"}
        with pytest.raises(Exception, match="negative"):
            api.frequent_items(df.withColumn("w", F.col("w") - 3), "item", 2, 2, builder, weight="w", **options).collect()


def test_quantiles_of_students_t():
    known = {1: 12.706205, 2: 4.302653, 5: 2.570582, 10: 2.228139, 19: 2.093024, 20: 2.085963, 21: 2.079614, 30: 2.042272, 60: 2.000298, 120: 1.979930, 200: 1.971896}
    assert all(metrics.t95(v) == pytest.approx(t, abs=2e-6) for v, t in known.items())
    values = [metrics.t95(v) for v in range(1, 400)]
    assert values == sorted(values, reverse=True) and abs(metrics.t95(200) - metrics.t_series(200.0)) < 1e-7 and metrics.t95(10**9) == pytest.approx(metrics.Z)


def test_intervals_of_many_runs(spark):
    runs = spark.range(22).select(F.lit("m").alias("method"), F.col("id").cast("double").alias("v"))
    got = metrics.mean_ci(runs, ["method"], "v").first()
    assert got.half_width == pytest.approx(metrics.t95(21) * (sum((x - 10.5) ** 2 for x in range(22)) / 21) ** 0.5 / 22**0.5)
    assert metrics.mean_ci(runs.limit(1), ["method"], "v").first().half_width is None


def test_names_of_the_input_stay(spark):
    taken = ["_id", "_part", "_row", "place", "range", "before", "size", "_Place"]
    df = spark.range(40).select(F.col("id").alias("item"), *[F.lit(n).alias(c) for n, c in enumerate(taken) if c != "_Place"])
    dealt = blocks.contiguous(df.repartition(5), 7, ["item"])
    assert dealt.columns == [*df.columns, "pos", "block_id"]
    got = {r.item: (r.pos, r.block_id, r["_row"], r["size"]) for r in dealt.collect()}
    assert got == {i: (i, ((i + 1) * 7 - 1) // 40, 2, 6) for i in range(40)}
    assert unused("a", ["A", "_a"]) == "__a" and blocks.contiguous(df.limit(0), 3, ["item"]).collect() == []


def test_blocks_in_order_are_streamed(spark):
    """Several blocks to a partition, blocks longer than a batch, equal rows: the same as a plain pass."""
    rng = random.Random(4)
    data = [(i % 5, i // 3, rng.choice([None, *range(20)])) for i in range(900)]
    df = spark.createDataFrame(data, "block_id int, at int, item long").repartition(4)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "17")
    try:
        got = {r.block_id: sorted(((c.item, c.est, c.err) for c in r.counters), key=repr) for r in local.in_order(df, "item", 6, ["at"]).collect()}
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    for b in range(5):
        kernel = SequentialKernel(6)
        kernel.update(pa.array([i for _, _, i in sorted((x for x in data if x[0] == b), key=lambda x: (x[1], x[2] is not None, x[2] or 0))]))
        assert got[b] == sorted(kernel.rows(), key=repr)


def test_user_functions_take_nulls(spark):
    df = spark.createDataFrame([("g", i, x) for i, x in enumerate([None, 3, None, 3, 4, 5, None])] + [(None, 0, 1), ("n", 0, None)], "g string, o int, item long")
    got = {(r.g, r.item): r.est for r in udfs.per_group_sequential(df, "g", "item", "o", 2).collect()}
    assert got[None, 1] == 1 and got["n", None] == 1 and sum(v for (g, _), v in got.items() if g == "g") == 7
    big = spark.createDataFrame([(1, None), (1, 9007199254740993)], "g int, item long")
    dropped, held = (big.groupBy("g").agg(udfs.summary_agg(4, n)("item").alias("c")).first().c for n in ("drop", "keep"))
    assert [c["item"] for c in dropped] == [9007199254740993] and {c["item"] for c in held} == {None, 9007199254740993}


def test_joins_that_match_nulls(spark):
    a = spark.createDataFrame([(None, 1), (2, 2)], "item long, x int")
    b = spark.createDataFrame([(None, 5), (3, 6)], "item long, y int")
    assert sorted(map(tuple, match(a, b, ["item"], "full_outer").collect()), key=repr) == sorted([(None, 1, 5), (2, 2, None), (3, None, 6)], key=repr)
    assert [tuple(r) for r in match(a, b, ["item"], "left_anti").collect()] == [(2, 2)]


def test_nested_items(spark):
    df = spark.createDataFrame([([1, 2],), ([1, 2],), ([3],)], "item array<long>")
    with pytest.raises(ValueError, match="nested"):
        api.frequent_items(df, "item", 2)
    got = api.frequent_items(df, "item", 2, 2, "histogram", blocks="hash_row", order_by=["item"], verify=True)
    assert [(r.item, r.cnt) for r in got.collect()] == [([1, 2], 2)]


def test_empty_and_identical_summaries_of_the_baseline(spark):
    s = local.histogram(block_frame(spark, "aabbc", "aabbc", ""), "item", 2, blocks=3)
    assert rows(baseline.deficit_merge(s, 3), "item", "est") == [] or all(e > 0 for _, e in rows(baseline.deficit_merge(s, 3), "item", "est"))
    none = local.histogram(block_frame(spark, "a").limit(0), "item", 2)
    for top in (merge.flat(none), merge.tree(none, 4)):
        assert top.counters.collect() == []
    assert as_item(spark.createDataFrame([("x",)], "item string"), "item") is not None
