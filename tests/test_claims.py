"""What the experiments are to show: the merged summaries beat the deficit merge, and how each measure moves."""

import pytest

from heavyhitters.plans import experiments
from heavyhitters.sources.workloads import WORKLOADS

SF = "/root/testdata/sf0.01"


def measured(df):
    return {tuple(r[c] for c in df.columns if c in ("method", "k", "size", "rho", "p")): r for r in df.collect()}


@pytest.mark.parametrize("workload,ks", [("values", (100, 200, 1000)), ("words", (100, 400, 1000)), ("chat_words", (400,)), ("suppliers", (50, 100))])
def test_real_data(spark, workload, ks):
    got = measured(experiments.accuracy(experiments.by_key(WORKLOADS[workload](spark, SF), 8), ks, 8))
    for k in ks:
        ours, theirs = got["summary", k], got["deficit", k]
        assert ours.recall == theirs.recall == 1
        assert ours.total_error <= theirs.total_error and (ours.precision or 0) >= (theirs.precision or 0)


def test_vary_k(spark):
    got = measured(experiments.vary_k(spark, 60_000, (100, 400, 1000), universe=20_000))
    for k in (100, 400, 1000):
        assert got["summary", k].precision == 1 and got["summary", k].total_error == 0 and got["deficit", k].precision < 0.2
    falling = [got["deficit", k].total_error for k in (100, 400, 1000)]
    assert falling == sorted(falling, reverse=True) and falling[-1] > 0


def test_vary_n(spark):
    got = measured(experiments.vary_n(spark, (12_000, 36_000, 60_000), 200, universe=20_000))
    growing = [got["deficit", n, 200] if ("deficit", n, 200) in got else got["deficit", 200, n] for n in (12_000, 36_000, 60_000)]
    errors = [r.total_error for r in growing]
    assert errors == sorted(errors) and all(r.precision == 1 for x, r in got.items() if x[0] == "summary")


def test_vary_skew(spark):
    rhos = (0.5, 1.0, 1.5, 2.0, 2.5, 3.0)
    rows = experiments.vary_skew(spark, 60_000, rhos, 200, universe=20_000).collect()
    by = {(r.method, r.rho): r for r in rows}
    assert by["summary", 0.5].n_true == 0 and by["deficit", 0.5].precision == 0
    assert all(by["summary", r].precision == 1 and by["summary", r].total_error == 0 for r in rhos[1:])
    errors = {r: by["deficit", r].total_error for r in rhos}
    assert max(errors, key=errors.get) == 1.0 and errors[2.5] == errors[3.0] == 0
    assert all(by["deficit", r].precision < 0.2 for r in rhos)


def test_one_block_is_the_sequential_pass(spark):
    from heavyhitters.registry import _in_order

    got = {(r.p, r.method): r for r in experiments.sequential_accuracy(_in_order(spark, SF), ["ts", "event_id"], (100,), (1, 8)).collect()}
    one = got[1, "summary"]
    assert (one.n_true, one.n_reported) == (35, 35) and one.total_error == got[1, "deficit"].total_error
    eight = got[8, "summary"]
    assert eight.recall == 1 and eight.n_reported == 37 and eight.total_error == 52
    assert got[8, "deficit"].n_reported == 93 and got[8, "deficit"].total_error == 4932


def test_literal_runs(spark):
    """The item-at-a-time experiments: recall 1, one worker alike, more workers more error, and only the baseline imprecise."""
    from heavyhitters.plans.experiments import Case, literal_runs

    cases, ks, seeds = [Case(p, 30_000, 1.5, 0.5) for p in (1, 2, 8)], (100, 400, 1000), (1, 2, 3)
    got = {(r.method, r.p, r.k, r.seed): r for r in literal_runs(spark, cases, ks, seeds, 100_000).collect()}
    assert len(got) == 2 * 3 * 3 * 3 and all(r.recall == 1 for r in got.values())
    for seed in seeds:
        for k in ks:
            ours, theirs = ({p: got[m, p, k, seed] for p in (1, 2, 8)} for m in ("summary", "deficit"))
            assert ours[1].total_error == theirs[1].total_error and ours[1].precision == theirs[1].precision
            for p in (2, 8):
                assert ours[p].total_error <= theirs[p].total_error and ours[p].precision >= 0.9 > 0.5 > theirs[p].precision
            assert theirs[8].total_error > theirs[1].total_error
    for p in (2, 8):
        falling = [sum(got["deficit", p, k, s].total_error for s in seeds) for k in ks]
        assert falling == sorted(falling, reverse=True)


def test_blocks_of_a_range_are_contiguous(spark):
    """Partition i of a range of n rows starts at floor(i * n / p), which the literal runs rely on."""
    from pyspark.sql import functions as F

    for n, p in ((60_175, 8), (10, 7), (1001, 5)):
        first = spark.range(0, n, 1, p).groupBy(F.spark_partition_id().alias("b")).agg(F.min("id").alias("low"))
        assert {r.b: r.low for r in first.collect()} == {b: b * n // p for b in range(p)}


def test_long_sequences(spark):
    """The verified report of the summaries is the exact answer."""
    import __spark_entry__
    from conftest import DATA

    q = __spark_entry__.queries()
    exact, ours = ({(r.item, r.cnt) for r in q[n](spark, DATA).collect()} for n in ("exact_synthetic_long", "ss_synthetic_long_verified"))
    assert exact == ours and len(exact) > 50
