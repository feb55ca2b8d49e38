"""Accuracy experiments: both methods over a grid of k (and seeds) in one plan each."""

from __future__ import annotations

import time
from collections.abc import Iterator, Sequence
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_type

from ..functions import metrics
from ..model import Summaries
from ..operators import baseline, local, merge, report
from ..operators.blocks import block_of, contiguous
from ..operators.kernels import ArrayKernel
from ..sources import datagen
from ..sources.stores import kept

#: The grid of k on real data.
KS = tuple(range(100, 1001, 100))


def by_key(df: DataFrame, p: int) -> DataFrame:
    """Blocks by the workload's key: a disjoint split without sorting."""
    return df.filter(F.col("item").isNotNull()).withColumn("block_id", F.pmod("key", F.lit(p)).cast("int"))


def reports(blocked: DataFrame, ks: Sequence[int], p: int, keys: Sequence[str] = (), how: str = "flat", weight: str | None = None) -> dict[str, DataFrame]:
    """(keys, k, item, est) of the merged summaries and of the baseline, from the same local summaries."""
    s = local.stored(local.histogram(blocked, "item", "k", [*keys, "k"], weight, ks=ks))
    top = merge.flat(s) if how == "flat" else merge.tree(s, p)
    ours = report.prune(top)
    return {"summary": ours.select(*s.keys, "item", "est"), "deficit": baseline.deficit_merge(s, p)}


def accuracy(blocked: DataFrame, ks: Sequence[int], p: int, keys: Sequence[str] = (), how: str = "flat") -> DataFrame:
    """(method, keys, k, n, n_true, n_reported, n_hit, total_error, are, precision, recall).

    The source is read once: exact counts by block are written to the shared folder,
    and both the local summaries and the truth come from them.
    """
    counts = kept(blocked.groupBy(*keys, "block_id", "item").agg(F.count("*").alias("times")), "counts")
    truth = counts.groupBy(*keys, "item").agg(F.sum("times").alias("cnt"))
    rows = None
    for method, reported in reports(counts, ks, p, keys, how, "times").items():
        part = metrics.summary(reported, truth, "k", [*keys, "k"], keys, ks).select(F.lit(method).alias("method"), "*")
        rows = part if rows is None else rows.unionByName(part)
    return rows


def synthetic(spark: SparkSession, n: int, rho: float, a: float, p: int, seeds: Sequence[int] = (1,), universe: int = 100_000) -> DataFrame:
    """(seed, id, item, block_id): contiguous blocks follow from the row number, nothing is sorted."""
    rows = datagen.shifted_power_law(spark, n, rho, universe, seeds, a)
    return rows.withColumn("block_id", block_of(F.col("id"), p, n))


def vary_k(spark: SparkSession, n: int, ks: Sequence[int], rho: float = 1.5, a: float = 0.5, p: int = 8, seeds: Sequence[int] = (1,), universe: int = 100_000) -> DataFrame:
    return accuracy(synthetic(spark, n, rho, a, p, seeds, universe), ks, p, ["seed"])


def vary_n(spark: SparkSession, ns: Sequence[int], k: int, rho: float = 1.5, a: float = 0.5, p: int = 8, seeds: Sequence[int] = (1,), universe: int = 100_000) -> DataFrame:
    """Prefixes of one sequence; each length is a bag of its own with its own blocks."""
    rows = datagen.shifted_power_law(spark, max(ns), rho, universe, seeds, a)
    each = rows.select("*", F.explode(F.array(*[F.lit(int(x)).cast("bigint") for x in ns])).alias("size")).filter("id < size")
    return accuracy(each.withColumn("block_id", block_of(F.col("id"), p, F.col("size"))), [k], p, ["seed", "size"])


def vary_skew(spark: SparkSession, n: int, rhos: Sequence[float], k: int, a: float = 0.5, p: int = 8, seeds: Sequence[int] = (1,), universe: int = 100_000) -> DataFrame:
    rows = None
    for rho in rhos:
        part = synthetic(spark, n, rho, a, p, seeds, universe).withColumn("rho", F.lit(float(rho)))
        rows = part if rows is None else rows.unionByName(part)
    return accuracy(rows, [k], p, ["seed", "rho"])


@dataclass(frozen=True)
class Case:
    """One setting of the synthetic experiments: p workers, n items of a law with skew rho and shift a."""

    p: int
    n: int
    rho: float
    a: float


#: Keys of a run; the exact counts depend on those of TRUTH alone.
RUN, TRUTH = ["seed", "p", "size", "rho", "k"], ["seed", "size", "rho"]


#: Items that a task draws at least, if there are so many, and that are counted exactly by one task at most.
TASK_ITEMS, TRUTH_ITEMS = 1 << 22, 1 << 26


def _blocks(spark: SparkSession, case: Case, ks: Sequence[int], seeds: Sequence[int], universe: int) -> DataFrame:
    """Row-form summaries of the item-at-a-time pass, for each seed, k and block.

    Block b has the row numbers floor(b * n / p) and on, in order. A task has a block
    and as many seeds as make TASK_ITEMS. Items are made where they are counted,
    nothing is shuffled or sorted; a task holds k counters for each k.
    """
    s = datagen.exponent(case.rho)
    schema = T.StructType([T.StructField("seed", T.IntegerType()), *local.row_schema(T.LongType()).fields])
    counters = to_arrow_type(schema["counters"].dataType)
    each = min(len(seeds), max(1, TASK_ITEMS * case.p // max(1, case.n)))
    parts = [seeds[i : i + each] for i in range(0, len(seeds), each)]
    p, n, a = case.p, case.n, case.a

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for task in batch.column(0).to_pylist():
                part, block = divmod(task, p)
                start, stop = block * n // p, (block + 1) * n // p
                if start == stop:
                    continue
                for seed in parts[part]:
                    kernels = {k: ArrayKernel(k, universe + 1) for k in ks}
                    for items in datagen.chunks(s, universe, a, seed, start, stop):
                        for kernel in kernels.values():
                            kernel.extend(items)
                    for k, kernel in kernels.items():
                        row = local._row(block, kernel, k, T.LongType(), counters)
                        yield pa.RecordBatch.from_arrays([pa.array([seed], pa.int32()), *row.columns], names=schema.names)

    rows = spark.range(0, p * len(parts), 1, p * len(parts)).mapInArrow(run, schema)
    keys = F.lit(p).alias("p"), F.lit(n).cast("bigint").alias("size"), F.lit(case.rho).alias("rho")
    return rows.select("seed", *keys, F.col("k").cast("int").alias("k"), "block_id", "n", "nz", "min_est", "total_est", "counters")


def _truth(spark: SparkSession, n: int, rho: float, a: float, seeds: Sequence[int], universe: int) -> DataFrame:
    """(seed, size, rho, item, cnt): exact counts, a seed and up to TRUTH_ITEMS row numbers to a task."""
    s = datagen.exponent(rho)
    parts = max(1, -(-n // TRUTH_ITEMS))
    each = min(len(seeds), max(1, TASK_ITEMS // max(1, n)))  # seeds of a task
    groups = [seeds[i : i + each] for i in range(0, len(seeds), each)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for task in batch.column(0).to_pylist():
                group, part = divmod(task, parts)
                for seed in groups[group]:
                    counts = np.zeros(universe + 1, np.int64)
                    for items in datagen.chunks(s, universe, a, seed, part * n // parts, (part + 1) * n // parts):
                        np.add.at(counts, items, 1)
                    found = np.flatnonzero(counts)
                    for at in range(0, len(found), datagen.CHUNK):
                        item = found[at : at + datagen.CHUNK]
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(item), seed), pa.int32()), pa.array(item), pa.array(counts[item])], names=["seed", "item", "cnt"])

    rows = spark.range(0, parts * len(groups), 1, parts * len(groups)).mapInArrow(run, "seed int, item long, cnt long")
    if parts > 1:
        rows = rows.groupBy("seed", "item").agg(F.sum("cnt").alias("cnt"))
    return rows.select("seed", F.lit(n).cast("bigint").alias("size"), F.lit(rho).alias("rho"), "item", "cnt")


def literal_runs(spark: SparkSession, cases: Sequence[Case], ks: Sequence[int], seeds: Sequence[int], universe: int = 1_100_000) -> DataFrame:
    """(method, seed, p, size, rho, k, measures): both methods from item-at-a-time summaries merged in a tree.

    The local phase as published: each worker passes over its contiguous block once.
    Summaries and exact counts of all cases are written once; p = 1 is a single pass,
    of which the baseline reports the pruned summary too.
    """
    union = lambda frames: reduce(DataFrame.unionByName, frames)
    rows = kept(union([_blocks(spark, c, ks, seeds, universe) for c in cases]), "literal")
    laws = {(c.n, c.rho, c.a) for c in cases}
    truth = [_truth(spark, n, rho, a, seeds, universe) for n, rho, a in sorted(laws)]
    truth = kept(union(truth), "truth")
    flat = rows.select(*RUN, "block_id", "min_est", F.inline("counters"))
    s = Summaries(flat.select(*RUN, "block_id", "item", "est", "err", "min_est"), rows.drop("counters"), "k", RUN, max(ks))
    most = max(c.p for c in cases)
    ours = report.prune(merge.tree(s, most)).select(*RUN, "item", "est")
    theirs = baseline.deficit_merge(s, most)
    if any(c.p == 1 for c in cases):
        theirs = theirs.filter("p > 1").unionByName(ours.filter("p = 1"))
    spread = {"p": sorted({c.p for c in cases})}
    return union([metrics.summary(r, truth, "k", RUN, TRUTH, ks, spread).select(F.lit(m).alias("method"), "*") for m, r in (("summary", ours), ("deficit", theirs))])


#: Items of a run time experiment that lie in the executors' memory at most, at five bytes each; more lie on their disks.
MEMORY_ITEMS = (1 << 28) // 5


def runtimes(spark: SparkSession, n: int, rho: float, k: int, ps: Sequence[int] = (1, 2, 4, 8), runs: int = 20, laws: Sequence[tuple[str, float]] = (("plain", 0.0), ("shifted", 0.5)), universe: int = 1_100_000) -> DataFrame:
    """(law, method, p, run, seconds): wall time of both methods on items that are in memory, p partitions.

    They lie there as packed numbers, many to a row, so that moving rows to the kernel is not what is timed.
    More than MEMORY_ITEMS would fill the heap, of one executor if p is 1: all of them lie on the local
    disks, from which a task reads a few rows at a time.

    The two differ in the merge alone, as the local phase is one and the same kernel.
    The cached items of a law and p are dropped before the next.
    """
    rows = []
    # a packed row is up to 640 kB: it is stored by itself, and few are handed to Python at once
    sizes = {"spark.sql.execution.arrow.maxBytesPerBatch": str(1 << 20), "spark.sql.inMemoryColumnarStorage.batchSize": "1"}
    before = {name: spark.conf.get(name) for name in sizes}
    for name, size in sizes.items():
        spark.conf.set(name, size)
    level = StorageLevel.MEMORY_AND_DISK_DESER if n <= MEMORY_ITEMS else StorageLevel.DISK_ONLY
    try:
        for law, a in laws:
            for p in ps:
                items = datagen.packed_power_law(spark, n, rho, universe, 1, a, p, narrow=True).persist(level)
                items.count()
                for run in range(runs):
                    for method in ("summary", "deficit"):
                        began = time.perf_counter()
                        s = local.per_block(items, "items", k, packed=True, narrow=True)
                        found = report.report(merge.tree(s, p)) if method == "summary" else baseline.deficit_merge(s, p)
                        found.write.format("noop").mode("overwrite").save()
                        rows.append((law, method, p, run, time.perf_counter() - began))
                items.unpersist(blocking=True)
    finally:
        for name, size in before.items():
            spark.conf.set(name, size)
    return spark.createDataFrame(rows, "law string, method string, p int, run int, seconds double")


def sequential_accuracy(rows: DataFrame, order_by: Sequence[str], ks: Sequence[int], ps: Sequence[int], how: str = "tree") -> DataFrame:
    """(p, method, k, measures): item-at-a-time local summaries of p contiguous blocks, merged both ways.

    The literal local phase; a block is read in order by one task. p = 1 is a single
    pass, of which the baseline's report is pruned as well (nothing is merged).
    """
    truth = rows.groupBy("item").agg(F.count("*").alias("cnt"))
    out = None
    for p in ps:
        dealt = contiguous(rows, p, order_by)
        for k in ks:
            s = local.per_block(dealt, "item", k, "sequential", order_by=order_by)
            top = merge.flat(s) if how == "flat" else merge.tree(s, p)
            for method, reported in (("summary", report.prune(top)), ("deficit", baseline.deficit_merge(s, p, p1_passthrough=True))):
                part = metrics.summary(reported, truth, k).select(F.lit(p).alias("p"), F.lit(method).alias("method"), F.lit(k).alias("k"), "*")
                out = part if out is None else out.unionByName(part)
    return out
