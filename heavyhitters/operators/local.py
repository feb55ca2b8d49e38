"""The local phase: one summary per block.

Null is an item like others, all NaN are one and both zeros are one. Rows of weight
0 or null count nothing, a negative weight fails the query. An empty partition has
no summary (its header would add nothing); an empty table has none at all. Equal
estimates are kept by the smaller item. Other columns of the input are not read.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_type

from ..model import Summaries, as_column, as_item, check_item_type, check_k, weighted
from ..sources.packed import counted, widened
from ..sources.stores import kept
from .blocks import room, rooms
from .kernels import ChunkedKernel, SequentialKernel

KERNELS: dict[str, Callable[[int], object]] = {"sequential": SequentialKernel, "chunked": ChunkedKernel}


def row_schema(item: T.DataType) -> T.StructType:
    """Row form of a summary: the header and an array of counters."""
    counter = T.StructType([T.StructField("item", item), T.StructField("est", T.LongType()), T.StructField("err", T.LongType())])
    longs = [T.StructField(c, T.LongType()) for c in ("n", "k", "nz", "min_est", "total_est")]
    return T.StructType([T.StructField("block_id", T.IntegerType()), *longs, T.StructField("counters", T.ArrayType(counter))])


def _row(block: int, kernel, k: int, item: T.DataType, counters_type: pa.DataType) -> pa.RecordBatch:
    rows = kernel.rows()
    counters = pa.array([[{"item": i, "est": e, "err": d} for i, e, d in rows]], counters_type)
    values = (kernel.n, k, len(rows), kernel.min_est, sum(r[1] for r in rows))
    return pa.RecordBatch.from_arrays([pa.array([block], pa.int32()), *(pa.array([v], pa.int64()) for v in values), counters], names=[f.name for f in row_schema(item)])


def in_partitions(df: DataFrame, item: str, k: int, make: Callable[[int], object], weight: str | None = None, packed: bool = False, narrow: bool = False) -> DataFrame:
    """Row-form summaries of the input's own partitions: a map without a shuffle.

    Only the item (and weight) column is read; the kernel holds k counters and a batch.
    If `packed`, a row is a binary of many unsigned 32-bit items, without weights; if
    also `narrow`, one that packed.narrowed has made.
    """
    kind = T.LongType() if packed else df.schema[item].dataType
    check_item_type(kind, kernel=True)
    schema = row_schema(kind)
    counters_type = to_arrow_type(schema["counters"].dataType)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kernel, block = make(k), None
        for batch in batches:
            if batch.num_rows:
                block = batch.column(0)[0].as_py()
                if packed:
                    for x in batch.column(1):
                        if narrow and isinstance(kernel, ChunkedKernel):
                            items, counts = counted(x.as_buffer())
                            kernel.fold(pa.array(items), counts)
                        else:
                            kernel.update(pa.array(widened(x.as_buffer()) if narrow else np.frombuffer(x.as_buffer(), "<u4").astype(np.int64)))
                else:
                    kernel.update(batch.column(1), batch.column(2) if weight else None)
        if block is not None:
            yield _row(block, kernel, k, kind, counters_type)

    columns = [F.spark_partition_id().alias("_b"), as_item(df, item).alias("_i")] + ([F.col(weight).cast("bigint").alias("_w")] if weight else [])
    return weighted(df, weight).select(*columns).mapInArrow(run, schema)


def in_order(df: DataFrame, item: str, k: int, order_by: Sequence[str], make: Callable[[int], object] = SequentialKernel, weight: str | None = None) -> DataFrame:
    """Row-form summaries of the blocks in `block_id`, each read in the given order.

    Blocks are dealt by a shuffle and sorted by Spark, which spills; the kernel reads
    them batch by batch, so a worker holds k counters and a batch whatever the size
    of a block. Rows that are equal in the order are read by item.
    """
    kind = df.schema[item].dataType
    check_item_type(kind, kernel=True)
    schema = row_schema(kind)
    counters_type = to_arrow_type(schema["counters"].dataType)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kernel, block = None, None
        for batch in batches:
            ids = batch.column(0).to_numpy()
            edges = [0, *(np.flatnonzero(ids[1:] != ids[:-1]) + 1).tolist(), len(ids)]
            for a, b in zip(edges, edges[1:]):
                if a == b:
                    continue
                if kernel is None or ids[a] != block:
                    if kernel is not None:
                        yield _row(block, kernel, k, kind, counters_type)
                    kernel, block = make(k), int(ids[a])
                kernel.update(batch.column(1).slice(a, b - a), batch.column(2).slice(a, b - a) if weight else None)
        if kernel is not None:
            yield _row(block, kernel, k, kind, counters_type)

    order = [f"_o{i}" for i in range(len(order_by))]
    columns = [F.col("block_id").cast("int").alias("_b"), as_item(df, item).alias("_i")] + ([F.col(weight).cast("bigint").alias("_w")] if weight else [])
    rows = weighted(df, weight).select(*columns, *(F.col(c).alias(o) for o, c in zip(order, order_by)))
    rows = rows.repartition("_b").sortWithinPartitions("_b", *order, "_i")
    return rows.mapInArrow(run, schema)


def from_rows(rows: DataFrame, k: int) -> Summaries:
    """Long form of row-form summaries; blocks without counters keep their header."""
    flat = rows.select("block_id", "min_est", F.explode("counters").alias("c"))
    counters = flat.select("block_id", F.col("c.item").alias("item"), F.col("c.est").alias("est"), F.col("c.err").alias("err"), "min_est")
    return Summaries(counters, rows.select("block_id", "n", "k", "nz", "min_est", "total_est"), k)


def stored(s: Summaries) -> Summaries:
    """The same summaries, written once to the shared folder: at most k counters a block."""
    return Summaries(kept(s.counters, "counters"), kept(s.headers, "headers"), s.k, s.keys, s.most)


def to_rows(s: Summaries) -> DataFrame:
    """Row form of long-form summaries, counters ascending by (est, item)."""
    packed = s.counters.groupBy(*s.block).agg(F.array_sort(F.collect_list(F.struct("est", "item", "err"))).alias("c"))
    packed = packed.select(*s.block, F.transform("c", lambda x: F.struct(x.item.alias("item"), x.est.alias("est"), x.err.alias("err"))).alias("counters"))
    return s.headers.join(packed, s.block, "left")


def keep_largest(rows: DataFrame, k: int | str, groups: Sequence[str], rank: str = "_rank", most: int | None = None) -> DataFrame:
    """The k rows of each group with the largest est, ties to smaller items.

    With a number as k, the limit is pushed below the shuffle of each group; with a
    column, its largest value `most` is.
    """
    order = [F.desc("est"), F.asc("item")]
    if not groups and isinstance(k, int):
        return rows.orderBy(*order).limit(k)
    limit: Column = F.lit(k) if isinstance(k, int) else F.col(k)
    ranked = rows.withColumn(rank, F.row_number().over(Window.partitionBy(*groups).orderBy(*order)))
    if most is not None:
        ranked = ranked.filter(F.col(rank) <= most)
    return ranked.filter(F.col(rank) <= limit).drop(rank)


def with_headers(counters: DataFrame, totals: DataFrame, k: int | str, keys: Sequence[str], most: int | None = None) -> Summaries:
    """Headers from kept counters and (keys, block_id, n) totals; adds min_est to the counters."""
    block = [*keys, "block_id"]
    size = as_column(k)
    # over the partitioning that the ranking left behind: no exchange, no join back
    whole = Window.partitionBy(*block)
    full = F.count("*").over(whole) == size
    counters = counters.withColumn("min_est", F.when(full, F.min("est").over(whole)).otherwise(F.lit(0)).cast("bigint"))
    stats = counters.groupBy(*block).agg(F.count("*").alias("nz"), F.max("min_est").alias("min_est"), F.sum("est").alias("total_est"))
    named = [] if "k" in keys else [size.cast("bigint").alias("k")]
    # put together by an aggregation, not a join, whose filters would keep the optimizer from sharing the scan
    zero = lambda *names: [F.lit(0).cast("bigint").alias(c) for c in names]
    both = totals.select(*block, F.col("n").cast("bigint").alias("n"), *zero("nz", "min_est", "total_est")).unionByName(stats.select(*block, *zero("n"), "nz", "min_est", "total_est"))
    headers = both.groupBy(*block).agg(F.sum("n").alias("n"), *(F.max(c).alias(c) for c in ("nz", "min_est", "total_est")))
    return Summaries(counters, headers.select(*block, "n", *named, "nz", "min_est", "total_est"), k, list(keys), most)


def histogram(df: DataFrame, item: str, k: int | str, keys: Sequence[str] = (), weight: str | None = None, blocks: int | None = None, ks: Sequence[int] = ()) -> Summaries:
    """Exact counts of each block in `block_id`, cut to the k largest: errors are 0.

    Only built-in aggregation and a ranking limit are used. `ks` summarises the same
    counts for several k at once; "k" then is a key. With `blocks`, blocks without
    rows get a header too.
    """
    if isinstance(k, int):
        check_k(k)
    check_item_type(df.schema[item].dataType)
    base = [c for c in keys if c != "k" or not ks]
    count = F.sum(F.col(weight).cast("bigint")) if weight else F.count("*")
    counts = weighted(df, weight).groupBy(*base, "block_id", F.col(item).alias("item")).agg(count.alias("est"))
    totals = counts.groupBy(*base, "block_id").agg(F.sum("est").alias("n"))
    if blocks:
        every = df.sparkSession.range(blocks).select(F.col("id").cast("int").alias("block_id"))
        if base:
            every = totals.select(*base).distinct().crossJoin(F.broadcast(every))
        totals = every.join(totals, [*base, "block_id"], "left").withColumn("n", F.coalesce("n", F.lit(0)))
    most = max(ks) if ks else None
    if ks:  # ranked once, for the largest k
        order = Window.partitionBy(*base, "block_id").orderBy(F.desc("est"), F.asc("item"))
        ranked = counts.withColumn("_rank", F.row_number().over(order)).filter(F.col("_rank") <= most)
        each = F.explode(F.array(*[F.lit(int(x)) for x in ks])).alias("k")
        largest = ranked.select("*", each).filter(F.col("_rank") <= F.col("k")).drop("_rank")
        totals, k, base = totals.select("*", each), "k", [*base, "k"]
    else:
        largest = keep_largest(counts, k, [*base, "block_id"])
    # nothing is cached: totals, counters and headers share the exchange of the counts, so the source is read once
    return with_headers(largest.withColumn("err", F.lit(0).cast("bigint")), totals, k, base, most)


def per_block(df: DataFrame, item: str, k: int, builder: str = "chunked", weight: str | None = None, order_by: Sequence[str] = (), packed: bool = False, narrow: bool = False) -> Summaries:
    """One summary per block by the named builder.

    histogram needs a `block_id` column; sequential and chunked take the input's own
    partitions, or the blocks of `block_id` read in order if `order_by` is given. Their
    row-form result, one row of at most k counters per block, is written to the shared
    folder when this is called, as merges read counters and headers from it several
    times: the source is scanned once, and an executor may be lost later.
    """
    check_k(k)
    if builder == "histogram":
        return histogram(df, item, k, weight=weight)
    make = KERNELS[builder]
    rows = in_order(df, item, k, order_by, make, weight) if order_by else in_partitions(df, item, k, make, weight, packed, narrow)
    return from_rows(kept(rows, "summaries"), k)


def sequential(df: DataFrame, item: str, k: int, order_by: Sequence[str], start: int | None = None, end: int | None = None, position: str | None = None, track_error: bool = True) -> DataFrame:
    """(item, est, err) of one pass over the whole input, or over positions start..end, in order.

    The pass is one task by nature; it is the reference the parallel method is
    measured against.
    """
    rows = df.filter(F.col(position).between(start, end)) if position else df
    one = in_order(rows.withColumn("block_id", F.lit(0)), item, k, order_by, lambda size: SequentialKernel(size, track_error))
    return one.select(F.inline("counters"))


def sequential_exact(df: DataFrame, item: str, k: int, order_by: Sequence[str]) -> DataFrame:
    """(item, est, err) of passes that never lack a counter: exact counts, errors 0.

    Up to k different items, it is one pass over the whole input, in order; more are
    dealt by item into rooms of at most k, each with a pass of k counters of its own.
    """
    dealt = df.withColumn("block_id", room(as_item(df, item), rooms(df, item, k)))
    return in_order(dealt, item, k, order_by).select(F.inline("counters"))
