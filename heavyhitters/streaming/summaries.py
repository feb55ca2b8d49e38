"""Frequent items over streams: windows, a running summary, per-key state, joins.

Null items count as items in windows and joins drop them; events without a time
never reach a window. Windows smaller than k have threshold 1. Streams without input
give empty results.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import Summaries, as_item, check_k, threshold_col
from ..operators import local, merge
from ..operators.blocks import room
from ..sources.stores import scratch


def file_stream(spark: SparkSession, folder: str, name: str, per_trigger: int = 1) -> DataFrame:
    """A stream over the Parquet files of a name in a folder; the schema comes from the file."""
    schema = spark.read.parquet(f"{folder}/{name}").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", name).option("maxFilesPerTrigger", per_trigger).parquet(folder)


def timed(stream: DataFrame, delay: str) -> DataFrame:
    """Event time as a timestamp with a watermark; rows later than `delay` are dropped."""
    return stream.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def run_available_now(stream: DataFrame, mode: str = "append", out: str | None = None, checkpoint: str | None = None, keys: Sequence[str] = ()) -> DataFrame:
    """Run all available input to the end and return what was written.

    Appends go to a file sink; complete results keep the last batch by foreachBatch,
    updates the last row of each of `keys` over all batches, as a batch has only what it changed. With
    `out` and `checkpoint` given, a later call goes on where this one ended; without,
    both are fresh folders that go with the application.
    """
    spark = stream.sparkSession
    out, state = out or scratch(spark, "sink"), checkpoint or scratch(spark, "stream")
    writer = stream.writeStream.option("checkpointLocation", state).trigger(availableNow=True)
    if mode == "append":
        query = writer.format("parquet").outputMode("append").start(out)
    elif mode == "update":
        if not keys:
            raise ValueError("updates need the keys of their rows")
        query = writer.outputMode(mode).foreachBatch(lambda batch, i: batch.write.mode("overwrite").parquet(f"{out}/batch={i}")).start()
        query.awaitTermination()
        rows = spark.read.schema(stream.schema.add("batch", "long")).parquet(out) if versions(spark, out, "batch=") else spark.createDataFrame([], stream.schema.add("batch", "long"))
        last = rows.groupBy(*keys).agg(F.max_by(F.struct(*stream.columns), "batch").alias("r"))
        return last.select("r.*")
    else:
        query = writer.outputMode(mode).foreachBatch(lambda batch, _: batch.write.mode("overwrite").parquet(out)).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def to_memory(stream: DataFrame, name: str, mode: str = "complete") -> DataFrame:
    """The stream's result as a table in the driver's memory: for results of bounded size, such as k counters."""
    query = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.table(name)


def rate_stream(spark: SparkSession, rows: int, partitions: int = 4) -> DataFrame:
    """(value, timestamp): numbers from 0 on, `rows` of them in each micro-batch, the same on every run."""
    return spark.readStream.format("rate-micro-batch").option("rowsPerBatch", rows).option("numPartitions", partitions).load()


def tumbling(stream: DataFrame, item: str, width: str, delay: str) -> DataFrame:
    """(start, item, cnt) of closed windows."""
    counts = timed(stream, delay).groupBy(F.window("ts", width).alias("w"), F.col(item).alias("item")).agg(F.count("*").alias("cnt"))
    return counts.select(F.col("w.start").alias("start"), "item", "cnt")


def frequent_in_windows(counts: DataFrame, k: int) -> DataFrame:
    """(start, item, cnt) of items that reach their window's own threshold."""
    totals = counts.groupBy("start").agg(F.sum("cnt").alias("n"))
    return counts.join(totals, "start").filter(F.col("cnt") >= threshold_col("n", F.lit(k))).select("start", "item", "cnt")


def sliding_from_panes(events: DataFrame, item: str, k: int, pane_seconds: int, panes: int) -> DataFrame:
    """(start, item, est, err): each window of `panes` panes, merged from one summary per pane.

    A pane is summarised once and counts in every window that covers it.
    """
    start = F.call_function("div", F.unix_timestamp(F.col("ts").cast("timestamp")), F.lit(pane_seconds).cast("bigint")) * pane_seconds
    return windows_of(local.histogram(events.withColumn("block_id", start), item, k), pane_seconds, panes)


def sliding_from_stream(stream: DataFrame, item: str, k: int, pane_seconds: int, panes: int, delay: str, out: str | None = None, checkpoint: str | None = None) -> DataFrame:
    """The same over a stream: (start, item, est, err) of windows, as far as their panes are closed.

    The stream counts the items of each pane once and appends a pane when the watermark
    closes it; windows are merged from the closed panes' summaries. Windows at the ends
    cover the panes there are. With `out` and `checkpoint` a later call goes on.
    """
    closed = run_available_now(tumbling(stream, item, f"{pane_seconds} seconds", delay), out=out, checkpoint=checkpoint)
    counts = closed.select(F.unix_timestamp("start").alias("block_id"), "item", "cnt")
    return windows_of(local.histogram(counts, "item", k, weight="cnt"), pane_seconds, panes)


def windows_of(s: Summaries, pane_seconds: int, panes: int) -> DataFrame:
    """(start, item, est, err) of all windows of `panes` panes; block_id is a pane's start in seconds."""
    shift = F.explode(F.array(*[F.lit(i * pane_seconds) for i in range(panes)])).alias("back")
    spread = lambda df: df.select("*", shift).withColumn("start", F.col("block_id") - F.col("back")).drop("back")
    return merge.flat(Summaries(spread(s.counters), spread(s.headers), s.k, ["start"])).counters.select("start", "item", "est", "err")


def sessions(stream: DataFrame, key: str, gap: str, delay: str) -> DataFrame:
    """(key, start, stop, events) of closed sessions."""
    grouped = timed(stream, delay).groupBy(F.session_window("ts", gap).alias("s"), F.col(key).alias("key")).agg(F.count("*").alias("events"))
    return grouped.select("key", F.col("s.start").alias("start"), F.col("s.end").alias("stop"), "events")


def versions(spark: SparkSession, store: str, prefix: str = "") -> list[int]:
    """Batch ids that a store has, in folders of this prefix, ascending."""
    path = spark._jvm.org.apache.hadoop.fs.Path(store)
    files = path.getFileSystem(spark._jsc.hadoopConfiguration())
    found = [x.getPath() for x in files.listStatus(path)] if files.exists(path) else []
    done = lambda p: files.exists(spark._jvm.org.apache.hadoop.fs.Path(p, "_SUCCESS"))
    names = (p.getName().removeprefix(prefix) for p in found if p.getName().startswith(prefix) and done(p))
    return sorted(int(n) for n in names if n.isdigit())


def running_summary(stream: DataFrame, item: str, k: int, store: str | None = None, checkpoint: str | None = None) -> DataFrame:
    """(item, est, err, n) of the whole stream: each micro-batch is summarised and merged into the store.

    The store keeps one version per batch id; a batch that is replayed after a failure
    starts from the version before it and overwrites its own. With `store` and
    `checkpoint` given, a later call or another application goes on where this one
    ended. Nulls are dropped; without input the result is empty.
    """
    check_k(k)
    spark = stream.sparkSession
    store, state = store or scratch(spark, "running"), checkpoint or scratch(spark, "stream")
    shape = f"item {stream.schema[item].dataType.simpleString()}, est long, err long, n long"

    def fold(batch: DataFrame, batch_id: int) -> None:
        before = [v for v in versions(spark, store) if v < batch_id]
        now = merge.flat(local.histogram(batch.filter(F.col(item).isNotNull()).withColumn("block_id", F.spark_partition_id()), item, k))
        if before:
            old = spark.read.schema(shape).parquet(f"{store}/{before[-1]}")
            past = local.with_headers(old.select("item", "est", "err").withColumn("block_id", F.lit(1)), old.agg(F.coalesce(F.max("n"), F.lit(0)).alias("n")).withColumn("block_id", F.lit(1)), k, [])
            now = merge.flat(Summaries(now.counters.drop("n").unionByName(past.counters), now.headers.unionByName(past.headers), k))
        now.counters.select("item", "est", "err").crossJoin(F.broadcast(now.headers.select("n"))).write.mode("overwrite").parquet(f"{store}/{batch_id}")

    stream.writeStream.option("checkpointLocation", state).trigger(availableNow=True).foreachBatch(fold).start().awaitTermination()
    found = versions(spark, store)
    return spark.read.schema(shape).parquet(f"{store}/{found[-1]}") if found else spark.createDataFrame([], shape)


def stateful_summary(stream: DataFrame, key: str, item: str, k: int, order_by: str = "event_id", idle_seconds: int | None = None, rooms: int = 1) -> DataFrame:
    """(key, room, n, items, ests, errs): a per-key summary kept as state, updated item by item.

    Items of a micro-batch are taken in the order of `order_by`, equal ones by item.
    Nulls are dropped. With `idle_seconds`, the state of a key without items for so
    long (of processing time) is given out once more and forgotten. With several
    `rooms` (see blocks.rooms) a key's items are dealt into so many states of k counters
    each, and n counts those of the room. A later run from the same checkpoint must
    give the same number.
    """
    check_k(k)
    item_kind = stream.schema[item].dataType.simpleString()
    key_kind = stream.schema[key].dataType.simpleString()
    shape = f"n long, items array<{item_kind}>, ests array<long>, errs array<long>"

    def update(keys: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        from ..operators.kernels import SequentialKernel

        def row(held: tuple) -> pd.DataFrame:
            return pd.DataFrame({"key": [keys[0]], "room": [keys[1]], "n": [held[0]], "items": [list(held[1])], "ests": [list(held[2])], "errs": [list(held[3])]})

        if state.hasTimedOut:
            held = state.get
            state.remove()
            yield row(held)
            return
        kernel = SequentialKernel(k)
        if state.exists:
            n, items, ests, errs = state.get
            kernel.n, kernel.est, kernel.err = n, dict(zip(items, ests)), dict(zip(items, errs))
        for frame in frames:
            kernel.extend(frame.sort_values(["_o", "_i"])["_i"].tolist())
        rows = kernel.rows()
        held = (kernel.n, [r[0] for r in rows], [r[1] for r in rows], [r[2] for r in rows])
        state.update(held)
        if idle_seconds is not None:
            state.setTimeoutDuration(idle_seconds * 1000)
        yield row(held)

    rows = stream.filter(F.col(item).isNotNull()).select(F.col(key).alias("key"), F.col(item).alias("_i"), F.col(order_by).alias("_o"))
    return rows.withColumn("room", room(as_item(rows, "_i"), rooms)).groupBy("key", "room").applyInPandasWithState(update, f"key {key_kind}, room int, {shape}", shape, "update", "NoTimeout" if idle_seconds is None else "ProcessingTimeTimeout")


def flag_candidates(stream: DataFrame, candidates: DataFrame, item: str) -> DataFrame:
    """Rows whose item is a candidate; candidates are at most k, so they are broadcast."""
    return stream.join(F.broadcast(candidates.select(F.col("item").alias(item))), item)


def distinct_within(stream: DataFrame, keys: list[str], delay: str) -> DataFrame:
    """First row of each key within the watermark."""
    return timed(stream, delay).dropDuplicatesWithinWatermark(keys)


def pairs_within(one: DataFrame, other: DataFrame, key: str, seconds: int, delay: str) -> DataFrame:
    """(key, a_id, b_id): events of `other` up to `seconds` after one of `one`, same key."""
    a = timed(one, delay).select(F.col(key), F.col("ts").alias("at"), F.col("event_id").alias("a_id"))
    b = timed(other, delay).select(F.col(key).alias("_k"), F.col("ts").alias("bt"), F.col("event_id").alias("b_id"))
    near = (F.col(key) == F.col("_k")) & (F.col("bt") > F.col("at")) & (F.col("bt") <= F.col("at") + F.expr(f"interval {seconds} seconds"))
    return a.join(b, near).select(key, "a_id", "b_id")
