"""Session, storage and Arrow helpers shared by the text operators."""

from __future__ import annotations

import ctypes
import gc
import os
import re
import sys
import tempfile
import time
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space, the only separators the text contracts know.
ASCII_SPACE = b" \t\n\x0b\x0c\r"
#: Bytes of an Arrow batch between Spark and a Python worker; bounds buffers on both sides.
BATCH_BYTES = 4 << 20
#: Text bytes handled at once inside a Python worker; bounds every temporary array.
CHUNK_BYTES = 1 << 20


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share; a private one only where the session names none."""
    configured = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    return configured or "file://" + os.path.join(tempfile.gettempdir(), "checkpoints")


def new_path(spark: SparkSession, tag: str) -> str:
    """A fresh folder under the shared one, deleted when the application ends."""
    path = f"{shared_dir(spark).rstrip('/')}/corpus-ops/{tag}-{uuid.uuid4().hex}"
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(hadoop)
    return path


def materialise(df: DataFrame, tag: str, codec: str = "zstd") -> DataFrame:
    """Cut the lineage: write once to the shared folder and read back.

    Survives the loss of executors, unlike a local checkpoint, and is columnar,
    so later stages read only what they use.
    """
    spark = df.sparkSession
    path = new_path(spark, tag)
    df.write.option("compression", codec).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def bounded_batches(spark: SparkSession) -> None:
    """Lower the session's limit of bytes per Arrow batch, where it is above ours.

    Documents are long: the default of 64 MB a batch is held several times over by
    every task. This is a runtime setting, read when a query runs.
    """
    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    digits, unit = re.fullmatch(r"(\d+)([kmgtp]?)b?", spark.conf.get(name).lower()).groups()
    if int(digits) << 10 * " kmgtp".index(unit or " ") > BATCH_BYTES:
        spark.conf.set(name, str(BATCH_BYTES))


def release(spark: SparkSession) -> None:
    """Let Spark drop the shuffle files of finished stages whose frames are gone.

    The cleaner learns of them by the driver's garbage collection; the second pass
    reaches what the first has unlinked.
    """
    for _ in range(2):
        gc.collect()
        spark._jvm.System.gc()
        time.sleep(0.3)


def trim() -> None:
    """Give freed memory of a Python worker back: it is used again by later stages."""
    pa.default_memory_pool().release_unused()
    if sys.platform == "linux":
        trim_heap = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc alone has it
        if trim_heap:
            trim_heap(0)


def lean(function: Callable) -> Callable:
    """A function for mapInArrow that trims its worker when it ends."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from function(batches)
        trim()

    return run


def lean_group(function: Callable) -> Callable:
    """A function for applyInArrow that trims its worker after each group."""

    def run(table: pa.Table) -> pa.Table:
        out = function(table)
        trim()
        return out

    return run


def lean_pair(function: Callable) -> Callable:
    """The same for cogrouped tables."""

    def run(one: pa.Table, other: pa.Table) -> pa.Table:
        out = function(one, other)
        trim()
        return out

    return run


def utf8(array: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and int64 offsets of a string column; a null counts as empty."""
    if isinstance(array, pa.ChunkedArray):
        array = array.combine_chunks()
    if array.null_count:
        array = array.fill_null("")
    if not len(array):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    if not (pa.types.is_string(array.type) or pa.types.is_large_string(array.type)):
        array = array.cast(pa.string())
    kind = np.int64 if pa.types.is_large_string(array.type) else np.int32
    _, offsets, data = array.buffers()
    off = np.frombuffer(offsets, kind)[array.offset : array.offset + len(array) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8)[off[0] : off[-1]] if data is not None else np.zeros(0, np.uint8)
    return raw, off - off[0]


def pieces(batch: pa.RecordBatch, column: str, limit: int = CHUNK_BYTES, most_rows: int = 1 << 30) -> Iterator[pa.RecordBatch]:
    """Slices of a batch with about `limit` bytes of text and at most `most_rows` rows, one at least."""
    if not batch.num_rows:
        return
    _, off = utf8(batch.column(batch.schema.get_field_index(column)))
    start, rows = 0, batch.num_rows
    while start < rows:
        stop = int(np.searchsorted(off, off[start] + limit, side="right")) - 1
        stop = min(rows, max(stop, start + 1), start + most_rows)
        yield batch.slice(start, stop - start)
        start = stop


def field(df: DataFrame, column: str):
    """The schema field of a column, for operators that pass an id of any type through."""
    return df.schema[column]


def unused(name: str, columns: list[str]) -> str:
    """`name` behind as many underscores as make it none of the columns, whatever their case."""
    taken = {c.lower() for c in columns}
    while name in taken:
        name = f"_{name}"
    return name


def unit_hash(seed: int, *columns: str):
    """A number in [0, 1) from the columns' hash, the same on every run."""
    return F.pmod(F.xxhash64(F.lit(seed), *columns), F.lit(1 << 40)).cast("double") / float(1 << 40)


def stratified(rows: DataFrame, key: str, total: int, seed: int, *id_cols: str) -> DataFrame:
    """About `total` rows at most, an equal share for each value of `key`, chosen by a hash.

    The values of `key` are classes (languages, labels): their counts are collected.
    """
    counts = {r[0]: r[1] for r in rows.groupBy(key).count().collect()}
    if not counts:
        return rows.limit(0)
    share = total / len(counts)
    fraction = F.lit(0.0)
    for value, n in counts.items():
        fraction = F.when(F.col(key) == F.lit(value), F.lit(share / n)).otherwise(fraction)
    return rows.filter(unit_hash(seed, *id_cols) < fraction)


def code_points(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Code points of all texts, one line feed after each, and the text each belongs to."""
    joined = "\n".join(texts) + "\n"
    points = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32)
    owner = np.repeat(np.arange(len(texts), dtype=np.int64), np.fromiter((len(t) + 1 for t in texts), np.int64, len(texts)))
    return points, owner
