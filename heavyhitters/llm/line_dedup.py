"""Line deduplication with two Bloom filters.

Each task marks the hashes of its line keys in a filter of once-seen keys, and
those met again in a filter of twice-seen keys; the tasks' filters merge by OR,
and what stands in both sides' once-filters is twice-seen too. Only keys that
the merged twice-filter suspects are shuffled, as strong digests with counts,
for the exact number of documents and the first occurrence.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import ASCII_SPACE, bounded_batches, field, lean, materialise, pieces, unused

#: Bits of each filter: a power of two by the size of the input, within these limits.
#: A fuller filter only suspects more, the counts stay exact.
LEAST_BITS, UNKNOWN_BITS, MOST_BITS = 1 << 20, 1 << 24, 1 << 29
BITS_PER_LINE = 8
#: Bytes of a line that the size of a filter reckons with.
LINE_BYTES = 16
PROBES = 4
CHUNK_BITS = 1 << 20
#: Repeated keys up to this many bytes of digests are broadcast; more are joined.
BROADCAST_BYTES = 4 << 20
MERGE_FAN_IN = 64


def line_keys(text: str | None) -> tuple[list[bytes], list[bytes]]:
    """Lines in UTF-8 and their keys: ASCII space stripped at both ends, A-Z lower-cased."""
    lines = (text or "").encode().split(b"\n")
    return lines, [line.strip(ASCII_SPACE).lower() for line in lines]


def long_enough(key: bytes, least: int) -> bool:
    return len(key) >= least and (least <= 1 or len(key.decode()) >= least)


def _digest(key: bytes) -> bytes:
    return hashlib.blake2b(key, digest_size=16).digest()


def _positions(hashes: np.ndarray, bits: int) -> np.ndarray:
    step = (hashes >> np.uint64(32)) | np.uint64(1)
    return (hashes[:, None] + np.arange(PROBES, dtype=np.uint64) * step[:, None]) & np.uint64(bits - 1)


def _set(filter_: np.ndarray, positions: np.ndarray) -> None:
    p = positions.ravel()
    np.bitwise_or.at(filter_, (p >> np.uint64(3)).astype(np.int64), np.left_shift(np.uint8(1), (p & np.uint64(7)).astype(np.uint8)))


def _has(filter_: np.ndarray, positions: np.ndarray) -> np.ndarray:
    cell = filter_[(positions >> np.uint64(3)).astype(np.int64)]
    return ((cell >> (positions & np.uint64(7)).astype(np.uint8)) & 1).all(axis=1)


def filter_bits(docs: DataFrame) -> int:
    """Bits of a filter for all lines, from the size that the optimizer knows without a scan."""
    size = int(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    if size >= docs.sparkSession._jsparkSession.sessionState().conf().defaultSizeInBytes():  # not known
        return UNKNOWN_BITS
    return min(max(1 << (size // LINE_BYTES * BITS_PER_LINE).bit_length(), LEAST_BITS), MOST_BITS)


def twice_filter(docs: DataFrame, least: int, bits: int) -> np.ndarray:
    """The merged filter of keys that at least two documents seem to have."""
    chunk_bytes = min(CHUNK_BITS, bits) // 8

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        once, twice = np.zeros(bits // 8, np.uint8), np.zeros(bits // 8, np.uint8)
        for whole in batches:
            for part in pieces(whole, "_text"):
                found: list[int] = []
                for text in part.column(1).to_pylist():
                    found += {xxhash.xxh3_64_intdigest(k) for k in line_keys(text)[1] if long_enough(k, least)}
                if not found:
                    continue
                hashes, count = np.unique(np.array(found, np.uint64), return_counts=True)
                at = _positions(hashes, bits)
                _set(twice, at[(count > 1) | _has(once, at)])
                _set(once, at)
        rows = [(i, once[i * chunk_bytes : (i + 1) * chunk_bytes], twice[i * chunk_bytes : (i + 1) * chunk_bytes]) for i in range(bits // 8 // chunk_bytes)]
        rows = [r for r in rows if r[1].any()]
        yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([zlib.compress(r[1].tobytes(), 1) for r in rows], pa.binary()), pa.array([zlib.compress(r[2].tobytes(), 1) for r in rows], pa.binary())], names=["chunk", "once", "twice"])

    def merge(table: pa.Table) -> pa.Table:
        once, twice = np.zeros(chunk_bytes, np.uint8), np.zeros(chunk_bytes, np.uint8)
        for a, b in zip(table["once"], table["twice"]):
            a, b = (np.frombuffer(zlib.decompress(x.as_py()), np.uint8) for x in (a, b))
            twice |= b | (once & a)
            once |= a
        return pa.table({"chunk": table["chunk"][:1].cast(pa.int32()), "once": [zlib.compress(once.tobytes(), 1)], "twice": [zlib.compress(twice.tobytes(), 1)]})

    shape = "chunk int, once binary, twice binary"
    parts = docs.mapInArrow(lean(build), shape).withColumn("_some", F.floor(F.spark_partition_id() / MERGE_FAN_IN))
    merged = parts.groupBy("chunk", "_some").applyInArrow(lambda t: merge(t), shape).groupBy("chunk").applyInArrow(merge, shape)
    out = np.zeros(bits // 8, np.uint8)
    for row in merged.select("chunk", "twice").toLocalIterator():  # `bits` bits in all
        out[row.chunk * chunk_bytes : (row.chunk + 1) * chunk_bytes] = np.frombuffer(zlib.decompress(bytes(row.twice)), np.uint8)
    return out


def repeated_keys(docs: DataFrame, min_docs: int, min_key_chars: int = 1, bits: int | None = None, flush: int = 100_000) -> DataFrame:
    """(digest, n_docs, first): line keys of at least `min_docs` documents, counted exactly.

    `docs` has (_id, _text). `first` is the smallest (document, line) that has the key.
    Counts are summed per task before they are shuffled, so a key that every
    document has reaches its counter as one row per task.
    """
    if min_docs < 2:
        raise ValueError("min_docs must be at least 2")
    spark = docs.sparkSession
    bits = bits or filter_bits(docs)
    seen = spark.sparkContext.broadcast(zlib.compress(twice_filter(docs, min_key_chars, bits).tobytes(), 1))
    kind = field(docs, "_id").dataType
    first = T.StructType([T.StructField("id", kind), T.StructField("line", T.LongType())])
    out = T.StructType([T.StructField("digest", T.BinaryType()), T.StructField("n", T.LongType()), T.StructField("id", kind), T.StructField("line", T.LongType())])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        twice = np.frombuffer(zlib.decompress(seen.value), np.uint8)
        held: dict[bytes, list] = {}
        id_type: list[pa.DataType] = []

        def rows() -> pa.RecordBatch:
            values = list(held.values())
            return pa.RecordBatch.from_arrays([pa.array(list(held), pa.binary()), pa.array([v[0] for v in values], pa.int64()), pa.array([v[1] for v in values], id_type[0]), pa.array([v[2] for v in values], pa.int64())], names=out.names)

        for whole in batches:
            id_type[:] = [whole.schema.field(0).type]
            for part in pieces(whole, "_text"):
                docs_of: list[int] = []
                keys: list[tuple[bytes, int]] = []
                hashes: list[int] = []
                ids = part.column(0).to_pylist()
                for i, text in enumerate(part.column(1).to_pylist()):
                    own: set[bytes] = set()
                    for at, key in enumerate(line_keys(text)[1]):
                        if key not in own and long_enough(key, min_key_chars):
                            own.add(key)
                            docs_of.append(i)
                            keys.append((key, at))
                            hashes.append(xxhash.xxh3_64_intdigest(key))
                if not keys:
                    continue
                for j in np.flatnonzero(_has(twice, _positions(np.array(hashes, np.uint64), bits))):
                    (key, at), id_ = keys[j], ids[docs_of[j]]
                    had = held.setdefault(_digest(key), [0, id_, at])
                    had[0] += 1
                    if id_ is not None and (had[1] is None or (id_, at) < (had[1], had[2])):
                        had[1:] = [id_, at]
                if len(held) >= flush:
                    yield rows()
                    held.clear()
        if held:
            yield rows()

    where = F.when(F.col("id").isNotNull(), F.struct("id", "line")).cast(first)
    counted = docs.mapInArrow(lean(count), out).groupBy("digest").agg(F.sum("n").alias("n_docs"), F.min(where).alias("first"))
    return counted.filter(F.col("n_docs") >= min_docs)


def dedup_lines(docs: DataFrame, min_docs: int = 10, min_key_chars: int = 1, keep_first: bool = False, output: str = "digest", id_col: str = "doc_id", text_col: str = "text", bits: int | None = None, broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """Drop every line whose key at least `min_docs` documents (rows) have.

    Keys are lines without ASCII space at both ends, A-Z lower-cased; keys under
    `min_key_chars` code points never count. A null or empty text is one empty
    line. With `keep_first` the first occurrence, by document id then line, stays.
    Kept lines are joined by a line feed; a document may end up empty.

    `output`: "digest" gives (id, n_lines, n_dropped, kept_sha256), "lines" adds
    the kept text, "documents" gives the input's own columns with the text
    replaced (and `n_chars` recounted if it is there). Rows that repeat are
    documents of their own; null ids are allowed but never a first occurrence.
    Columns of any names pass through "documents".

    `bits` is the size of a filter, by the input's size if not given and at most
    2**29. Beyond some 10**8 distinct lines the filters fill up and more keys are
    suspected, at worst all: then every line's digest is counted by the shuffle.
    """
    spark = docs.sparkSession
    bounded_batches(spark)
    base = docs.select(F.col(id_col).alias("_id"), F.col(text_col).cast("string").alias("_text"))
    repeated = materialise(repeated_keys(base, min_docs, min_key_chars, bits), "lines")
    few = repeated.count() * 16 <= broadcast_bytes
    kind = field(base, "_id").dataType
    if output == "documents":
        out = docs.schema
        rows = docs
        text_at, id_at = docs.columns.index(text_col), docs.columns.index(id_col)
    else:
        fields = [T.StructField(id_col, kind), T.StructField("n_lines", T.LongType()), T.StructField("n_dropped", T.LongType()), T.StructField("kept_sha256", T.StringType())]
        out = T.StructType(fields + [T.StructField("kept", T.StringType())] * (output == "lines"))
        rows, text_at, id_at = base, 1, 0
    known = repeated.select("digest", "first.id", "first.line").toArrow() if few else None
    firsts = zip(known["id"].to_pylist(), known["line"].to_pylist()) if few else ()
    table = spark.sparkContext.broadcast(dict(zip(known["digest"].to_pylist(), firsts)) if few else {})

    def apply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = table.value
        for whole in batches:
            named = whole.rename_columns([f"c{i}" for i in range(whole.num_columns)])
            for part in pieces(named, f"c{text_at}"):
                lists = part.column(part.num_columns - 1).to_pylist() if not few else None
                counts, texts = [], []
                for i, (id_, text) in enumerate(zip(part.column(id_at).to_pylist(), part.column(text_at).to_pylist())):
                    here = known if few else {d["digest"]: (d["id"], d["line"]) for d in lists[i] or ()}
                    lines, keys = line_keys(text)
                    if here:
                        kept = []
                        for at, (line, key) in enumerate(zip(lines, keys)):
                            hit = long_enough(key, min_key_chars) and _digest(key)
                            if not hit or hit not in here or (keep_first and here[hit] == (id_, at)):
                                kept.append(line)
                    else:
                        kept = lines
                    counts.append((len(lines), len(lines) - len(kept)))
                    texts.append(b"\n".join(kept))
                if output == "documents":
                    arrays = [part.column(i) for i in range(len(out))]
                    strings = [t.decode() for t in texts]
                    changed = [c[1] > 0 for c in counts]
                    arrays[text_at] = pa.array([s if x else o for s, x, o in zip(strings, changed, arrays[text_at].to_pylist())], arrays[text_at].type)
                    if "n_chars" in out.names:
                        at = out.names.index("n_chars")
                        arrays[at] = pa.array([len(s) if x else o for s, x, o in zip(strings, changed, arrays[at].to_pylist())], arrays[at].type)
                else:
                    arrays = [part.column(0), pa.array([c[0] for c in counts], pa.int64()), pa.array([c[1] for c in counts], pa.int64()), pa.array([hashlib.sha256(t).hexdigest() for t in texts])]
                    arrays += [pa.array([t.decode() for t in texts])] * (output == "lines")
                yield pa.RecordBatch.from_arrays(arrays, names=out.names)

    if not few:
        rows = _with_own_keys(rows, repeated, rows.columns[id_at], rows.columns[text_at], min_key_chars)
    return rows.mapInArrow(lean(apply), out)


def _with_own_keys(rows: DataFrame, repeated: DataFrame, id_col: str, text_col: str, least: int) -> DataFrame:
    """The rows with the repeated keys each of them has, by a join instead of a broadcast.

    The keys stand in one more column, the last, under a name that the rows do not have.
    """
    row = unused("row", rows.columns)
    rows = materialise(rows.withColumn(row, F.monotonically_increasing_id()), "lines-rows")

    def keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for part in pieces(whole, "_text"):
                at, digest = [], []
                for r, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                    own = {_digest(k) for k in line_keys(text)[1] if long_enough(k, least)}
                    at += [r] * len(own)
                    digest += own
                yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(digest, pa.binary())], names=["_at", "digest"])

    own = rows.select(F.col(row).alias("_at"), rows[text_col].cast("string").alias("_text")).mapInArrow(lean(keys), "_at long, digest binary").join(repeated, "digest")
    at, held = unused("at", rows.columns), unused("keys", rows.columns)
    own = own.groupBy(F.col("_at").alias(at)).agg(F.collect_list(F.struct("digest", "first.id", "first.line")).alias(held))
    return rows.join(own, rows[row] == own[at], "left").drop(row, at)
