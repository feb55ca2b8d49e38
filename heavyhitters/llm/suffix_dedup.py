"""Exact removal of repeated byte strings by a suffix sort.

A byte goes if a string of `length` bytes over it also starts in a document with
a smaller id. The work is spread by anchors: every window of `length` bytes picks
the smallest hashed q-gram inside it, so equal windows have equal anchors. Anchors
of one document only are settled by their hash alone; around the others the bytes
are gathered, those suffixes sorted that share their hash with another, and in each
run of suffixes that agree for `length` bytes the smallest document stays. Hashes only propose: whatever is
removed has been compared byte by byte.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator
from copy import copy

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import bounded_batches, field, lean, lean_group, lean_pair, materialise, pieces, release, utf8
from .fingerprints import mix, powers, prefix, spans

#: Bytes of the q-grams that anchors are.
GRAM = 16
#: Text bytes of a group of documents, anchors of a bucket, and text bytes whose
#: repeated windows meet in one suffix sort, about.
GROUP_BYTES = 4 << 20
BUCKET_ANCHORS = 1_000_000
SORT_BYTES = 2 << 20
FLUSH = 1_000_000
#: Text bytes whose anchors are found at once: arrays of eight times their size stay in a core's cache.
PIECE_BYTES = 1 << 18
#: Groups of documents whose repeated windows are settled together before all are.
FAN_IN = 1024
#: Copies of whole texts whose ids, and repeated digests that, may be broadcast.
BROADCAST_ROWS = 1 << 18
#: Copies from which on a text's digest is always broadcast: one key is one task otherwise.
HOT_ROWS = 100_000
#: Bits that a window's place may take from its hash where both are sorted as one number.
PLACE_BITS = 24
_LOW = np.uint64((1 << 40) - 1)
_NO_ID = (1 << 63) - 1


# ---- bytes ---------------------------------------------------------------------------


def words(data: np.ndarray, length: int) -> tuple[np.ndarray, list[int]]:
    """Eight bytes from every position as one number that sorts like them, and the steps that cover `length`."""
    view = np.ndarray((max(len(data) - 7, 0),), ">u8", np.ascontiguousarray(data), strides=(1,))
    return view, [*range(0, length - 8, 8), length - 8]


def same_bytes(data: np.ndarray, a: np.ndarray, b: np.ndarray, length: int) -> np.ndarray:
    """Whether `length` bytes from a and from b are equal."""
    view, steps = words(data, length)
    equal = np.ones(len(a), bool)
    for i in steps:
        equal &= view[a + i] == view[b + i]
    return equal


def later_windows(hashed: np.ndarray, owner: np.ndarray, data: np.ndarray, at: np.ndarray, length: int) -> np.ndarray:
    """Windows (starting at `at`) that a smaller document has too, as far as neighbours by hash and id show.

    Equal hashes, or upper bits of them, count only if the bytes agree. Where other
    bytes with the same hash stand between equal windows, the later one is left to
    the suffix sort.
    """
    later = np.zeros(len(hashed), bool)
    if not len(later):
        return later
    place = len(hashed).bit_length()
    if place <= PLACE_BITS and (owner[1:] >= owner[:-1]).all():
        # owners rise: a number of the hash's upper bits and the place sorts as both keys would
        packed = np.sort(hashed >> np.uint64(place) << np.uint64(place) | np.arange(len(hashed), dtype=np.uint64))
        order, upper = (packed & np.uint64((1 << place) - 1)).astype(np.int64), packed >> np.uint64(place)
    else:
        order = np.lexsort((owner, hashed))
        upper = hashed[order]
    lead = np.ones(len(order), bool)
    same = np.flatnonzero(upper[1:] == upper[:-1])
    lead[same[same_bytes(data, at[order[same]], at[order[same + 1]], length)] + 1] = False
    first = np.flatnonzero(lead)
    least = np.repeat(owner[order[first]], np.diff(np.concatenate([first, [len(order)]])))
    later[order] = owner[order] > least
    return later


# ---- suffix sort ---------------------------------------------------------------------


class Suffixes:
    """Suffixes of a byte array, told apart by their first `length` bytes."""

    def __init__(self, data: np.ndarray, starts: np.ndarray, length: int):
        self.data, self.starts, self.length = data, starts, length
        self.sums = prefix(data)
        self.inverse = powers(len(self.sums), inverse=True)
        self.whole = self._hash(starts, np.full(len(starts), length))

    def _hash(self, start: np.ndarray, size: np.ndarray) -> np.ndarray:
        return (self.sums[start + size] - self.sums[start]) * self.inverse[start]

    def repeated(self) -> tuple[np.ndarray, Suffixes]:
        """(indices, suffixes) whose hash another one has; the first `length` bytes of any other occur once."""
        order = np.argsort(self.whole)
        same = np.flatnonzero(self.whole[order[1:]] == self.whole[order[:-1]])
        twice = np.zeros(len(order), bool)
        twice[order[same]] = twice[order[same + 1]] = True
        out = copy(self)
        out.starts, out.whole = self.starts[twice], self.whole[twice]
        return np.flatnonzero(twice), out

    def by_bytes(self, order: np.ndarray) -> np.ndarray:
        """Indices of suffixes in order of their first `length` bytes, equal ones as they stood.

        Eight bytes are sorted at a time, and only where all before them agree.
        """
        view, steps = words(self.data, self.length)
        order = order.copy()
        slot, run = np.arange(len(order)), np.zeros(len(order), np.int64)
        for i in steps:
            word = view[self.starts[order[slot]] + i].astype(np.uint64)
            rank = np.argsort(word, kind="stable") if i == 0 else np.lexsort((word, run))
            word, run = word[rank], run[rank]
            order[slot] = order[slot[rank]]
            tied = np.zeros(len(slot) + 1, bool)
            tied[1:-1] = (word[1:] == word[:-1]) & (run[1:] == run[:-1])
            run = np.cumsum(~tied[:-1])
            still = tied[1:] | tied[:-1]
            slot, run = slot[still], run[still]
            if not len(slot):
                break
        return order

    def order(self) -> np.ndarray:
        """Indices of the suffixes in order of their first `length` bytes, as far as hashes tell equal ones.

        Suffixes with one hash stand together, and one of them is sorted for all: where
        many copies meet, it is their number alone that grows.
        """
        together = np.argsort(self.whole, kind="stable")
        if len(together) < 2:
            return together
        start = np.flatnonzero(np.concatenate([[True], self.whole[together[1:]] != self.whole[together[:-1]]]))
        size = np.diff(np.concatenate([start, [len(together)]]))
        one = together[start]
        rank = np.empty(len(self.whole), np.int64)
        rank[one] = np.arange(len(one))
        classes = rank[self.by_bytes(one)]
        _, member = _expand(start[classes], size[classes])
        return together[member]

    def _compared(self, order: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Of each neighbouring pair in the order: whether the bytes agree, whether they rise."""
        view, steps = words(self.data, self.length)
        equal, rises = np.ones(max(len(order) - 1, 0), bool), np.zeros(max(len(order) - 1, 0), bool)
        for i in steps:
            word = view[self.starts[order] + i].astype(np.uint64)
            rises |= equal & (word[:-1] < word[1:])
            equal &= word[:-1] == word[1:]
        return equal, rises

    def runs(self) -> tuple[np.ndarray, np.ndarray]:
        """(order, first of run): suffixes whose first `length` bytes are equal, byte by byte.

        The order that hashes gave is verified on the bytes of all neighbours; if a
        collision has spoilt it, the bytes themselves are sorted.
        """
        order = self.order()
        equal, rises = self._compared(order)
        if not (equal | rises).all():
            order = self.by_bytes(np.arange(len(order)))
            equal, _ = self._compared(order)
        new = np.ones(len(order), bool)
        new[1:] = ~equal
        return order, np.flatnonzero(new)


def later_suffixes(data: np.ndarray, at: np.ndarray, owner: np.ndarray, length: int) -> np.ndarray:
    """Windows (starting at `at`) that a smaller document has too, all of them."""
    later = np.zeros(len(at), bool)
    twice, repeated = Suffixes(data, at, length).repeated()
    order, lead = repeated.runs()
    if len(order):
        owner = owner[twice][order]
        later[twice[order]] = owner > np.repeat(np.minimum.reduceat(owner, lead), np.diff(np.concatenate([lead, [len(order)]])))
    return later


# ---- anchors -------------------------------------------------------------------------


def anchors(data: np.ndarray, off: np.ndarray, length: int) -> tuple[np.ndarray, ...]:
    """(document, hash, first window, windows) of each anchor, and the prefix sums.

    Consecutive windows with the same leftmost smallest q-gram share an anchor.
    """
    none = np.zeros(0, np.int64)
    sums = prefix(data)
    per = np.maximum(np.diff(off) - length + 1, 0)
    total = int(per.sum())
    if not total:
        return none, none.astype(np.uint64), none, none, sums
    grams = len(data) - GRAM + 1
    hashed = ((sums[GRAM:] - sums[:-GRAM]) * powers(grams, inverse=True)) * np.uint64(0x9E3779B97F4A7C15)
    best = (hashed & np.uint64(0xFFFFFFFF00000000)) | np.arange(grams, dtype=np.uint64)
    span, wide = 1, length - GRAM + 1
    while 2 * span <= wide:
        best = np.minimum(best[:-span], best[span:])
        span *= 2
    if span < wide:
        best = np.minimum(best[: len(best) - (wide - span)], best[wide - span :])
    doc = np.repeat(np.arange(len(per)), per)
    window = np.arange(total) - np.repeat(np.cumsum(per) - per, per) + np.repeat(off[:-1], per)
    place = (best[window] & np.uint64(0xFFFFFFFF)).astype(np.int64)
    edge = np.flatnonzero(np.concatenate([[True], place[1:] != place[:-1]]))
    at = place[edge]
    return doc[edge], spans(sums, at, at + GRAM), window[edge], np.diff(np.concatenate([edge, [total]])), sums


def _keys(hashes: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """Bucket of each anchor, and bucket and 40 bits of the hash as one key."""
    bucket = (hashes >> np.uint64(40)) * np.uint64(buckets) >> np.uint64(24)
    return bucket.astype(np.int64), (bucket << np.uint64(40)) | (hashes & _LOW)


def _join(table: pa.Table, name: str, kind: type) -> np.ndarray:
    """All numbers packed in a binary column, row after row."""
    parts = [np.zeros(0, np.uint8)]
    for chunk in table[name].chunks:
        _, offsets, data = chunk.buffers()
        if len(chunk) and data is not None:
            off = np.frombuffer(offsets, np.int64 if pa.types.is_large_binary(chunk.type) else np.int32)
            parts.append(np.frombuffer(data, np.uint8)[off[chunk.offset] : off[chunk.offset + len(chunk)]])
    return np.concatenate(parts).view(kind)


def _binary(data: np.ndarray, cuts: np.ndarray) -> pa.Array | pa.ChunkedArray:
    """A binary column, of whose rows each packs data[cuts[i]:cuts[i + 1]]."""
    data = np.ascontiguousarray(data)
    if data.nbytes >= 1 << 31:  # more than one array holds
        return pa.array([data[i:j].tobytes() for i, j in zip(cuts[:-1], cuts[1:])], pa.binary())
    return pa.Array.from_buffers(pa.binary(), len(cuts) - 1, [None, pa.py_buffer((cuts * data.itemsize).astype(np.int32)), pa.py_buffer(data)])


def _by_group(group: np.ndarray, *columns: np.ndarray) -> tuple:
    """(groups, binary columns): a row for each group, its numbers packed in the order they had."""
    order = np.argsort(group, kind="stable")
    group = group[order]
    cuts = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1], [True]])) if len(group) else np.zeros(1, np.int64)
    return group[cuts[:-1]], *(_binary(c[order], cuts) for c in columns)


def _among(values: np.ndarray, known: np.ndarray) -> np.ndarray:
    """Which values are in `known`, which is sorted."""
    if not len(known):
        return np.zeros(len(values), bool)
    return known[np.minimum(np.searchsorted(known, values), len(known) - 1)] == values


def repeated_anchors(texts: DataFrame, length: int, buckets: int, fan_in: int = FAN_IN) -> DataFrame:
    """(_g, hot, ids, keys): packed (document, anchor) pairs whose anchor more than one document has.

    A document sends each anchor once. Where a task knows of a repeat by itself it
    settles that at once and sends one mark, so a hot anchor is no hot bucket. `hot`
    are anchors settled so, and those that more than `fan_in` documents have.
    """
    shape = "bucket int, low binary, high binary, doc binary, ids binary, groups binary"

    def emit(held: list[tuple]) -> pa.RecordBatch:
        hashed, owner = np.concatenate([h[0] for h in held]), np.concatenate([h[1] for h in held])
        ids, groups = np.concatenate([h[2] for h in held]), np.concatenate([h[3] for h in held])
        order = np.argsort(hashed, kind="stable")  # documents stay in order within a hash
        hashed, owner = hashed[order], owner[order]
        once = np.ones(len(hashed), bool)
        once[1:] = (hashed[1:] != hashed[:-1]) | (owner[1:] != owner[:-1])
        hashed, owner = hashed[once], owner[once]
        start = np.flatnonzero(np.concatenate([[True], hashed[1:] != hashed[:-1]]))
        size = np.diff(np.concatenate([start, [len(hashed)]]))
        known = np.repeat(size > 1, size)
        bucket, key = _keys(hashed, buckets)
        to, pairs, keys = _by_group(groups[owner[known]], ids[owner[known]], key[known])
        rows = [(buckets + g, b"", k, b"", i, b"") for g, i, k in zip(to.tolist(), pairs.to_pylist(), keys.to_pylist())]
        settled = known[start]
        hashed, owner, bucket, key = hashed[start], owner[start], bucket[start], key[start]
        cuts = np.searchsorted(bucket, np.arange(buckets + 1))
        for b, (i, j) in enumerate(zip(cuts[:-1], cuts[1:])):
            if j > i:
                mine, local = np.unique(owner[i:j], return_inverse=True)
                local = np.where(settled[i:j], len(mine) + size[i:j] - 1, local).astype(np.uint32)
                part = key[i:j] & _LOW
                rows.append((b, part.astype(np.uint32).tobytes(), (part >> np.uint64(32)).astype(np.uint8).tobytes(), local.tobytes(), ids[mine].tobytes(), groups[mine].tobytes()))
        columns = list(zip(*rows))
        return pa.RecordBatch.from_arrays([pa.array(columns[0], pa.int32()), *(pa.array(c, pa.binary()) for c in columns[1:])], names=["bucket", "low", "high", "doc", "ids", "groups"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        n = docs = 0
        for whole in batches:
            for part in pieces(whole, "_text", PIECE_BYTES):
                doc, hashed, _, _, _ = anchors(*utf8(part.column(2)), length)
                if len(doc):
                    held.append((hashed, doc + docs, part.column(0).to_numpy(), part.column(1).to_numpy()))
                    docs, n = docs + part.num_rows, n + len(doc)
                if n >= FLUSH:
                    yield emit(held)
                    held, n, docs = [], 0, 0
        if held:
            yield emit(held)

    def meet(table: pa.Table) -> pa.Table:
        bucket = table["bucket"][0].as_py() if table.num_rows else 0
        if bucket >= buckets:
            return pa.table({"_g": pa.array([bucket - buckets] * table.num_rows, pa.int32()), "hot": pa.array([True] * table.num_rows), "ids": table["ids"], "keys": table["high"]})
        low, high = _join(table, "low", np.uint32), _join(table, "high", np.uint8)
        ids, groups, docs = [], [], []
        for r in range(table.num_rows):
            local = np.frombuffer(table["doc"][r].as_py(), np.uint32).astype(np.int64)
            known = np.frombuffer(table["ids"][r].as_py(), np.int64)
            # past the end stands the mark of a repeat that is settled already, further by each of its documents
            ids.append(np.append(known, 0)[np.minimum(local, len(known))])
            groups.append(np.append(np.frombuffer(table["groups"][r].as_py(), np.int32), -1)[np.minimum(local, len(known))])
            docs.append(np.maximum(local - len(known), 0) + 1)
        ids, groups, docs = np.concatenate(ids), np.concatenate(groups), np.concatenate(docs)
        key = low.astype(np.uint64) | high.astype(np.uint64) << np.uint64(32)
        order = np.argsort(key, kind="stable")
        start = np.flatnonzero(np.concatenate([[True], key[order][1:] != key[order][:-1]]))
        size = np.diff(np.concatenate([start, [len(key)]]))
        hot = np.repeat(np.add.reduceat(docs[order], start) > fan_in, size)
        # a mark alone means two documents
        go = np.repeat(size > 1, size) & (groups[order] >= 0)
        hit, hot = order[go], hot[go]
        to, *packed = _by_group(groups[hit].astype(np.int64) * 2 + hot, ids[hit], key[hit] | np.uint64(bucket) << np.uint64(40))
        return pa.table({"_g": pa.array(to >> 1, pa.int32()), "hot": pa.array((to & 1).astype(bool)), "ids": packed[0], "keys": packed[1]})

    return texts.mapInArrow(lean(run), shape).groupBy("bucket").applyInArrow(lean_group(meet), "_g int, hot boolean, ids binary, keys binary")


# ---- windows -------------------------------------------------------------------------

_FOUND = "_g int, ids binary, start binary, stop binary"


def _runs_of(keep: np.ndarray, record: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First and last index of each run of kept, consecutive windows of one record."""
    linked = keep[1:] & keep[:-1] & (record[1:] == record[:-1])
    first = np.flatnonzero(keep & ~np.concatenate([[False], linked]))
    last = np.flatnonzero(keep & ~np.concatenate([linked, [False]]))
    return first, last


def _expand(first: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    record = np.repeat(np.arange(len(count)), count)
    return record, first[record] + np.arange(len(record)) - np.repeat(np.cumsum(count) - count, count)


def _open(later: np.ndarray, record: np.ndarray, window: np.ndarray, records: int) -> tuple[np.ndarray, np.ndarray]:
    """First and last window of each record that is not settled; last before first if all are."""
    left, right = np.full(records, np.iinfo(np.int64).max), np.full(records, -1)
    np.minimum.at(left, record[~later], window[~later])
    np.maximum.at(right, record[~later], window[~later])
    return left, right


def repeated_windows(texts: DataFrame, suspects: DataFrame, length: int, buckets: int, groups: int, sorts: int, fan_in: int = FAN_IN) -> DataFrame:
    """(_g, ids, start, stop): packed byte ranges that a smaller document has too.

    A group of documents first compares its own windows: those that a smaller
    document of the group has are settled there, so of a window that many
    documents share at most one document of each group goes on. With more than
    `fan_in` groups, windows of hot anchors are settled among `fan_in` of them in the
    same way before the rest meets, so that an anchor which all documents have is no
    hot task. All other windows are sorted once, whatever the number of groups.
    """
    names = ("ids", "start", "count", "groups", "keys", "bytes")
    shape = "bucket long, " + ", ".join(f"{n} binary" for n in names)
    parts = -(-groups // fan_in)
    first_sorts = max(8, -(-sorts // parts))

    def settled(group: np.ndarray, ids: np.ndarray, start: np.ndarray, stop: np.ndarray) -> pa.Table:
        """Rows of ranges to remove; they travel under the negative of their group."""
        to, *packed = _by_group(group.astype(np.int64), ids, start.astype(np.uint32), stop.astype(np.uint32))
        empty = pa.array([b""] * len(to), pa.binary())
        return pa.table([pa.array(-1 - to, pa.int64()), *packed, empty, empty, empty], names=["bucket", *names])

    def onward(ids: np.ndarray, lo: np.ndarray, hi: np.ndarray, group: np.ndarray, keys: np.ndarray, data: np.ndarray, at: np.ndarray, first: np.ndarray) -> pa.Table:
        """Rows of windows lo..hi of records, with their bytes, which stand at `at`; `first` are to meet among `fan_in` groups."""
        bucket = np.where(first, sorts + group // fan_in * first_sorts + keys.astype(np.int64) % first_sorts, keys.astype(np.int64) % sorts)
        to, *packed = _by_group(bucket, ids, lo.astype(np.uint32), (hi - lo + 1).astype(np.uint8), group.astype(np.int32), keys)
        order = np.argsort(bucket, kind="stable")
        size = (hi - lo + length)[order]
        _, byte = _expand(at[order], size)
        ends = np.concatenate([[0], np.cumsum(size)])[np.searchsorted(bucket[order], np.append(to, np.iinfo(np.int64).max))]
        return pa.table([pa.array(to, pa.int64()), *packed, _binary(data[byte], ends)], names=["bucket", *names])

    def nothing() -> pa.Table:
        return pa.table([pa.array([], pa.int64()), *[pa.array([], pa.binary())] * 6], names=["bucket", *names])

    def codes(marks: pa.Table) -> np.ndarray:
        return np.unique(mix(_join(marks, "ids", np.int64).view(np.uint64)) ^ _join(marks, "keys", np.uint64) * np.uint64(0x9E3779B97F4A7C15))

    def gather(docs: pa.Table, marks: pa.Table) -> pa.Table:
        if not docs.num_rows or not marks.num_rows:
            return nothing()
        group = docs["_g"][0].as_py()
        wanted, many = codes(marks), codes(marks.filter(marks["hot"])) if parts > 1 else np.zeros(0, np.uint64)
        held, base = [], 0
        docs = docs.select(["_o", "_text"])
        docs = docs.sort_by("_o") if docs.nbytes < 1 << 31 else docs
        for batch in docs.combine_chunks().to_batches():
            for part in pieces(batch, "_text", PIECE_BYTES):
                data, off = utf8(part.column(1))
                ids = part.column(0).to_numpy()
                doc, hashed, first, count, sums = anchors(data, off, length)
                _, key = _keys(hashed, buckets)
                code = mix(ids[doc].view(np.uint64)) ^ key * np.uint64(0x9E3779B97F4A7C15)
                use = _among(code, wanted)
                doc, first, count = doc[use], first[use], count[use]
                _, window = _expand(first, count)
                held.append((ids[doc], first - off[doc], count, (mix(key[use]) >> np.uint64(32)).astype(np.uint32), _among(code[use], many), first + base, data, spans(sums, window, window + length)))
                base += len(data)
        ids, begin, sizes, keys, hot, at, data, hashed = (np.concatenate(x) for x in zip(*held))
        record, window = _expand(begin, sizes)
        later = later_windows(hashed, ids[record], data, (at - begin)[record] + window, length)
        a, b = _runs_of(later, record)
        done = settled(np.full(len(a), group), ids[record[a]], window[a], window[b] + length)
        left, right = _open(later, record, window, len(sizes))
        go = np.flatnonzero(right >= 0)
        return pa.concat_tables([done, onward(ids[go], left[go], right[go], np.full(len(go), group), keys[go], data, (at - begin + left)[go], hot[go])])

    def compared(table: pa.Table) -> tuple:
        """The records of a bucket, and which of their windows a smaller document has."""
        ids, begin, count, group = _join(table, "ids", np.int64), _join(table, "start", np.uint32).astype(np.int64), _join(table, "count", np.uint8).astype(np.int64), _join(table, "groups", np.int32)
        data = _join(table, "bytes", np.uint8)
        size = count + length - 1
        base = np.cumsum(size) - size
        record, at = _expand(base, count)
        later = later_suffixes(data, at, ids[record], length)
        window = begin[record] + at - base[record]
        a, b = _runs_of(later, record)
        found = group[record[a]], ids[record[a]], window[a], window[b] + length
        return found, (ids, begin, group, data, base, record, window, later)

    def narrow(table: pa.Table) -> pa.Table:
        """One bucket of some groups: what is not settled goes on to all groups' bucket."""
        if not table.num_rows:
            return nothing()
        found, (ids, begin, group, data, base, record, window, later) = compared(table)
        left, right = _open(later, record, window, len(ids))
        go = np.flatnonzero(right >= 0)
        return pa.concat_tables([settled(*found), onward(ids[go], left[go], right[go], group[go], _join(table, "keys", np.uint32)[go], data, (base - begin + left)[go], np.zeros(len(go), bool))])

    def compare(table: pa.Table) -> pa.Table:
        found, _ = compared(table)
        to, *packed = _by_group(found[0], found[1], found[2].astype(np.uint32), found[3].astype(np.uint32))
        return pa.table([pa.array(to, pa.int32()), *packed], names=["_g", "ids", "start", "stop"])

    spark = texts.sparkSession
    # written once, since what is settled, hot and open goes three ways, and the texts' shuffle can go
    rows = materialise(texts.groupBy("_g").cogroup(suspects.groupBy("_g")).applyInArrow(lean_pair(gather), shape), "windows", "lz4")
    release(spark)
    if parts > 1:
        first = materialise(rows.filter(F.col("bucket") >= sorts).groupBy("bucket").applyInArrow(lean_group(narrow), shape), "hot", "lz4")
        rows = rows.filter(F.col("bucket") < sorts).unionByName(first)
    done = rows.filter("bucket < 0").select((F.lit(-1) - F.col("bucket")).cast("int").alias("_g"), "ids", "start", F.col("count").alias("stop"))
    return rows.filter("bucket >= 0").groupBy("bucket").applyInArrow(lean_group(compare), _FOUND).unionByName(done)


def _cut(docs: pa.Table, found: pa.Table, keep_text: bool, names: list[str]) -> pa.Table:
    """Digest columns of a group of documents, its byte ranges taken out."""
    ids, start, stop = _join(found, "ids", np.int64), _join(found, "start", np.uint32), _join(found, "stop", np.uint32)
    order = np.argsort(ids, kind="stable")
    ids, start, stop = ids[order], start[order].astype(np.int64), stop[order].astype(np.int64)
    rows: list[tuple] = []
    for order_id, text in zip(docs["_o"].to_numpy(), docs["_text"]):
        data = (text.as_py() or "").encode()
        i, j = np.searchsorted(ids, [order_id, order_id + 1] if order_id < _NO_ID else [order_id, order_id], side="left")
        j = j if order_id < _NO_ID else len(ids)
        removed = spans_n = 0
        if j > i:
            depth = np.zeros(len(data) + 1, np.int64)
            np.add.at(depth, start[i:j], 1)
            np.add.at(depth, stop[i:j], -1)
            gone = np.cumsum(depth)[:-1] > 0
            removed = int(gone.sum())
            spans_n = int(gone[0]) + int((gone[1:] & ~gone[:-1]).sum())
            kept = np.frombuffer(data, np.uint8)[~gone].tobytes()
        else:
            kept = data
        rows.append((len(data), removed, spans_n, hashlib.sha256(kept).hexdigest(), kept))
    columns = list(zip(*rows)) if rows else [()] * 5
    out = [docs["_id"], pa.array(columns[0], pa.int64()), pa.array(columns[1], pa.int64()), pa.array(columns[2], pa.int64()), pa.array(columns[3], pa.string())]
    return pa.table(out + [pa.array(columns[4], pa.binary())] * keep_text, names=names)


def copies_of(known: DataFrame, few: int = BROADCAST_ROWS, hot_rows: int = HOT_ROWS) -> DataFrame:
    """The rows whose digest a smaller id has, by the smallest id of each repeated digest.

    Digests of many copies are at most rows / `hot_rows`; they are broadcast within
    the limit, so that the join deals only short groups by digest.
    """
    first = materialise(known.groupBy("digest").agg(F.min("_o").alias("low"), F.count("*").alias("rows")).filter("rows > 1"), "first")
    if first.count() <= few:
        return known.join(F.broadcast(first), "digest").filter("_o > low")
    hot, rest = first.filter(F.col("rows") >= hot_rows), first.filter(F.col("rows") < hot_rows)
    some = known.join(F.broadcast(hot) if hot.count() <= few else hot, "digest").filter("_o > low")
    return some.unionByName(known.join(rest, "digest").filter("_o > low"))


def dedup_strings(docs: DataFrame, length: int = 50, keep_bytes: bool = False, id_col: str = "doc_id", text_col: str = "text", fan_in: int = FAN_IN) -> DataFrame:
    """(id, n_bytes, n_removed, n_spans, kept_sha256) per row; `kept` too with `keep_bytes`.

    A byte of the UTF-8 text is removed if a string of `length` bytes that covers
    it also starts in a document with a smaller id; strings never cross documents
    and are judged on the input. Ids are integers; a null id stands after all
    others. Rows with equal ids do not remove from each other. A null text is
    empty; texts shorter than `length` stay whole. `length` must be from 17 to 250.
    Whole texts that a smaller id has as well are settled by their digest.
    """
    if not GRAM < length <= 250:
        raise ValueError("length must be from 17 to 250")
    spark = docs.sparkSession
    bounded_batches(spark)
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    base = docs.select(F.col(id_col).alias("_id"), F.coalesce(F.col(id_col).cast("long"), F.lit(_NO_ID)).alias("_o"), text.alias("_text"), F.xxhash64(text).alias("_x"))
    raw = F.encode("_text", "UTF-8")
    known = materialise(base.select("_id", "_o", "_x", F.octet_length("_text").cast("long").alias("n"), F.sha2(raw, 256).alias("digest")), "strings")
    copies = materialise(copies_of(known).select("_id", "_o", "_x", "n", "digest"), "copies")
    few = copies.count() <= BROADCAST_ROWS
    gone = copies.select("_o", "_x").distinct()
    total = int(known.agg(F.sum("n")).first()[0] or 0)
    groups = max(8, math.ceil(total / GROUP_BYTES))
    buckets = max(8, math.ceil(total / 18 / BUCKET_ANCHORS))
    texts = base.join(F.broadcast(gone) if few else gone, ["_o", "_x"], "left_anti").select("_o", F.pmod(F.xxhash64("_o", "_x"), F.lit(groups)).cast("int").alias("_g"), "_text", "_id")
    # the group of a row follows from id and text; rows that repeat both stand together
    suspects = materialise(repeated_anchors(texts.select("_o", "_g", "_text"), length, buckets, fan_in), "anchors", "lz4")
    release(spark)
    found = materialise(repeated_windows(texts.select("_o", "_g", "_text"), suspects, length, buckets, groups, max(8, math.ceil(total / SORT_BYTES)), fan_in), "ranges", "lz4")
    release(spark)
    kind = field(base, "_id").dataType
    fields = [T.StructField(id_col, kind), T.StructField("n_bytes", T.LongType()), T.StructField("n_removed", T.LongType()), T.StructField("n_spans", T.LongType()), T.StructField("kept_sha256", T.StringType())]
    out = T.StructType(fields + [T.StructField("kept", T.BinaryType())] * keep_bytes)
    names = out.names
    rest = texts.groupBy("_g").cogroup(found.groupBy("_g")).applyInArrow(lean_pair(lambda a, b: _cut(a, b, keep_bytes, names)), out)
    long = F.col("n") >= length
    whole = copies.select(F.col("_id").alias(id_col), F.col("n").alias("n_bytes"), F.when(long, F.col("n")).otherwise(F.lit(0)).alias("n_removed"), F.when(long, F.lit(1)).otherwise(F.lit(0)).cast("long").alias("n_spans"), F.when(long, F.sha2(F.encode(F.lit(""), "UTF-8"), 256)).otherwise(F.col("digest")).alias("kept_sha256"))
    if keep_bytes:  # short copies keep their bytes
        short = base.join(copies.filter(~long).select("_o", "_x").distinct(), ["_o", "_x"]).select("_o", "_x", raw.alias("_raw")).dropDuplicates(["_o", "_x"])
        whole = copies.join(short, ["_o", "_x"], "left").select(*[c for c in ("_id", "n", "digest")], "_raw")
        whole = whole.select(F.col("_id").alias(id_col), F.col("n").alias("n_bytes"), F.when(long, F.col("n")).otherwise(F.lit(0)).alias("n_removed"), F.when(long, F.lit(1)).otherwise(F.lit(0)).cast("long").alias("n_spans"), F.when(long, F.sha2(F.encode(F.lit(""), "UTF-8"), 256)).otherwise(F.col("digest")).alias("kept_sha256"), F.coalesce("_raw", F.encode(F.lit(""), "UTF-8")).alias("kept"))
    return rest.unionByName(whole)
