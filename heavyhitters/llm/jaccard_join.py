"""N-gram Jaccard join with PartEnum signatures.

Documents are sets of word shingles; equal sets are one class. Sizes fall into
bands so that sets similar enough stand in the same or in neighbouring bands.
For each pair of neighbouring bands the domain of shingles is dealt into
first-level partitions, of which at least one has few differences between two similar sets;
each is dealt into cells, of which then all but so many agree. A set's signatures
are its projections on every choice of so many cells of every partition: similar
sets share one. What shares a signature is verified exactly.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import combinations, product

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import bounded_batches, field, lean, lean_group, lean_pair, materialise, pieces, release, utf8
from .components import components
from .fingerprints import MASK, mix, shingles

#: Signatures a reducer gets, about.
BUCKET_ROWS = 400_000
#: Sets that share a signature within a task before they are passed on one by one.
HOT = 64
#: Candidate classes whose keys may be broadcast (8 bytes each).
BROADCAST_CLASSES = 1 << 18
#: Bytes of sets that are compared in one task, about, and most around one pivot.
TASK_BYTES = 8 << 20
SPLIT_BYTES = 64 << 20
#: Group members compared in one task, about, of one pivot.
TASK_ROWS = 100_000
#: Members of a large group that meet as many others in one task.
BLOCK = 1024
#: Signatures a worker holds before it passes them on.
FLUSH = 500_000


@dataclass(frozen=True)
class Scheme:
    """Second level of a partitioning: cells per partition and differences it tolerates."""

    cells: int
    differences: int

    @property
    def choices(self) -> list[tuple[int, ...]]:
        """The cells of each signature: some choice agrees if at most `differences` cells do not."""
        return list(combinations(range(self.cells), self.cells - self.differences))


#: By size of the sets, up to which each scheme is used: small sets get signatures of
#: more elements, so that a passage shared by many documents seldom fills one.
SCHEMES = ((64, Scheme(7, 3)), (320, Scheme(5, 2)), (1 << 62, Scheme(3, 1)))


@dataclass(frozen=True)
class Bands:
    """Size bands and the partitioning of each pair of neighbours, up to a largest size."""

    lower: np.ndarray  # first size of each band
    scheme: np.ndarray  # by instance j, which is for bands j - 1 and j: index into SCHEMES
    partitions: np.ndarray
    slack: np.ndarray
    distance: np.ndarray

    @classmethod
    def upto(cls, largest: int, percent: int) -> Bands:
        lower, upper = [1], []
        while True:
            upper.append(lower[-1] * 100 // percent)
            if upper[-1] >= largest:
                break
            lower.append(upper[-1] + 1)
        upper += [(upper[-1] + 1) * 100 // percent]
        # |A xor B| <= (1 - t) / (1 + t) * (|A| + |B|)
        top = [0, *upper]
        distance = [(100 - percent) * (a + b) // (100 + percent) for a, b in zip(top, top[1:])]
        kinds, partitions, slack = [], [], []
        for j, k in enumerate(distance):
            kind = next(i for i, (limit, _) in enumerate(SCHEMES) if upper[j] <= limit)
            s = SCHEMES[kind][1]
            n1 = k // (s.differences + 1) + 1
            least = lower[max(j - 1, 0)] if j < len(lower) + 1 else lower[-1]
            # how many partitions of the smallest set have so many empty cells that a choice is empty
            empty = math.exp(-least / n1 / s.cells)
            many = sum(math.comb(s.cells, e) * empty**e * (1 - empty) ** (s.cells - e) for e in range(s.cells - s.differences, s.cells + 1))
            extra = math.ceil(n1 * many + 3 * math.sqrt(n1 * many)) if n1 * many > 1e-3 else 0
            kinds.append(kind)
            slack.append(extra)
            partitions.append(n1 + extra)
        return cls(np.array(lower), np.array(kinds), np.array(partitions), np.array(slack), np.array(distance))

    def of(self, size: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.lower, size, side="right") - 1


def class_keys(doc: np.ndarray, value: np.ndarray, docs: int, salt: int = 0x5851F42D4C957F2D) -> tuple[np.ndarray, np.ndarray]:
    """Set size and 64-bit key of each document's set; key 0 stands for an empty set."""
    size = np.bincount(doc, minlength=docs)
    total = np.zeros(docs, np.uint64)
    np.add.at(total, doc, mix(value ^ np.uint64(salt)))
    key = mix(total + size.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    return size, np.where(size > 0, np.where(key == 0, np.uint64(1), key), np.uint64(0))


#: Salt of the second key of a set, which shows where two sets share the first.
SECOND = 0x14057B7EF767814F


def final_keys(doc: np.ndarray, value: np.ndarray, docs: int, shared: frozenset) -> tuple[np.ndarray, np.ndarray]:
    """Size and key, which is the second key of sets whose first one is `shared` by different sets."""
    size, key = class_keys(doc, value, docs)
    if shared:
        again = np.isin(key, np.array(sorted(shared), np.uint64)) & (size > 0)
        key = np.where(again, class_keys(doc, value, docs, SECOND)[1], key)
    return size, key


def signatures(doc: np.ndarray, value: np.ndarray, size: np.ndarray, bands: Bands) -> tuple[np.ndarray, np.ndarray]:
    """(document, signature) of all sets, in both instances of each set's band.

    A projection without elements says little, yet cannot simply be left out. Of
    the partitions with few enough differences there are more than `slack`; where a
    set has at most `slack` partitions with an empty projection, one of the others
    shows the match, so only other sets emit empty projections.
    """
    owners, found = [], []
    band = bands.of(np.maximum(size, 1))
    stir = mix(value)
    term = mix(value + np.uint64(0x2545F4914F6CDD1D))
    for side, (kind, (_, scheme)) in product((0, 1), enumerate(SCHEMES)):
        instance = band + side
        active = (size > 0) & (bands.distance[instance] > 0) & (bands.scheme[instance] == kind)
        n1 = np.where(active, bands.partitions[instance], 0)
        base = np.zeros(len(size) + 1, np.int64)
        np.cumsum(n1, out=base[1:])
        if not base[-1]:
            continue
        use = active[doc]
        d, bits, t = doc[use], stir[use], term[use]
        first = ((bits >> np.uint64(32)) * n1[d].astype(np.uint64) >> np.uint64(32)).astype(np.int64)
        second = ((bits & np.uint64(0xFFFFFFFF)) * np.uint64(scheme.cells) >> np.uint64(32)).astype(np.int64)
        cell = (base[d] + first) * scheme.cells + second
        sums = np.zeros(int(base[-1]) * scheme.cells, np.uint64)
        np.add.at(sums, cell, t)
        filled = np.bincount(cell, minlength=len(sums)).reshape(-1, scheme.cells) > 0
        # a cell's sum, made different for each cell, so that a choice is the sum of its cells
        sums = mix(sums.reshape(-1, scheme.cells) + np.arange(1, scheme.cells + 1, dtype=np.uint64))
        owner = np.repeat(np.arange(len(size)), n1)
        place = (np.arange(int(base[-1])) - base[owner]).astype(np.uint64) * np.uint64(64) + (instance[owner].astype(np.uint64) << np.uint64(40))
        weak = np.bincount(owner[(~filled).sum(axis=1) >= scheme.cells - scheme.differences], minlength=len(size))
        unsafe = (weak > bands.slack[instance])[owner]
        for c, choice in enumerate(scheme.choices):
            emit = np.flatnonzero(filled[:, choice].any(axis=1) | unsafe)
            owners.append(owner[emit])
            found.append(mix(sums[np.ix_(emit, choice)].sum(axis=1) + mix(place[emit] + np.uint64(c))))
    if not found:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    return np.concatenate(owners), np.concatenate(found)


def _sets(part: pa.RecordBatch, width: int, shared: frozenset) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    data, off = utf8(part.column(part.num_columns - 1))
    doc, value = shingles(data, off, width)
    size, key = final_keys(doc, value, part.num_rows, shared)
    return doc, value, size, key


def _once(doc: np.ndarray, value: np.ndarray, size: np.ndarray, key: np.ndarray, wanted: np.ndarray) -> tuple:
    """The sets of `wanted` documents alone, renumbered."""
    at = np.full(len(size), -1)
    at[wanted] = np.arange(len(wanted))
    keep = at[doc] >= 0
    return at[doc[keep]], value[keep], size[wanted], key[wanted]


def _long(x: np.ndarray) -> pa.Array:
    return pa.array(x.view(np.int64), pa.int64())


def classes(docs: DataFrame, width: int) -> tuple[DataFrame, frozenset]:
    """(_id, n, fp): set size and key of the class of equal sets, per row; fp 0 if empty. And the shared keys.

    Every set has two independent keys of 64 bits. Where different sets share the
    first (some hundred pairs among 10**11 sets), those take the second instead.
    """
    out = T.StructType([T.StructField("_id", field(docs, "_id").dataType), T.StructField("n", T.LongType()), T.StructField("one", T.LongType()), T.StructField("two", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for part in pieces(whole, "_text"):
                data, off = utf8(part.column(1))
                doc, value = shingles(data, off, width)
                size, key = class_keys(doc, value, part.num_rows)
                other = class_keys(doc, value, part.num_rows, SECOND)[1]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(size, pa.int64()), _long(key), _long(other)], names=out.names)

    known = materialise(docs.mapInArrow(lean(run), out), "classes")
    twice = known.groupBy("one").agg(F.min("two").alias("low"), F.max("two").alias("high")).filter("low <> high").select("one")
    shared = materialise(twice, "shared-keys")  # chance alone fills it: expected pairs are (sets / 2**32)**2 / 2
    keys = frozenset(r.one & MASK for r in shared.collect())
    fp = F.when(F.col("one").isin([k - (1 << 64) if k >> 63 else k for k in sorted(keys)]), F.col("two")).otherwise(F.col("one")) if keys else F.col("one")
    return known.select("_id", "n", fp.alias("fp")), keys


def shared_signatures(docs: DataFrame, width: int, shared: frozenset, bands: Bands, buckets: int) -> DataFrame:
    """(gid, fp): groups of two or more classes that share a signature.

    Signatures travel packed, 40 bits and the class key each, in blocks by bucket.
    Where a signature has many classes within one task, they are passed on as rows
    of its group and one of them stands for all, so no reducer gets a hot group.
    """
    shape = "bucket int, low binary, high binary, fp binary, hot binary"

    def group_of(low: np.ndarray, high: np.ndarray, bucket: np.ndarray) -> np.ndarray:
        return mix(low.astype(np.uint64) | high.astype(np.uint64) << np.uint64(32) | bucket.astype(np.uint64) << np.uint64(40))

    def block(bucket: int, low: np.ndarray, high: np.ndarray, fp: np.ndarray, hot: np.ndarray) -> tuple:
        return bucket, low.tobytes(), high.tobytes(), fp.tobytes(), hot.tobytes()

    def emit(held: list[tuple[np.ndarray, np.ndarray]]) -> pa.RecordBatch:
        sig, fp = (np.concatenate(x) for x in zip(*held))
        order = np.lexsort((fp, sig))
        sig, fp = sig[order], fp[order]
        new = np.ones(len(sig), bool)
        new[1:] = (sig[1:] != sig[:-1]) | (fp[1:] != fp[:-1])
        sig, fp = sig[new], fp[new]
        bucket = ((sig >> np.uint64(40)) * np.uint64(buckets) >> np.uint64(24)).astype(np.int64)
        low, high = (sig & np.uint64(0xFFFFFFFF)).astype(np.uint32), ((sig >> np.uint64(32)) & np.uint64(0xFF)).astype(np.uint8)
        start = np.flatnonzero(np.concatenate([[True], sig[1:] != sig[:-1]]))
        run = np.diff(np.concatenate([start, [len(sig)]]))
        many = np.repeat(run > HOT, run)
        rows = []
        if many.any():
            gid, member = group_of(low[many], high[many], bucket[many]), fp[many]
            to = (mix(gid + member) % np.uint64(buckets)).astype(np.int64)
            for b in np.unique(to):
                at = to == b
                rows.append((buckets + int(b), b"", gid[at].tobytes(), member[at].tobytes(), b""))
            keep = ~many
            keep[start] = True
            low, high, fp, bucket, many = low[keep], high[keep], fp[keep], bucket[keep], many[keep]
        cuts = np.searchsorted(bucket, np.arange(buckets + 1))  # signatures are sorted, so buckets are
        rows += [block(b, low[i:j], high[i:j], fp[i:j], many[i:j].astype(np.uint8)) for b, (i, j) in enumerate(zip(cuts[:-1], cuts[1:])) if j > i]
        columns = list(zip(*rows))
        return pa.RecordBatch.from_arrays([pa.array(columns[0], pa.int32()), *(pa.array(c, pa.binary()) for c in columns[1:])], names=["bucket", "low", "high", "fp", "hot"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []
        n = 0
        for whole in batches:
            for part in pieces(whole, "_text"):
                doc, value, size, key = _sets(part, width, shared)
                _, first = np.unique(key, return_index=True)
                doc, value, size, key = _once(doc, value, size, key, first[size[first] > 0])
                owner, sig = signatures(doc, value, size, bands)
                if len(sig):
                    held.append((sig, key[owner]))
                    n += len(sig)
                if n >= FLUSH:
                    yield emit(held)
                    held, n = [], 0
        if held:
            yield emit(held)

    def meet(table: pa.Table) -> pa.Table:
        join = lambda name, kind: np.frombuffer(b"".join(x.as_py() for x in table[name]), kind)
        bucket = table["bucket"][0].as_py() if table.num_rows else 0
        if bucket >= buckets:
            return pa.table({"gid": _long(join("high", np.uint64)), "fp": _long(join("fp", np.uint64))})
        low, high, fp, hot = join("low", np.uint32), join("high", np.uint8), join("fp", np.uint64), join("hot", np.uint8)
        sig = low.astype(np.uint64) | high.astype(np.uint64) << np.uint64(32)
        order = np.lexsort((fp, sig))
        sig, fp, hot = sig[order], fp[order], hot[order]
        edge = np.concatenate([[True], sig[1:] != sig[:-1]])
        start = np.flatnonzero(edge)
        size = np.diff(np.concatenate([start, [len(sig)]]))
        warm = np.maximum.reduceat(hot, start) > 0 if len(start) else np.zeros(0, bool)
        differ = fp != np.repeat(fp[start], size)
        plain = (np.add.reduceat(differ.astype(np.int64), start) > 0 if len(start) else warm) & ~warm
        fresh = np.ones(len(sig), bool)
        fresh[1:] = edge[1:] | (fp[1:] != fp[:-1])
        # groups of the same classes count once
        members = np.zeros(len(start), np.uint64)
        group = np.repeat(np.arange(len(start)), size)
        np.add.at(members, group[fresh], mix(fp[fresh] + np.uint64(99)))
        _, one = np.unique(members, return_index=True)
        chosen = np.zeros(len(start), bool)
        chosen[one] = True
        gid = np.where(warm, group_of(sig[start] & np.uint64(0xFFFFFFFF), sig[start] >> np.uint64(32), np.full(len(start), bucket)), members)
        keep = fresh & np.repeat(warm | (plain & chosen), size)
        return pa.table({"gid": _long(gid[group[keep]]), "fp": _long(fp[keep])})

    return docs.mapInArrow(lean(run), shape).groupBy("bucket").applyInArrow(lean_group(meet), "gid long, fp long")


def class_sets(docs: DataFrame, width: int, shared: frozenset, wanted: DataFrame) -> DataFrame:
    """(task, fp, s): the sorted shingle hashes of each wanted class, for each of its tasks.

    `wanted` is (fp, _h, task); a class's set is taken from the row with the id hash
    _h. Up to BROADCAST_CLASSES of them are broadcast to the scan of the texts, more
    are joined by a shuffle.
    """
    wanted = wanted.groupBy("_h", "fp").agg(F.collect_list("task").alias("tasks"))  # tasks of a class are few
    few = wanted.count() <= BROADCAST_CLASSES
    rows = docs.select(F.xxhash64("_id").alias("_h"), "_text").join(F.broadcast(wanted) if few else wanted, "_h").select("fp", "tasks", "_text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for part in pieces(whole, "_text"):
                doc, value, _, key = _sets(part, width, shared)
                bounds = np.searchsorted(doc, np.arange(part.num_rows + 1))
                # ids may repeat with other texts
                picked = np.flatnonzero(key.view(np.int64) == part.column(0).to_numpy())
                blobs = pa.array([np.sort(value[bounds[i] : bounds[i + 1]]).tobytes() for i in picked], pa.binary())
                tasks = part.column(1).take(pa.array(picked))
                again = np.repeat(np.arange(len(picked)), np.asarray(tasks.value_lengths(), np.int64))
                to, fp = tasks.flatten(), part.column(0).take(pa.array(picked))
                for cut in range(0, len(again), 256):  # a class may go to many tasks
                    these = pa.array(again[cut : cut + 256])
                    yield pa.RecordBatch.from_arrays([to.slice(cut, 256), fp.take(these), blobs.take(these)], names=["task", "fp", "s"])

    return rows.mapInArrow(lean(run), "task long, fp long, s binary")


def verify(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """(a, b, na, nb, shared) of each pair of classes, counted on the full sets."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows: list[tuple[int, int, int]] = []
            for x, y in zip(batch.column(2), batch.column(3)):
                a, b = (np.frombuffer(v.as_buffer(), np.uint64) for v in (x, y))
                at = np.searchsorted(b, a)
                rows.append((len(a), len(b), int((b[np.minimum(at, len(b) - 1)] == a).sum())))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *(pa.array(c, pa.int64()) for c in (zip(*rows) if rows else ([], [], [])))], names=["a", "b", "na", "nb", "shared"])

    joined = pairs.join(sets.select(F.col("fp").alias("a"), F.col("s").alias("sa")), "a").join(sets.select(F.col("fp").alias("b"), F.col("s").alias("sb")), "b")
    return joined.select("a", "b", "sa", "sb").mapInArrow(lean(run), "a long, b long, na long, nb long, shared long")


def _linked(percent: int):
    return 100 * F.col("shared") >= percent * (F.col("na") + F.col("nb") - F.col("shared"))


def link_groups(sets: pa.Table, groups: pa.Table, percent: int, every: bool = False) -> pa.Table:
    """(a, b): verified links that connect what is similar within the groups of a task.

    Classes are taken by falling number of groups. Each is compared with those it
    shares a group with, but for those already connected with it (unless `every`
    link is asked for), by one pass over their elements; no pair is tested twice.
    """
    none = pa.table({"a": pa.array([], pa.int64()), "b": pa.array([], pa.int64())})
    if not sets.num_rows or not groups.num_rows:
        return none
    fp, which = np.unique(sets["fp"].to_numpy(), return_index=True)
    blobs = sets["s"].combine_chunks().take(pa.array(which))
    size = np.array([len(x) // 8 for x in (v.as_buffer() for v in blobs)], np.int64)
    element = np.unique(np.frombuffer(b"".join(v.as_py() for v in blobs), np.uint64), return_inverse=True)[1]
    off = np.concatenate([[0], np.cumsum(size)])
    member, gid = np.searchsorted(fp, groups["fp"].to_numpy()), groups["gid"].to_numpy()
    order = np.argsort(gid, kind="stable")
    member, gid = member[order], gid[order]
    start = np.flatnonzero(np.concatenate([[True], gid[1:] != gid[:-1]]))
    stop = np.concatenate([start[1:], [len(gid)]])
    group = np.repeat(np.arange(len(start)), stop - start)
    by_member = np.argsort(member, kind="stable")
    own = np.searchsorted(member[by_member], np.arange(len(fp) + 1))
    root = np.arange(len(fp))
    done = np.zeros(len(fp), bool)
    flag = np.zeros(int(element.max(initial=0)) + 1, bool)
    links: list[tuple[int, int]] = []
    for i in np.argsort(-np.diff(own), kind="stable"):
        done[i] = True
        near = group[by_member[own[i] : own[i + 1]]]
        if not len(near):
            continue
        others = np.unique(np.concatenate([member[start[g] : stop[g]] for g in near]))
        others = others[~done[others] & (every | (root[others] != root[i]))]
        others = others[100 * np.minimum(size[others], size[i]) >= percent * np.maximum(size[others], size[i])]
        mine = element[off[i] : off[i + 1]]
        flag[mine] = True
        for at in range(0, len(others), 2048):
            part = others[at : at + 2048]
            count = size[part]
            first = np.cumsum(count) - count
            shared = np.add.reduceat(flag[element[np.arange(int(count.sum())) - np.repeat(first - off[part], count)]].astype(np.int64), first)
            for j in part[100 * shared >= percent * (size[i] + count - shared)]:
                if every or root[j] != root[i]:
                    links.append((int(min(fp[i], fp[j])), int(max(fp[i], fp[j]))))
                    if not every:
                        root[root == root[j]] = root[i]
        flag[mine] = False
    if not links:
        return none
    a, b = zip(*links)
    return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})


def similar_classes(docs: DataFrame, width: int, percent: int, known: DataFrame, shared: frozenset, split_bytes: int = SPLIT_BYTES, every: bool = False) -> DataFrame:
    """(a, b): verified links between class keys that connect all that is similar; with `every`, all links.

    Each group of a shared signature goes to the task of its pivot, the class in
    most groups, so that groups that overlap mostly meet in one task, and a class's
    set is sent once to each task that has one of its groups. Groups of a pivot with
    more than `split_bytes` of sets around it are verified pair by pair instead.
    """
    stats = known.agg(F.max("n").alias("largest"), F.sum("n").alias("total")).first()
    bands = Bands.upto(max(int(stats.largest or 1), 1), percent)
    buckets = max(8, math.ceil(int(stats.total or 0) / BUCKET_ROWS))
    groups = materialise(shared_signatures(docs, width, shared, bands, buckets).distinct(), "groups")
    release(docs.sparkSession)
    weight = groups.groupBy("fp").agg(F.count("*").alias("w"))
    pivots = groups.join(weight, "fp").groupBy("gid").agg(F.max(F.struct("w", "fp")).alias("p")).select("gid", F.col("p.fp").alias("p"))
    member = materialise(groups.join(pivots, "gid"), "members")
    one = known.groupBy("fp").agg(F.min(F.xxhash64("_id")).alias("_h"), F.max("n").alias("n"))
    around = materialise(member.groupBy("p", "fp").agg(F.count("*").alias("rows")).join(one, "fp"), "around")
    pivot = around.groupBy("p").agg((F.sum("n") * 8).alias("bytes"), F.sum("rows").alias("rows"))
    # a hot pivot's groups are dealt to several tasks
    parts = F.greatest(F.ceil(F.col("bytes") / TASK_BYTES), F.ceil(F.col("rows") / TASK_ROWS), F.lit(1))
    pivot = materialise(pivot.select("p", "bytes", parts.alias("parts")), "pivots")
    total = int(pivot.agg(F.sum("bytes")).first()[0] or 0)
    task = F.pmod(F.xxhash64("p", F.pmod(F.xxhash64("gid"), F.col("parts"))), F.lit(max(24, math.ceil(total / TASK_BYTES))))
    small, large = pivot.filter(F.col("bytes") <= split_bytes), pivot.filter(F.col("bytes") > split_bytes).select("p")
    near = materialise(member.join(small, "p").select("gid", "fp", task.alias("task")), "tasks")
    sets = class_sets(docs, width, shared, near.select("fp", "task").distinct().join(one.select("fp", "_h"), "fp"))
    links = sets.groupBy("task").cogroup(near.groupBy("task")).applyInArrow(lean_pair(lambda s, g: link_groups(s, g, percent, every)), "a long, b long")
    if not large.isEmpty():
        wanted = around.join(large, "p").select("fp", "_h").distinct().withColumn("task", F.lit(0).cast("long"))
        links = links.unionByName(pairwise_links(docs, width, shared, percent, member.join(large, "p").select("gid", "fp"), wanted, every))
    links = materialise(links.distinct() if every else links, "links")  # groups in several tasks may show a link again
    release(docs.sparkSession)
    return links


def pairwise_links(docs: DataFrame, width: int, shared: frozenset, percent: int, groups: DataFrame, wanted: DataFrame, every: bool = False) -> DataFrame:
    """(a, b): verified links within groups too large for a task.

    First each group's class with most groups is verified against the others. Pairs
    of a group whose classes are then connected need no more; the rest is verified
    unless sizes, or the distances to the class both were compared with, exclude it
    (the Jaccard distance obeys the triangle inequality). With `every`, pairs that
    are connected already are verified too. A group's members are dealt into blocks
    of about BLOCK, and each pair of blocks meets by itself, so a task's pairs are
    bounded.
    """
    sets = materialise(class_sets(docs, width, shared, wanted).select("fp", "s"), "sets", "lz4")
    weight = groups.groupBy("fp").agg(F.count("*").alias("w"))
    ranked = groups.join(weight, "fp")
    pivots = ranked.groupBy("gid").agg(F.max(F.struct("w", "fp")).alias("p")).select("gid", F.col("p.fp").alias("p"))
    member = groups.join(pivots, "gid")
    star = materialise(verify(member.filter("p <> fp").select(F.col("p").alias("a"), F.col("fp").alias("b")).distinct(), sets).distinct(), "star")
    links = star.filter(_linked(percent)).select("a", "b")
    first = materialise(components(links), "components")
    apart = F.lit(1.0) - F.col("shared") / (F.col("na") + F.col("nb") - F.col("shared"))
    near = star.select(F.col("a").alias("p"), F.col("b").alias("fp"), F.col("nb").alias("size"), apart.alias("d"))
    rest = member.join(first.select(F.col("node").alias("fp"), "component"), "fp", "left").select("gid", "p", "fp", F.coalesce("component", "fp").alias("c"))
    size = rest.groupBy("gid").agg(F.min("c").alias("low"), F.max("c").alias("high"), F.count("*").alias("g")).filter("g > 2" if every else "low <> high AND g > 2")
    size = size.select("gid", F.ceil(F.col("g") / BLOCK).cast("int").alias("blocks"))
    rest = materialise(rest.join(size, "gid").join(near, ["p", "fp"]).select("gid", "blocks", "fp", "c", "size", "d", F.pmod(F.xxhash64("fp"), F.col("blocks")).cast("int").alias("own")), "open")
    limit = (100 - percent) / 100 + 1e-9
    fits = (F.abs(F.col("x.d") - F.col("y.d")) <= limit) & (100 * F.least("x.size", "y.size") >= percent * F.greatest("x.size", "y.size"))
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other")
    x = rest.select("*", other).withColumnsRenamed({"own": "i", "other": "j"}).alias("x")
    y = rest.select("*", other).withColumnsRenamed({"own": "j", "other": "i"}).alias("y")
    meet = (F.col("x.gid") == F.col("y.gid")) & (F.col("x.i") == F.col("y.i")) & (F.col("x.j") == F.col("y.j"))
    order = F.col("x.fp") < F.col("y.fp") if every else F.col("x.c") < F.col("y.c")
    pairs = x.join(y, meet & order & fits).select(F.col("x.fp").alias("a"), F.col("y.fp").alias("b")).distinct()
    links = links.unionByName(verify(pairs, sets).filter(_linked(percent)).select("a", "b"))
    return links.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))


def jaccard_components(docs: DataFrame, width: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_shingles, component_id) per row: documents linked by similar shingle sets.

    Words are runs of other characters than ASCII white space, A-Z lower-cased; a
    set is the distinct `width`-word shingles, the whole sequence as one if there
    are fewer words, empty without words or text. Rows link where 100 * shared >=
    percent * union; empty sets link with nothing. `component_id` is the smallest id
    reachable, the row's own if it has no link; null ids count only where there is
    no other. Sets are compared by 64-bit hashes of shingles, classes of equal sets
    told apart by two keys of 64 bits. What connects is verified, but not every link
    of a component; `jaccard_links` gives all.
    """
    bounded_batches(docs.sparkSession)
    base = docs.select(F.col(id_col).alias("_id"), F.col(text_col).cast("string").alias("_text"))
    known, shared = classes(base, width)
    found = components(similar_classes(base, width, percent, known, shared))
    own = known.filter("fp <> 0").groupBy("fp").agg(F.min("_id").alias("low"), F.count("*").alias("copies"))
    placed = own.join(found.select(F.col("node").alias("fp"), "component"), "fp", "left").withColumn("component", F.coalesce("component", "fp"))
    lowest = placed.groupBy("component").agg(F.min("low").alias("component_id"), F.sum("copies").alias("rows")).filter("rows > 1")
    special = materialise(placed.join(lowest, "component").select("fp", "component_id"), "members")
    few = special.count() <= BROADCAST_CLASSES
    result = known.join(F.broadcast(special) if few else special, "fp", "left")
    return result.select(F.col("_id").alias(id_col), F.col("n").alias("n_shingles"), F.coalesce("component_id", "_id").alias("component_id"))


def jaccard_links(docs: DataFrame, width: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, DataFrame]:
    """The whole join: (a, b) of every link between different sets, and (id, n_shingles, class_id, n_links) per row.

    Rows with equal sets are one class; `class_id` is its smallest id (null where all
    are null), `a` and `b` (a < b) are class ids, and no link is left out. `n_links`
    counts the rows that a row links with: the others of its class and all of the
    classes its class links with. Empty sets have no class and no links. Definitions
    are those of `jaccard_components`. Links may be as many as the square of a
    group's different sets.
    """
    bounded_batches(docs.sparkSession)
    base = docs.select(F.col(id_col).alias("_id"), F.col(text_col).cast("string").alias("_text"))
    known, shared = classes(base, width)
    own = materialise(known.filter("fp <> 0").groupBy("fp").agg(F.min("_id").alias("low"), F.count("*").alias("copies")), "class-sizes")
    found = similar_classes(base, width, percent, known, shared, every=True)
    ends = found.select(F.col("a").alias("fp"), F.col("b").alias("to")).unionByName(found.select(F.col("b").alias("fp"), F.col("a").alias("to")))
    more = ends.join(own.select(F.col("fp").alias("to"), "copies"), "to").groupBy("fp").agg(F.sum("copies").alias("more"))
    table = own.join(more, "fp", "left").select("fp", "low", (F.col("copies") - 1 + F.coalesce("more", F.lit(0))).alias("links"))
    name = own.select(F.col("fp"), F.col("low"))
    pairs = found.join(name.select(F.col("fp").alias("a"), F.col("low").alias("x")), "a").join(name.select(F.col("fp").alias("b"), F.col("low").alias("y")), "b")
    rows = known.join(table, "fp", "left").select(F.col("_id").alias(id_col), F.col("n").alias("n_shingles"), F.col("low").alias("class_id"), F.coalesce("links", F.lit(0)).alias("n_links"))
    return pairs.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")), rows


def keep_one(docs: DataFrame, width: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows, with all their columns, that have the smallest id of their component; rows with a null id stay."""
    found = jaccard_components(docs, width, percent, id_col, text_col)
    gone = materialise(found.filter(~F.col(id_col).eqNullSafe(F.col("component_id")) & F.col(id_col).isNotNull()).select(id_col).distinct(), "gone")
    few = gone.count() <= BROADCAST_CLASSES
    # by a condition: a join on the name would put that column first
    return docs.join(F.broadcast(gone) if few else gone, docs[id_col] == gone[id_col], "left_anti")
