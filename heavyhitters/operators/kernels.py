"""In-memory kernels that turn a sequence of items into a counter summary.

Null is an item that sorts before all others, NaN one item that sorts after them.
"""

from __future__ import annotations

import heapq
from bisect import bisect_left
from collections.abc import Iterable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc


class _Extreme:
    """Stands for null (before every item) or NaN (after every item) in Python's dicts and orders."""

    def __init__(self, value: object, first: bool):
        self.value, self.first = value, first

    def __lt__(self, other: object) -> bool:
        return self is not other and self.first

    def __gt__(self, other: object) -> bool:
        return self is not other and not self.first


NULL, NAN = _Extreme(None, True), _Extreme(float("nan"), False)


def items_of(column: pa.Array) -> list:
    """The items of a column, equal ones equal and all of them in one order."""
    items = column.to_pylist()
    if pa.types.is_floating(column.type):
        return [NULL if x is None else NAN if x != x else x for x in items]
    return [NULL if x is None else x for x in items] if column.null_count else items


def plain(item: object) -> object:
    return item.value if isinstance(item, _Extreme) else item


def ascending(rows: Iterable[tuple]) -> list[tuple]:
    """(item, est, ..) by (est, item), with null and NaN as such."""
    return [(plain(r[0]), *r[1:]) for r in sorted(rows, key=lambda r: (r[1], r[0]))]


class SequentialKernel:
    """One item at a time: count it, use a free counter, or take over the smallest.

    The counter taken over is the one with the smallest (est, item). While items weigh
    1, `level` holds those that had the smallest estimate when it was built, the
    smallest item last; what is counted or new stands above. It is built anew once for
    each value of the smallest estimate, which is at most n / k times. From the first other weight on, a
    heap holds possibly outdated (est, item) pairs, which are renewed when they surface.
    """

    def __init__(self, k: int, track_error: bool = True):
        self.k, self.track_error = k, track_error
        self.est: dict = {}
        self.err: dict = {}
        self.heap: list[tuple[int, object]] | None = None
        self.least, self.level = 0, []
        self.n = 0

    def _take(self) -> int:
        """The smallest estimate, whose smallest item gives up its counter."""
        est, least, level = self.est, self.least, self.level
        while True:
            while level:
                item = level.pop()
                if est.get(item) == least:
                    del est[item], self.err[item]
                    return least
            least = self.least = min(est.values())
            level = self.level = sorted([i for i, e in est.items() if e == least], reverse=True)

    def add(self, item: object, weight: int = 1) -> None:
        self.n += weight
        if weight != 1 and self.heap is None:
            self.heap = [(e, i) for i, e in self.est.items()]
            heapq.heapify(self.heap)
        if self.heap is None:
            if item in self.est:
                self.est[item] += 1
            else:
                base = self._take() if len(self.est) >= self.k else 0
                self.est[item], self.err[item] = base + 1, base
            return
        if item in self.est:
            self.est[item] += weight
            return
        base = 0
        if len(self.est) >= self.k:
            while True:
                seen, least = self.heap[0]
                now = self.est.get(least)
                if now == seen:
                    break
                heapq.heapreplace(self.heap, (now, least))  # every counter has one pair
            heapq.heappop(self.heap)
            base = self.est.pop(least)
            del self.err[least]
        self.est[item], self.err[item] = base + weight, base
        heapq.heappush(self.heap, (base + weight, item))

    def extend(self, items: Iterable) -> None:
        if self.heap is not None:
            for item in items:
                self.add(item)
            return
        est, err, free, seen = self.est, self.err, self.k - len(self.est), 0
        for seen, item in enumerate(items, 1):
            if item in est:
                est[item] += 1
            elif free:
                est[item], err[item] = 1, 0
                free -= 1
            else:
                base = self._take()
                est[item], err[item] = base + 1, base
        self.n += seen

    def update(self, column: pa.Array, weight: pa.Array | None = None) -> None:
        if weight is None:
            self.extend(items_of(column))
        else:
            for item, w in zip(items_of(column), weight.to_pylist()):
                self.add(item, w)

    @property
    def min_est(self) -> int:
        return min(self.est.values()) if len(self.est) >= self.k else 0

    def rows(self) -> list[tuple]:
        """(item, est, err) ascending by (est, item)."""
        err = self.err if self.track_error else dict.fromkeys(self.err, None)
        return ascending((i, e, err[i]) for i, e in self.est.items())


class ArrayKernel:
    """The counters of SequentialKernel, for items from 0 to below - 1, many at a time.

    While the smallest estimate stands, only the counters that have it are taken over,
    by ascending item, and whatever is counted or new is out of reach. So a stretch of
    items in which no more of those at risk occur than there are such counters is
    counted at once: just for the counters at risk that occur in it, the order decides
    whether they were counted first or taken over first.
    """

    #: Items of a stretch, at least and at most.
    FEW, MANY = 1 << 10, 1 << 17

    def __init__(self, k: int, below: int):
        self.k, self.used, self.n = k, 0, 0
        self.slot = np.full(below, -1, np.int32)  # of an item, -1 without a counter
        self.item, self.est, self.err = (np.zeros(k, np.int64) for _ in range(3))
        self.least, self.queue = 0, np.zeros(0, np.int64)  # slots at the smallest estimate, by item
        self.look = self.FEW

    @property
    def min_est(self) -> int:
        return int(self.est.min()) if self.used >= self.k else 0

    def rows(self) -> list[tuple]:
        """(item, est, err) ascending by (est, item)."""
        u = self.used
        return ascending(zip(self.item[:u].tolist(), self.est[:u].tolist(), self.err[:u].tolist()))

    def extend(self, items: np.ndarray) -> None:
        at = 0
        while at < len(items):
            part = items[at : at + self.look]
            done = self._fill(part) if self.used < self.k else self._pass(part)
            self.look = min(self.MANY, 2 * self.look) if done == len(part) else max(self.FEW, done + done // 4)
            self.n += done
            at += done

    @staticmethod
    def _first(items: np.ndarray, where: np.ndarray, most: int, end: int) -> tuple[np.ndarray, int]:
        """Distinct items at these positions in the order they come, at most `most`, and where the next one would stand."""
        values, first = np.unique(items[where], return_index=True)
        place = where[first]
        order = np.argsort(place)
        if len(order) > most:
            end, order = int(place[order[most]]), order[:most]
        return values[order], end

    def _fill(self, part: np.ndarray) -> int:
        """Free counters are used; returns how many items were counted."""
        fresh, end = self._first(part, np.flatnonzero(self.slot[part] < 0), self.k - self.used, len(part))
        slots = np.arange(self.used, self.used + len(fresh))
        self.item[slots], self.slot[fresh] = fresh, slots
        self.used += len(fresh)
        self.est += np.bincount(self.slot[part[:end]], minlength=self.k)
        return end

    def _pass(self, part: np.ndarray) -> int:
        """All counters are used; returns how many items were counted."""
        if not len(self.queue):
            self.least = int(self.est.min())
            lowest = np.flatnonzero(self.est == self.least)
            self.queue = lowest[np.argsort(self.item[lowest])]
        queue, size = self.queue, len(self.queue)
        slots = self.slot[part]
        values, end = self._first(part, np.flatnonzero((slots < 0) | (self.est[slots] == self.least)), size, len(part))
        enters = self.slot[values] < 0
        risky = np.flatnonzero(~enters)
        counted: list[int] = []  # ranks in the queue, ascending
        back = 0
        ranks = np.searchsorted(self.item[queue], values[risky])
        for j, (i, rank) in enumerate(zip(risky.tolist(), ranks.tolist())):
            before = bisect_left(counted, rank)
            if i - j + back > rank - before:  # more were taken over by then than stand before it
                enters[i] = True
                back += 1
            else:
                counted.insert(before, rank)
        left = np.delete(queue, counted) if counted else queue
        fresh = values[enters]
        taken, self.queue = left[: len(fresh)], left[len(fresh) :]
        self.slot[self.item[taken]] = -1
        self.item[taken], self.slot[fresh] = fresh, taken
        self.err[taken] = self.least
        self.est += np.bincount(self.slot[part[:end]], minlength=self.k)
        return end


class ChunkedKernel:
    """One Arrow batch at a time: count its items exactly, then fold the counts in.

    A monitored item gains its count; a new one starts at the present minimum,
    which is its error. The k largest stay. The result depends on where batches
    end, the summary's bounds do not.
    """

    def __init__(self, k: int):
        self.k = k
        self.items: pa.Array | None = None
        self.est = np.zeros(0, np.int64)
        self.err = np.zeros(0, np.int64)
        self.n = 0

    @property
    def min_est(self) -> int:
        return int(self.est.min()) if len(self.est) >= self.k else 0

    def update(self, column: pa.Array, weight: pa.Array | None = None) -> None:
        if not len(column):
            return
        if weight is None:
            counted = column.value_counts()
            items, counts = counted.field("values"), np.array(counted.field("counts"), np.int64)  # a copy, as counts are added to
        else:
            coded = column.dictionary_encode(null_encoding="encode")
            items = coded.dictionary
            counts = np.zeros(len(items), np.int64)
            np.add.at(counts, np.asarray(coded.indices), np.asarray(weight, np.int64))
        self.fold(items, counts)

    def fold(self, items: pa.Array, counts: np.ndarray) -> None:
        """A batch's distinct items and their counts, which are kept and added to."""
        self.n += int(counts.sum())
        floor = self.min_est
        if self.items is None:
            self.items, self.est, self.err = items, counts, np.zeros(len(items), np.int64)
        else:
            at = pc.index_in(items, value_set=self.items)
            old = np.asarray(pc.is_valid(at))
            self.est[np.asarray(at.filter(pa.array(old)), np.int64)] += counts[old]
            fresh = items.filter(pa.array(~old))
            self.items = pa.concat_arrays([self.items, fresh])
            self.est = np.concatenate([self.est, counts[~old] + floor])
            self.err = np.concatenate([self.err, np.full(len(fresh), floor, np.int64)])
        if len(self.est) > self.k:
            self._truncate()

    def _truncate(self) -> None:
        cut = np.partition(self.est, len(self.est) - self.k)[len(self.est) - self.k]
        keep = np.flatnonzero(self.est > cut)
        tied = np.flatnonzero(self.est == cut)
        if len(tied) > self.k - len(keep):  # of equal counters the smallest items stay
            order = np.asarray(pc.array_sort_indices(self.items.take(pa.array(tied)), null_placement="at_start"))
            tied = tied[order[: self.k - len(keep)]]
        keep = np.concatenate([keep, tied])
        self.items, self.est, self.err = self.items.take(pa.array(keep)), self.est[keep], self.err[keep]

    def rows(self) -> list[tuple]:
        items = items_of(self.items) if self.items is not None else []
        return ascending(zip(items, self.est.tolist(), self.err.tolist()))


class DecrementKernel:
    """k - 1 counters; an item that finds none free lowers all counters by one."""

    def __init__(self, k: int):
        self.k, self.est, self.n = k, {}, 0

    def update(self, column: pa.Array, weight: pa.Array | None = None) -> None:
        est = self.est
        for item in items_of(column):
            self.n += 1
            if item in est:
                est[item] += 1
            elif len(est) < self.k - 1:
                est[item] = 1
            else:
                for other in [i for i, e in est.items() if e == 1]:
                    del est[other]
                for other in est:
                    est[other] -= 1

    min_est = 0

    def rows(self) -> list[tuple]:
        return ascending((i, e, 0) for i, e in self.est.items())


class LossyKernel:
    """Counts with a deficit bound; each window of ceil(1/eps) items ends with a pruning."""

    def __init__(self, eps: float):
        self.width, self.n = int(np.ceil(1 / eps)), 0
        self.counts: dict = {}

    def update(self, column: pa.Array, weight: pa.Array | None = None) -> None:
        for item in items_of(column):
            window = self.n // self.width + 1
            self.n += 1
            count, deficit = self.counts.get(item, (0, window - 1))
            self.counts[item] = count + 1, deficit
            if self.n % self.width == 0:
                self.counts = {i: c for i, c in self.counts.items() if sum(c) > window}

    min_est = 0

    def rows(self) -> list[tuple]:
        """(item, count, deficit): count <= true <= count + deficit."""
        return ascending((i, c, d) for i, (c, d) in self.counts.items())
