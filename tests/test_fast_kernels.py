"""What counts and draws many items at a time gives what one at a time does."""

from collections import Counter

import numpy as np
import pytest

from heavyhitters.operators import local
from heavyhitters.operators.kernels import ArrayKernel, SequentialKernel
from heavyhitters.operators.sketches import PRIME, portable_hash_of, portable_hash_range
from heavyhitters.plans import experiments
from heavyhitters.sources import datagen, packed


def test_array_kernel_is_the_sequential_one(monkeypatch):
    for trial in range(200):
        rng = np.random.default_rng(trial)
        below, n, k = int(rng.integers(2, 200)), int(rng.integers(1, 3000)), int(rng.integers(2, 40))
        items = np.minimum(rng.zipf(rng.choice([1.1, 1.5, 2.5]), n), below) if trial % 2 else rng.integers(0, below + 1, n)
        monkeypatch.setattr(ArrayKernel, "FEW", int(rng.choice([4, 64, 1024])))
        fast, plain = ArrayKernel(k, below + 1), SequentialKernel(k)
        for part in np.array_split(items.astype(np.int64), 3):
            fast.extend(part)
        plain.extend(items.tolist())
        assert (fast.rows(), fast.n, fast.min_est) == (plain.rows(), plain.n, plain.min_est), trial


def test_levels_are_the_heap():
    rng = np.random.default_rng(1)
    items = rng.integers(0, 90, 5000).tolist()
    level, heap = SequentialKernel(12), SequentialKernel(12)
    level.extend(items)
    heap.heap = []
    heap.extend(items)
    assert level.rows() == heap.rows() and level.n == heap.n


@pytest.mark.parametrize("rho", [0.5, 1.5, 3.0])
def test_guided_draws(rho):
    hashed = portable_hash_of(np.arange(50_000), 3)
    for universe in (1, 50, 70_000):
        law = datagen.law(rho, universe, 0.5)
        assert (law.drawn(hashed) == datagen.drawn(law.bounds, hashed)).all()
        edges = np.array([0, PRIME - 1])
        assert (law.drawn(edges) == datagen.drawn(law.bounds, edges)).all()


def test_packed_items_are_the_same(spark, monkeypatch):
    monkeypatch.setattr(datagen, "CHUNK", 1000)
    rows = datagen.packed_power_law(spark, 10_007, 1.5, 500, 1, 0.5, 3)
    packed = np.concatenate([np.frombuffer(r.items, "<u4") for r in rows.collect()])
    plain = datagen.shifted_power_law(spark, 10_007, 1.5, 500, (1,), 0.5).orderBy("id").collect()
    assert packed.tolist() == [r.item for r in plain]
    s = local.per_block(rows, "items", 20, packed=True)
    assert sum(r.n for r in s.headers.collect()) == 10_007


def test_hashes_of_ranges():
    for start in (0, 1_800_000_000, PRIME - 3, 5 * PRIME + 1):
        for seed in (0, 1, 20, 1 << 30):
            assert portable_hash_range(start, start + 3000, seed).tolist() == portable_hash_of(np.arange(start, start + 3000), seed).tolist()


def test_narrow_items_are_the_same(spark, monkeypatch):
    """One byte for small items, and the same counters as without; wide ones come back as they were."""
    items = np.array([0, 255, 254, 1, (1 << 32) - 1, 255, 256, 0, 1 << 31])
    for x in (items, items[:0], items[items < 255], items[items >= 255]):
        assert packed.widened(packed.narrowed(x)).tolist() == x.tolist()
        low, times = packed.counted(packed.narrowed(x))
        assert dict(zip(low.tolist(), times.tolist())) == Counter(x.tolist()) and low.tolist() == sorted(low.tolist())
    monkeypatch.setattr(datagen, "CHUNK", 1000)
    for rho in (0.5, 1.5):
        both = [datagen.packed_power_law(spark, 10_007, rho, 5000, 1, 0.5, 3, narrow) for narrow in (False, True)]
        wide, narrow = ([bytes(r.items) for r in rows.collect()] for rows in both)
        assert [np.frombuffer(x, "<u4").tolist() for x in wide] == [packed.widened(x).tolist() for x in narrow]
        for builder in ("chunked", "sequential"):
            read = lambda rows, narrow, builder=builder: sorted(map(tuple, local.per_block(rows, "items", 20, builder, packed=True, narrow=narrow).counters.collect()))
            assert read(both[0], False) == read(both[1], True)


def test_large_experiments_keep_items_out_of_the_heap(spark, monkeypatch):
    """Items beyond the bound lie on disk, fewer in memory; the runs are the same, and nothing stays."""
    seen, info = [], spark._jsc.sc().getRDDStorageInfo
    deficit = experiments.baseline.deficit_merge
    monkeypatch.setattr(experiments.baseline, "deficit_merge", lambda *a: seen.extend((x.memSize() > 0, x.diskSize() > 0) for x in info()) or deficit(*a))
    for most, held in ((50_000, (True, False)), (49_999, (False, True))):
        monkeypatch.setattr(experiments, "MEMORY_ITEMS", most)
        rows = experiments.runtimes(spark, 50_000, 1.5, 50, (1, 2), 1, universe=500).collect()
        assert sorted((r.law, r.method, r.p, r.run) for r in rows) == sorted((law, m, p, 0) for law in ("plain", "shifted") for m in ("summary", "deficit") for p in (1, 2))
        assert seen == [held] * 4 and not list(info())
        seen.clear()


def test_experiment_counts(spark, monkeypatch):
    """Blocks, seeds and exact counts in many tasks are those of one."""
    case = experiments.Case(3, 5003, 1.0, 0.5)
    read = lambda: sorted((r.seed, r.k, r.block_id, r.n, tuple(map(tuple, r.counters))) for r in experiments._blocks(spark, case, (20, 50), (1, 2, 3), 700).collect())
    counts = lambda: Counter({(r.seed, r.item): r.cnt for r in experiments._truth(spark, 5003, 1.0, 0.5, (1, 2, 3), 700).collect()})
    one = read(), counts()
    items = {s: [r.item for r in datagen.shifted_power_law(spark, 5003, 1.0, 700, (s,), 0.5).orderBy("id").collect()] for s in (1, 2, 3)}
    assert one[1] == Counter((s, i) for s in items for i in items[s])
    kernel = SequentialKernel(20)
    kernel.extend(items[2][5003 // 3 : 2 * 5003 // 3])
    assert next(r for r in one[0] if r[:3] == (2, 20, 1))[4] == tuple(kernel.rows())
    monkeypatch.setattr(experiments, "TASK_ITEMS", 1000)
    monkeypatch.setattr(experiments, "TRUTH_ITEMS", 1500)
    assert (read(), counts()) == one
