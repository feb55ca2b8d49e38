"""Connected components of a distributed graph."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialise

SHAPE = "a long, b long"


def _forest(a: np.ndarray, b: np.ndarray) -> tuple[list[int], list[int]]:
    """Every node of the edges with the smallest node of its component."""
    parent: dict[int, int] = {}

    def root(x: int) -> int:
        top = x
        while (up := parent.setdefault(top, top)) != top:
            top = up
        while x != top:
            parent[x], x = top, parent[x]
        return top

    for x, y in zip(a.tolist(), b.tolist()):
        x, y = root(x), root(y)
        if x < y:
            parent[y] = x
        elif y < x:
            parent[x] = y
    nodes = [x for x in parent if root(x) != x]
    return nodes, [root(x) for x in nodes]


def contract(edges: DataFrame, batch_edges: int = 1 << 20) -> DataFrame:
    """Within bounded runs of each partition, replace edges by stars to the smallest node."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []
        n = 0

        def out() -> pa.RecordBatch:
            v, m = _forest(np.concatenate([h[0] for h in held]), np.concatenate([h[1] for h in held]))
            return pa.RecordBatch.from_arrays([pa.array(v, pa.int64()), pa.array(m, pa.int64())], names=["a", "b"])

        for batch in batches:
            held.append((batch.column(0).to_numpy(), batch.column(1).to_numpy()))
            n += batch.num_rows
            if n >= batch_edges:
                yield out()
                held, n = [], 0
        if held:
            yield out()

    return edges.select("a", "b").mapInArrow(run, SHAPE)


def _stars(edges: DataFrame, large: bool) -> DataFrame:
    """One large-star or small-star step; edges are (a, b) with a > b."""
    if large:
        around = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    else:
        around = edges
    low = around.groupBy("a").agg(F.min("b").alias("m"))
    low = low.select("a", F.least("a", "m").alias("m"))
    joined = around.join(low, "a")
    if large:  # neighbours above a are moved to the smallest node around a
        step = joined.filter("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        # a itself keeps its edge to the smallest
        return step.unionByName(low.select("a", F.col("m").alias("b")))
    step = joined.select(F.col("b").alias("a"), F.col("m").alias("b"))
    return step.unionByName(low.select("a", F.col("m").alias("b")))


def components(edges: DataFrame, rounds: int = 40) -> DataFrame:
    """(node, component): each node of the edges with the smallest node that it reaches.

    Edges (a, b) are bigint pairs, in any direction and repeated at will. Each
    round aggregates and joins by node; links never leave the cluster.
    """
    clean = lambda e: e.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    edges = materialise(clean(contract(edges.filter("a IS NOT NULL AND b IS NOT NULL"))), "edges")
    state = None
    for _ in range(rounds):
        # done when every node has one edge, to a node that has none of its own
        row = edges.agg(F.count("*").alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("h")).first()
        if (row.n, row.h) == state or not row.n:
            break
        state = (row.n, row.h)
        edges = materialise(clean(_stars(clean(_stars(edges, True)), False)), "edges")
    else:
        raise RuntimeError("components did not settle")
    return edges.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(edges.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())
