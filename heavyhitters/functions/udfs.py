"""User-defined functions: aggregate, grouped, cogrouped and table forms of summaries."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..model import as_item
from ..operators.blocks import room
from ..operators.kernels import NULL, ChunkedKernel, SequentialKernel, plain
from ..operators.sketches import portable_hash_of

COUNTERS = "array<struct<item:bigint,est:bigint,err:bigint>>"


def summary_agg(k: int, nulls: str = "drop"):
    """A grouped aggregate over a bigint column: its counters, ascending by (est, item).

    Nulls are dropped, or with "keep" an item as any other; a group of nulls alone
    then has no counters. A Python aggregate sees whole groups; for large ones use the
    two-stage local phase.
    """
    if nulls not in ("drop", "keep"):
        raise ValueError("nulls must be drop or keep")

    @F.arrow_udf(COUNTERS)
    def agg(items: pa.Array) -> list:
        kernel = ChunkedKernel(k)
        items = items.cast(pa.int64())
        kernel.update(items.drop_null() if nulls == "drop" else items)
        return [{"item": i, "est": e, "err": d} for i, e, d in kernel.rows()]

    return agg


@F.pandas_udf(T.LongType())
def portable_hash_udf(x: pd.Series) -> pd.Series:
    """Seed 0 of the portable hash, vectorised; the column expression is preferred."""
    return pd.Series(portable_hash_of(x.to_numpy(), 0))


def per_group_sequential(df: DataFrame, group: str, item: str, order_by: str, k: int, rooms: int = 1) -> DataFrame:
    """(group, item, est, err): one ordered pass per group.

    Null is an item, and a group; rows that are equal in the order are read by item.
    With several `rooms` (see blocks.rooms) a group's items are dealt into so many
    passes of k counters each, one task a pass.
    """
    kind = df.schema[group].dataType.simpleString()
    item_kind = df.schema[item].dataType.simpleString()

    def run(table: pa.Table) -> pa.Table:
        kernel = SequentialKernel(k)
        for chunk in table.sort_by([("_o", "ascending"), ("item", "ascending")])["item"].chunks:
            kernel.update(chunk)
        rows = kernel.rows()
        return pa.table({"g": pa.array([table["g"][0].as_py()] * len(rows), table["g"].type), "item": pa.array([r[0] for r in rows], table["item"].type), "est": pa.array([r[1] for r in rows], pa.int64()), "err": pa.array([r[2] for r in rows], pa.int64())})

    rows = df.select(F.col(group).alias("g"), as_item(df, item).alias("item"), F.col(order_by).alias("_o")).withColumn("_room", room(F.col("item"), rooms))
    return rows.groupBy("g", "_room").applyInArrow(run, f"g {kind}, item {item_kind}, est long, err long").withColumnRenamed("g", group)


def cogroup_combine(one: DataFrame, other: DataFrame, group: str, k: int) -> DataFrame:
    """(group, item, est, err): both summaries of each group combined and cut, in one task per group.

    Inputs are (group, item, est, err, min_est) with at most k counters a group.
    """

    def run(a: pa.Table, b: pa.Table) -> pa.Table:
        sides = [{r["item"]: r for r in t.to_pylist()} for t in (a, b)]
        low = [next(iter(s.values()))["min_est"] if s else 0 for s in sides]
        rows = []
        for item in {**sides[0], **sides[1]}:
            pair = [s.get(item, {"est": m, "err": m}) for s, m in zip(sides, low)]
            rows.append((item, sum(p["est"] for p in pair), sum(p["err"] for p in pair)))
        rows = [(plain(i), -e, d) for e, i, d in sorted((-e, NULL if i is None else i, d) for i, e, d in rows)[:k]]
        g = (a if a.num_rows else b)["g"]
        return pa.table({"g": pa.array([g[0].as_py()] * len(rows), g.type), "item": pa.array([r[0] for r in rows], (a if a.num_rows else b)["item"].type), "est": pa.array([r[1] for r in rows], pa.int64()), "err": pa.array([r[2] for r in rows], pa.int64())})

    kinds = f"g {one.schema[group].dataType.simpleString()}, item {one.schema['item'].dataType.simpleString()}, est long, err long"
    columns = ("g", "item", "est", "err", "min_est")
    named = [x.select(F.col(group), *columns[1:]).select(*(F.col(o).alias(f"_{c}") for o, c in zip((group, *columns[1:]), columns))).toDF(*columns) for x in (one, other)]
    return named[0].groupBy("g").cogroup(named[1].groupBy("g")).applyInArrow(run, kinds).withColumnRenamed("g", group)


def register_table_function(spark: SparkSession, name: str = "k_majority", k: int = 10) -> None:
    """SQL: SELECT * FROM k_majority(TABLE(rows) PARTITION BY g ORDER BY o), rows being (g, o, item)."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="g string, item bigint, cnt bigint")
    class Majority:
        def __init__(self) -> None:
            self.counts: dict = {}
            self.g = None

        def eval(self, row) -> Iterator:
            self.g = row["g"]
            self.counts[row["item"]] = self.counts.get(row["item"], 0) + 1

        def terminate(self) -> Iterator:
            t = sum(self.counts.values()) // k + 1
            for item, c in self.counts.items():
                if c >= t:
                    yield str(self.g), item, c

    spark.udtf.register(name, Majority)
