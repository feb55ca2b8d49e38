"""Exact top-k by inner product: exhaustive term-at-a-time accumulation.

Vectors become sparse rows of (component, integer weight). Candidates are held
as postings per component in blocks; each component's query weights are
scattered with the postings into a dense score array, the block's best are
selected by partition, and the blocks' lists are merged.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Scores are 64-bit integers; what lies beyond is given as the nearest of them.
LEAST, MOST = -(1 << 63), (1 << 63) - 1


def usable(vectors: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    """(_id, _v): rows with an id and a vector of finite components, which keep their own type."""
    cell = F.col("_v")
    kind = vectors.schema[vector_col].dataType
    kind = kind if isinstance(kind, T.ArrayType) and isinstance(kind.elementType, (T.FloatType, T.DoubleType)) else T.ArrayType(T.DoubleType())
    finite = cell.isNotNull() & F.forall(cell, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != F.lit(float("inf"))))
    return vectors.select(F.col(id_col).alias("_id"), F.col(vector_col).cast(kind).alias("_v")).filter(F.col("_id").isNotNull() & finite)


def _matrix(column: pa.Array, scale: int) -> np.ndarray:
    """Whole weights floor(scale * x) as doubles; rows of different lengths are padded with 0."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    size = np.asarray(column.value_lengths().fill_null(0), np.int64)
    out = np.zeros((len(column), int(size.max(initial=0))))
    flat = np.asarray(column.flatten()).astype(np.float64)
    row = np.repeat(np.arange(len(size)), size)
    out[row, np.arange(len(flat)) - np.repeat(np.cumsum(size) - size, size)] = np.nan_to_num(np.floor(flat * scale))
    return out


def _integers(weights: np.ndarray, kind: type) -> np.ndarray:
    """Whole doubles in a type in which all sums are exact: 64 bits, or Python's integers."""
    if kind is not object:
        return weights.astype(kind)
    return np.array([int(x) for x in weights.ravel()], object).reshape(weights.shape)


def _postings(matrix: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
    return [(at := np.flatnonzero(column), column[at]) for column in matrix.T]


def _accumulate(queries: np.ndarray, postings: list, rows: int, kind: type) -> np.ndarray:
    """Dense scores (query, row): one pass per component over its postings."""
    scores = np.zeros((len(queries), rows), kind)  # Python's own 0 where kind is object
    for term, (at, weight) in enumerate(postings[: queries.shape[1]]):
        hit = np.flatnonzero(queries[:, term])
        if not len(hit) or not len(at):
            continue
        w = queries[hit, term].astype(kind)[:, None]
        if 2 * len(at) >= rows:  # a long posting list is scattered once, then added row by row
            dense = np.zeros(rows, kind)
            dense[at] = weight
            if len(hit) == len(queries):
                scores += w * dense
            else:
                scores[hit] += w * dense
        else:
            scores[hit[:, None], at] += w * weight.astype(kind)
    return scores


def _best(scores: np.ndarray, own: np.ndarray, k: int) -> list[np.ndarray]:
    """Per query the columns of its k best scores; columns stand in id order, ties go left."""
    out = []
    for row, same in zip(scores, own):
        free = np.flatnonzero(~same)
        value = row[free]
        if len(free) > k:
            least = np.partition(value, len(free) - k)[len(free) - k]
            free = np.concatenate([free[value > least], free[value == least][: k - int((value > least).sum())]])
        out.append(free)
    return out


def exact_top_k(vectors: DataFrame, k: int = 20, scale: int = 64, every: int = 20, id_col: str = "vec_id", vector_col: str = "embedding", query_block: int = 4096, row_block: int = 8192) -> DataFrame:
    """(query_id, rank, vec_id, score): each query's k highest scores, ties to smaller ids.

    Queries are the rows whose id is divisible by `every`; candidates are all rows
    with another id. A row takes part only if its id is not null and its vector is
    neither null nor holding a null, NaN or infinite component; an empty vector
    scores 0 with all. Shorter vectors count as padded with zeros. Weights of any
    size are whole and their products exact: sums beyond 2**62 are taken in Python's
    integers. A score outside 64 bits is given as the nearest 64-bit number and ties
    with others that are. Repeated rows are candidates each; a repeated query is
    answered once. Each group joins one block of queries with one block of
    candidates, so memory is bounded by the two block sizes at any scale.
    """
    rows = usable(vectors, id_col, vector_col)
    asked = rows.filter(F.col("_id") % every == 0).dropDuplicates(["_id"])
    n, q = rows.count(), asked.count()
    row_blocks = max(math.ceil(n / row_block), min(24, math.ceil(n / 512)), 1)
    query_blocks = max(math.ceil(q / query_block), 1)
    place = F.monotonically_increasing_id()
    left = asked.withColumn("_qb", F.pmod(F.xxhash64("_id"), F.lit(query_blocks)).cast("int")).withColumn("_rb", F.explode(F.sequence(F.lit(0), F.lit(row_blocks - 1))))
    right = rows.withColumn("_rb", F.pmod(place, F.lit(row_blocks)).cast("int")).withColumn("_qb", F.explode(F.sequence(F.lit(0), F.lit(query_blocks - 1))))
    kind = vectors.schema[id_col].dataType
    out = T.StructType([T.StructField("query_id", kind), T.StructField("vec_id", kind), T.StructField("score", T.LongType())])

    def block(queries: pa.Table, candidates: pa.Table) -> pa.Table:
        cols: list[list] = [[], [], []]
        if queries.num_rows and candidates.num_rows:
            candidates = candidates.sort_by("_id")
            ids, qids = np.asarray(candidates["_id"]), np.asarray(queries["_id"])
            c, a = _matrix(candidates["_v"], scale), _matrix(queries["_v"], scale)
            width = max(c.shape[1], a.shape[1])
            bound = float(np.abs(c).max(initial=0)) * float(np.abs(a).max(initial=0)) * width
            kind = np.float32 if bound < 1 << 24 else np.float64 if bound < 1 << 53 else np.int64 if bound < 1 << 62 else object
            c, a = _integers(c, kind), _integers(a, kind)
            post = _postings(c)
            for at in range(0, len(qids), 128):
                part = slice(at, at + 128)
                scores = _accumulate(a[part], post, len(ids), kind)
                for i, best in enumerate(_best(scores, qids[part][:, None] == ids[None, :], k)):
                    value = scores[i, best]
                    if kind is object:
                        value = np.array([min(max(v, LEAST), MOST) for v in value], np.int64)
                    cols[0].append(np.full(len(best), qids[at + i]))
                    cols[1].append(ids[best])
                    cols[2].append(value.astype(np.int64))
        types = [out_type(queries, candidates), out_type(queries, candidates), pa.int64()]
        return pa.table({f.name: pa.array(np.concatenate(v) if v else [], t) for f, v, t in zip(out, cols, types)})

    def out_type(queries: pa.Table, candidates: pa.Table) -> pa.DataType:
        return queries.schema.field("_id").type

    partial = left.groupBy("_qb", "_rb").cogroup(right.groupBy("_qb", "_rb")).applyInArrow(block, out)
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), F.asc("vec_id"))
    return partial.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
