"""The contract of counter summaries.

Items may be null (with nulls kept), NaN or a zero of either sign: null is one item,
all NaN are one item, both zeros are one item, in every builder, merge, join and
measure, as in GROUP BY.

A summary of a bag holds at most k counters (item, est, err): `est` never
under-estimates an item's count and `est - err` never over-estimates it; an item
without a counter occurs at most `min_est` times, which is the smallest `est` of a
full summary and 0 otherwise, and never more than floor(n / k).
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Columns of a header, after the keys and the block.
HEADER = ("n", "k", "nz", "min_est", "total_est")


def threshold(n: int, k: int) -> int:
    """Least count of a frequent item: floor(n / k) + 1."""
    check_k(k)
    return n // k + 1


def threshold_col(n: Column | str = "n", k: Column | str = "k", strict: bool = False) -> Column:
    """The same on columns, in integer arithmetic. `strict`: k > n fails the query where a row meets it."""
    n, k = (F.col(x) if isinstance(x, str) else x for x in (n, k))
    t = F.call_function("div", n.cast("bigint"), k.cast("bigint")) + F.lit(1)
    if not strict:
        return t
    return F.when(k > n, F.raise_error(F.lit("k must not exceed the number of items")).cast("bigint")).otherwise(t)


def check_k(k: int, n: int | None = None) -> None:
    """2 <= k, and k <= n where n is known."""
    if k < 2:
        raise ValueError("k must be at least 2")
    if n is not None and k > n:
        raise ValueError("k must not exceed the number of items")


def check_item_type(kind: T.DataType, kernel: bool = False) -> None:
    """Items must be groupable; maps are not. Kernels take no arrays and structs either."""
    if isinstance(kind, T.MapType):
        raise ValueError("a map cannot be an item; use to_json of its sorted entries")
    if kernel and isinstance(kind, (T.ArrayType, T.StructType)):
        raise ValueError("kernels take no nested items; use to_json, or the histogram builder")


def as_item(df: DataFrame, item: str) -> Column:
    """The item column with one NaN and one zero, as GROUP BY has them."""
    x = F.col(item)
    if isinstance(df.schema[item].dataType, (T.FloatType, T.DoubleType)):
        kind = df.schema[item].dataType
        return F.when(F.isnan(x), F.lit(float("nan")).cast(kind)).when(x == 0, F.lit(0.0).cast(kind)).otherwise(x)
    return x


def weighted(df: DataFrame, weight: str | None) -> DataFrame:
    """The rows that count: those with a weight that is neither null nor 0. A negative one fails the query."""
    if weight is None:
        return df
    w = F.col(weight).cast("bigint")
    return df.filter(F.when(w < 0, F.raise_error(F.lit("weights must not be negative")).cast("boolean")).otherwise(w > 0))


def match(one: DataFrame, other: DataFrame, on: Sequence[str], how: str = "inner") -> DataFrame:
    """A join on columns of the same names in which null matches null; they stand first, once.

    The other columns of both sides must have different names.
    """
    right = other.select(*[F.col(c).alias(f"_other_{c}") if c in on else F.col(c) for c in other.columns])
    same = reduce(lambda a, b: a & b, [F.col(c).eqNullSafe(F.col(f"_other_{c}")) for c in on])
    joined = one.join(right, same, how)
    if how in ("left_semi", "left_anti"):
        return joined
    keys = [(F.coalesce(c, f"_other_{c}") if how in ("full_outer", "right") else F.col(c)).alias(c) for c in on]
    return joined.select(*keys, *[c for c in (*one.columns, *other.columns) if c not in on])


def unused(name: str, columns: Sequence[str]) -> str:
    """`name` behind as many underscores as make it none of the columns, whatever their case."""
    taken = {c.lower() for c in columns}
    while name in taken:
        name = f"_{name}"
    return name


def as_column(k: int | str) -> Column:
    """k as a column: a literal, or the key column of that name."""
    return F.lit(k).cast("int") if isinstance(k, int) else F.col(k).cast("int")


@dataclass
class Summaries:
    """Summaries in long form.

    `counters`: keys, block_id, item, est, err, min_est (the block's, on every row);
    `headers`: keys, block_id and HEADER, one row per block even if it has no counter.
    `keys` separate independent bags; `k` is a number or the name of a key column,
    whose values are then at most `most`.
    """

    counters: DataFrame
    headers: DataFrame
    k: int | str
    keys: list[str] = field(default_factory=list)
    most: int | None = None

    @property
    def block(self) -> list[str]:
        return [*self.keys, "block_id"]

    def same_k(self, other: Summaries) -> None:
        if self.k != other.k or self.keys != other.keys:
            raise ValueError("only summaries with the same k and keys can be merged")
