"""Mixing sources to target weights by Pareto order sampling.

A document's expected copies grow with its weight, the binary length of its word
count by default: a text of a thousand words is worth ten times one of a single
word. Within a source, expected copies are the weight times one level, capped, and
the level makes expected words meet the source's target. The whole part of the
expected copies is certain; the fraction left is the document's inclusion
probability in a Pareto order sample: random odds divided by inclusion odds rank
the documents, and the smallest ranks are taken until the words reach the target.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import materialise

#: Rows of a table of sources, or of their weight classes, that may be broadcast.
BROADCAST_SOURCES = 100_000
#: Equal slices of the rank scale; only the slice that holds the cut is sorted.
SLICES = 1024


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def ranked(df: DataFrame, *order: Column) -> DataFrame:
    """Adds `place`, the 0-based rank in the order, without a sort in one task.

    Ranges are sorted apart and written once; a range's first rank is the number of
    rows in the ranges before it.
    """
    sorted_ = df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_at", F.monotonically_increasing_id())
    sorted_ = materialise(sorted_, "ranked").withColumn("_range", F.shiftright("_at", 33))
    before = Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)  # one row per range
    first = sorted_.groupBy("_range").count().withColumn("_first", F.coalesce(F.sum("count").over(before), F.lit(0))).drop("count")
    return sorted_.join(F.broadcast(first), "_range").withColumn("place", F.col("_first") + F.col("_at").bitwiseAND(F.lit((1 << 33) - 1))).drop("_range", "_at", "_first")


def targets(sizes: DataFrame, weights: Sequence[int] = (1, 2, 3), max_copies: int = 3) -> DataFrame:
    """(_key, source_size, target): shares by weight, capped, the excess reshared by weight.

    One level L settles it: source i gets min(w_i * L, cap_i). In the order of
    cap_i / w_i the capped sources come first, so L follows from running sums over
    the distinct values of cap_i / w_i, which are far fewer than sources: sources of
    different sizes are at most the square root of twice the words. Sources stand by
    code point, null last.
    """
    s = sizes.groupBy("_key").agg(F.sum("_size").alias("s"), F.min("_source").alias("src"))
    s = ranked(s, F.asc_nulls_last("src"))
    s = s.withColumn("w", F.element_at(F.array(*[F.lit(int(w)) for w in weights]), (F.col("place") % len(weights) + 1).cast("int")).cast("long"))
    s = s.withColumn("cap", F.col("s") * max_copies).withColumn("t", F.col("cap") / F.col("w"))
    steps = s.groupBy("t").agg(F.sum("cap").alias("caps"), F.sum("w").alias("ws"), F.min(F.struct("w", "cap")).alias("one"))
    total = s.agg(F.sum("s").alias("total"))
    up = Window.orderBy("t")
    steps = steps.withColumn("capped", F.coalesce(F.sum("caps").over(up.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    steps = steps.withColumn("left_w", F.sum("ws").over(up.rowsBetween(Window.currentRow, Window.unboundedFollowing)))
    steps = steps.crossJoin(F.broadcast(total)).withColumn("rest", F.col("total") - F.col("capped"))
    whole = lambda c: F.col(c).cast("decimal(19,0)")  # noqa: E731  products beyond 64 bits
    # the first step that its share does not lift over the cap, and all after it, are not capped
    free = whole("rest") * whole("one.w") <= whole("one.cap") * whole("left_w")
    cut = steps.filter(free).agg(F.min(F.struct("t", "rest", "left_w")).alias("c")).select(F.col("c.t").alias("t0"), F.col("c.rest").alias("rest0"), F.col("c.left_w").alias("left0"))
    target = F.when(F.col("t") >= F.col("t0"), (F.col("w") * F.col("rest0")).cast("double") / F.col("left0").cast("double")).otherwise(F.col("cap").cast("double"))
    return s.crossJoin(F.broadcast(cut)).select("_key", F.col("s").alias("source_size"), target.alias("target"))


def expected_copies(classes: DataFrame, max_copies: int) -> DataFrame:
    """(_key, _g, copies): expected copies of each weight class of a source.

    `classes` is (_key, _g, s, target): words by weight. min(max_copies, _g * level)
    makes the source's words meet its target. The heaviest classes reach the cap
    first, so the level follows from running sums over a source's classes.
    """
    down = Window.partitionBy("_key").orderBy(F.desc("_g"))
    capped = F.coalesce(F.sum("s").over(down.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)) * max_copies
    rest = F.sum(F.col("_g") * F.col("s")).over(down.rowsBetween(Window.currentRow, Window.unboundedFollowing))
    rows = classes.withColumn("level", (F.col("target") - capped) / rest)
    # the first class that the level of those not above it does not lift over the cap
    free = F.col("level") * F.col("_g") <= F.lit(float(max_copies))
    cut = rows.filter(free).groupBy("_key").agg(F.max(F.struct("_g", "level")).alias("c")).select("_key", F.col("c.level").alias("_level"))
    level = F.coalesce("_level", F.lit(float("inf")))  # all are capped
    copies = F.least(F.greatest(F.col("_g") * level, F.lit(0.0)), F.lit(float(max_copies)))
    return classes.join(cut, "_key", "left").select("_key", "_g", copies.alias("copies"))


def weight_of(size: Column, odds: Column | None = None) -> Column:
    """A document's weight: the binary length of its size, or `odds` read to a quarter of a doubling.

    Weights are few (64, or four for each doubling), so a source's classes are too.
    """
    if odds is None:
        return F.when(size > 0, F.length(F.bin(size))).otherwise(F.lit(0)).cast("double")
    return F.when((odds > 0) & (odds < float("inf")), F.pow(F.lit(2.0), F.floor(F.log2(odds) * 4) / 4)).otherwise(F.lit(0.0))


def mix_sources(docs: DataFrame, weights: Sequence[int] = (1, 2, 3), max_copies: int = 3, seed: int = 7, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", odds_col: str | None = None) -> DataFrame:
    """(id, size, source_size, target, copies, taken), one row per input row.

    `size` is the number of words of the text, 0 for a null; null sources form a
    source of their own, the last. `copies` whole copies are taken, at most
    `max_copies`, `taken` = size * copies. A source's taken words come within half
    a document of its target. The random numbers are digests of seed and id, so
    reruns agree; rows of one id draw the same number, null ids count as ''.
    `odds_col`, if given, is the weight that expected copies are proportional to
    instead of the size's; nulls, NaN, infinities and values of 0 and below are never
    taken, and a target beyond `max_copies` of the rest is not met. Only the slice of
    the rank scale in which a source's cut falls is sorted, so a hot source is no hot
    task.
    """
    key = F.coalesce(F.concat(F.lit("="), F.col(source_col).cast("string")), F.lit(""))
    digest = F.md5(F.encode(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col(id_col).cast("string"), F.lit(""))), "UTF-8"))
    u = (F.conv(F.substring(digest, 1, 13), 16, 10).cast("bigint").cast("double") + 0.5) / float(1 << 52)
    odds = F.nanvl(F.col(odds_col).cast("double"), F.lit(0.0)) if odds_col else F.lit(0.0)
    narrow = docs.select(F.col(id_col).alias("_id"), F.col(source_col).cast("string").alias("_source"), key.alias("_key"), word_count(F.col(text_col).cast("string")).alias("_size"), u.alias("_u"), odds.alias("_odds"))
    narrow = materialise(narrow.withColumn("_g", weight_of(F.col("_size"), F.col("_odds") if odds_col else None)).drop("_odds"), "mix")
    sources = targets(narrow, weights, max_copies)
    classes = narrow.filter("_g > 0 AND _size > 0").groupBy("_key", "_g").agg(F.sum("_size").alias("s"))
    classes = expected_copies(classes.join(sources, "_key").select("_key", "_g", "s", "target"), max_copies).join(classes, ["_key", "_g"])
    whole = F.floor("copies").cast("long")
    classes = classes.select("_key", "_g", whole.alias("whole"), (F.col("copies") - whole).alias("_pi"), (whole * F.col("s")).alias("_sure"))
    sure = classes.groupBy("_key").agg(F.sum("_sure").alias("_sure"))
    lack = F.greatest(F.col("target") - F.coalesce("_sure", F.lit(0)), F.lit(0.0))
    sources = materialise(sources.join(sure, "_key", "left").select("_key", "source_size", "target", lack.alias("lack")), "mix-sources")
    classes = materialise(classes.drop("_sure"), "mix-classes")
    small = classes.count() <= BROADCAST_SOURCES and sources.count() <= BROADCAST_SOURCES
    beside = lambda table: F.broadcast(table) if small else table
    rows = narrow.join(beside(sources), "_key").join(beside(classes), ["_key", "_g"], "left")
    rows = rows.withColumn("whole", F.coalesce("whole", F.lit(0))).withColumn("_pi", F.coalesce("_pi", F.lit(0.0)))
    rank = (F.col("_u") / (1 - F.col("_u"))) / (F.col("_pi") / (1 - F.col("_pi")))
    rows = rows.withColumn("_q", F.when((F.col("_pi") > 0) & (F.col("_size") > 0), rank))
    # q / (1 + q) maps the ranks to (0, 1) in order; without a chance a document is last
    rows = rows.withColumn("_slice", F.when(F.col("_q").isNull(), F.lit(SLICES)).otherwise(F.least(F.floor(F.col("_q") / (1 + F.col("_q")) * SLICES), F.lit(SLICES - 1))).cast("int"))
    up_to = Window.partitionBy("_key").orderBy("_slice").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    sums = rows.filter(F.col("_slice") < SLICES).groupBy("_key", "_slice").agg(F.sum("_size").alias("part"), F.first("lack").alias("lack"))
    sums = sums.withColumn("upto", F.sum("part").over(up_to)).filter(F.col("upto") > F.col("lack"))
    cut = sums.groupBy("_key").agg(F.min(F.struct("_slice", (F.col("upto") - F.col("part")).alias("base"))).alias("c")).select("_key", F.col("c._slice").alias("_cut"), F.col("c.base").alias("_base"))
    rows = rows.join(beside(cut), "_key", "left").withColumn("_cut", F.coalesce("_cut", F.lit(SLICES)))
    copies = lambda extra: (F.col("whole") + F.when(extra, F.lit(1)).otherwise(F.lit(0)))
    clear = rows.filter(F.col("_slice") != F.col("_cut")).withColumn("copies", copies(F.col("_slice") < F.col("_cut")))
    order = Window.partitionBy("_key").orderBy("_q", F.asc_nulls_first("_id"), "_size").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    edge = rows.filter(F.col("_slice") == F.col("_cut")).withColumn("_sum", F.sum("_size").over(order))
    nearer = 2 * F.col("_sum") - F.col("_size") <= 2 * (F.col("lack") - F.col("_base"))
    edge = edge.withColumn("copies", copies(F.col("_q").isNotNull() & nearer)).drop("_sum")
    return clear.unionByName(edge).select(F.col("_id").alias(id_col), F.col("_size").alias("size"), "source_size", "target", "copies", (F.col("_size") * F.col("copies")).alias("taken"))
