"""Benchmark decontamination by pigeonhole edit matching.

An item with an error budget of e is cut into e + 1 pieces, one of which any
match within e edits contains unchanged. The pieces of all items are searched
together; where one hits, the item's bit-parallel edit distance against the
text around the hit decides.
"""

from __future__ import annotations

import math
from collections import defaultdict
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import bounded_batches, field, lean, pieces

#: Benchmark text handled by one scan of the documents; more is scanned in blocks.
BLOCK_BYTES = 16 << 20
#: Edits an item may differ by, as a share of its length.
ERROR_RATE = 1 / 16
#: From this code point on, most scripts are written without spaces.
SPACELESS = 0x0E00


def normalise(text: str | None) -> str:
    """Lower case, each run of white space one space, none at the ends."""
    return " ".join((text or "").lower().split())


def splits_word(text: str, start: int, stop: int) -> bool:
    """Whether text[start:stop] begins or ends within a word.

    Only scripts that put spaces between words have such borders.
    """
    letter = lambda c: c.isalnum() and ord(c) < SPACELESS
    return (start > 0 and letter(text[start - 1]) and letter(text[start])) or (stop < len(text) and letter(text[stop]) and letter(text[stop - 1]))


def place(text: str, item: str) -> int:
    """Where the item stands unchanged, as whole words; -1 if nowhere."""
    at = text.find(item)
    while at >= 0 and splits_word(text, at, at + len(item)):
        at = text.find(item, at + 1)
    return at


def cut(text: str, errors: int) -> list[tuple[int, str]]:
    """errors + 1 pieces of almost equal size, with their offsets."""
    n = errors + 1
    at = [len(text) * i // n for i in range(n + 1)]
    return [(a, text[a:b]) for a, b in zip(at, at[1:])]


class Pattern:
    """Bit-parallel edit distance of one pattern (one machine word of any length)."""

    def __init__(self, text: str):
        self.size = len(text)
        self.bits: dict[str, int] = {}
        for i, c in enumerate(text):
            self.bits[c] = self.bits.get(c, 0) | 1 << i

    def best(self, text: str, anchored: bool = False) -> tuple[int, int]:
        """(distance, end) of the nearest substring of text, the first of them.

        `anchored`: of the nearest prefix.
        """
        full, top, get = (1 << self.size) - 1, self.size - 1, self.bits.get
        up, down, score = full, 0, self.size
        least, end = score, 0
        for at, c in enumerate(text, 1):
            match = get(c, 0)
            vertical = match | down
            diagonal = (((match & up) + up) ^ up) | match
            plus = down | (full & ~(diagonal | up))
            minus = up & diagonal
            if plus >> top & 1:
                score += 1
            elif minus >> top & 1:
                score -= 1
            plus = (plus << 1 | anchored) & full
            minus = minus << 1 & full
            up = minus | (full & ~(vertical | plus))
            down = plus & vertical
            if score < least:
                least, end = score, at
                if not least:
                    break
        return least, end


class Matcher:
    """All items of a block, ready to search texts."""

    def __init__(self, items: list[tuple[object, str]], error_rate: float):
        import ahocorasick

        self.items = [(i, t, int(len(t) * error_rate)) for i, t in items]
        self.patterns: dict[int, tuple[Pattern, Pattern]] = {}
        found: dict[str, list[tuple[int, int]]] = defaultdict(list)
        for k, (_, text, errors) in enumerate(self.items):
            for at, piece in cut(text, errors):
                found[piece].append((k, at))
        self.automaton = ahocorasick.Automaton()
        for piece, where in found.items():
            self.automaton.add_word(piece, (len(piece), where))
        if found:
            self.automaton.make_automaton()
        self.some = bool(found)

    def _pattern(self, k: int) -> tuple[Pattern, Pattern]:
        if k not in self.patterns:
            text = self.items[k][1]
            self.patterns[k] = Pattern(text), Pattern(text[::-1])
        return self.patterns[k]

    def search(self, raw: str | None) -> list[tuple[object, int, int, int]]:
        """(item, distance, start, end) of each item within its budget, its nearest place."""
        if not self.some:
            return []
        text = normalise(raw)
        windows: dict[int, set[int]] = defaultdict(set)
        for last, (size, where) in self.automaton.iter(text):
            for k, at in where:
                windows[k].add(last + 1 - size - at)
        out = []
        for k, starts in windows.items():
            item, pattern, errors = self.items[k]
            exact = text.find(pattern) if errors else place(text, pattern)
            if exact >= 0:
                out.append((item, 0, exact, exact + len(pattern)))
            if exact >= 0 or not errors:
                continue
            best: tuple[int, int] | None = None
            reach = 0
            merged: list[list[int]] = []
            for s in sorted(starts):
                a, b = max(0, s - errors), min(len(text), s + len(pattern) + errors)
                if merged and a <= merged[-1][1]:
                    merged[-1][1] = max(merged[-1][1], b)
                else:
                    merged.append([a, b])
            forward, backward = self._pattern(k)
            for a, b in merged:
                distance, end = forward.best(text[a:b])
                if distance <= errors and (best is None or distance < best[0]):
                    best, reach = (distance, a + end), a
            if best:
                distance, end = best
                _, size = backward.best(text[max(reach, end - len(pattern) - errors) : end][::-1], anchored=True)
                out.append((item, distance, end - size, end))
        return out


def _blocks(benchmark: DataFrame, item_col: str, text_col: str, min_item_chars: int, block_bytes: int) -> Iterator[list[tuple[object, str]]]:
    """The items, normalised, in blocks of about `block_bytes`, each collected by itself."""
    rows = benchmark.select(F.col(item_col).alias("i"), F.col(text_col).cast("string").alias("t")).filter("t IS NOT NULL")
    size = rows.agg(F.sum(F.octet_length("t"))).first()[0] or 0
    blocks = max(1, math.ceil(size / block_bytes))
    for b in range(blocks):
        part = rows if blocks == 1 else rows.filter(F.pmod(F.xxhash64("t"), F.lit(blocks)) == b)
        items = sorted({(r.i, normalise(r.t)) for r in part.collect()}, key=lambda x: (str(x[0]), x[1]))
        yield [x for x in items if len(x[1]) >= max(min_item_chars, 1)]


def find_items(docs: DataFrame, benchmark: DataFrame, error_rate: float = ERROR_RATE, min_item_chars: int = 1, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """(id, item, distance, start, stop): items found in documents within their budget.

    Both texts are lower-cased with white space collapsed; start and stop are code
    points of that form of the document, at the item's nearest place. The budget is
    floor(error_rate * length of the item) edits. One row per document row and item;
    documents without a hit have none, nulls and empty texts among them. An item too
    short for a single edit is searched unchanged, as whole words. Items that are
    null, empty or shorter than `min_item_chars` are not searched.
    """
    spark = docs.sparkSession
    bounded_batches(spark)
    base = docs.select(F.col(id_col).alias("_id"), F.col(text_col).cast("string").alias("_text"))
    item_type = field(benchmark, item_col).dataType
    out = T.StructType([T.StructField(id_col, field(base, "_id").dataType), T.StructField(item_col, item_type), T.StructField("distance", T.IntegerType()), T.StructField("start", T.LongType()), T.StructField("stop", T.LongType())])
    from pyspark.sql.pandas.types import to_arrow_type

    item_arrow = to_arrow_type(item_type)
    result = None
    for items in _blocks(benchmark, item_col, item_text_col, min_item_chars, block_bytes):
        shared = spark.sparkContext.broadcast(items)

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            matcher = Matcher(shared.value, error_rate)
            for whole in batches:
                for part in pieces(whole, "_text"):
                    hits = [(row, *hit) for row, text in enumerate(part.column(1).to_pylist()) for hit in matcher.search(text)]
                    if hits:
                        rows, found, distance, start, stop = zip(*hits)
                        yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(rows)), pa.array(found, item_arrow), pa.array(distance, pa.int32()), pa.array(start, pa.int64()), pa.array(stop, pa.int64())], names=out.names)

        part = base.mapInArrow(lean(run), out)
        result = part if result is None else result.unionByName(part)
    return result


def keep_clean(docs: DataFrame, benchmark: DataFrame, error_rate: float = ERROR_RATE, min_item_chars: int = 1, text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """The rows, with all their columns, in which no item is found."""
    bounded_batches(docs.sparkSession)
    at = docs.columns.index(text_col)
    for items in _blocks(benchmark, item_col, item_text_col, min_item_chars, block_bytes):
        shared = docs.sparkSession.sparkContext.broadcast(items)

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            matcher = Matcher(shared.value, error_rate)
            for whole in batches:
                clean = pa.array([not matcher.search(t) for t in whole.column(at).to_pylist()], pa.bool_())
                yield whole.filter(clean)

        docs = docs.mapInArrow(lean(run), docs.schema)
    return docs
