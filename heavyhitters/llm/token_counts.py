"""Token counts without token ids.

Every document is cut into pre-tokens and their frequencies. Pieces are counted
once per distinct pre-token and joined to the documents' frequencies, and the
products are summed by document. No list of ids is kept.

The join has two sides, as pre-tokens are as skewed as words are. Those in most
documents, a bounded number, are found by one scan, counted and broadcast; the
others travel to the task of their hash, where each is counted once, in sorted
order, and meets the documents that hold it.

The vocabulary in question has no piece with a space mark after another
character, and its merges therefore never cross the border in front of a run of
spaces; cutting there is exact (checked when the model is loaded).
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from itertools import repeat
from operator import mul

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import bounded_batches, field, lean, materialise, pieces

#: SentencePiece's mark for a space; in a text it means the same as a space.
SPACE_MARK = "▁"
_RUNS = re.compile(" +[^ ]*")
#: Distinct pre-tokens that a task watches at once while it looks for frequent ones.
WINDOW = 1 << 18
#: Code points of a pre-token that is worth moving; longer ones are counted where they stand.
LONGEST = 64


def pre_tokens(text: str) -> list[str]:
    """The cuts of a text, each without the one space mark that the model puts in front."""
    if not text:
        return []
    text = text.replace(SPACE_MARK, " ")
    if "  " not in text and text[0] != " " and text[-1] != " ":
        return text.split(" ")
    return [run[1:] for run in _RUNS.findall(" " + text)]


class PieceCounter:
    """The library, asked for the number of pieces of pre-tokens."""

    def __init__(self, model_file: str):
        import sentencepiece

        self.model = sentencepiece.SentencePieceProcessor(model_file=model_file)
        crossing = [p for p in map(self.model.id_to_piece, range(self.model.get_piece_size())) if SPACE_MARK in p.lstrip(SPACE_MARK)]
        if crossing:
            raise ValueError(f"pieces cross the border of a pre-token: {crossing[:3]}")

    def count(self, words: list[str]) -> list[int]:
        """An empty pre-token is a lone space mark, one piece."""
        found: list[int] = []
        for at in range(0, len(words), 20_000):
            part = words[at : at + 20_000]
            found += [len(ids) if word else 1 for word, ids in zip(part, self.model.encode(part, num_threads=1))]
        return found


def document_frequencies(texts: DataFrame, text_col: str) -> DataFrame:
    """Pre-tokens in many documents, and in how many about: `pre`, `df`.

    A task counts within windows of `WINDOW` distinct pre-tokens and passes on what a
    full window holds four times or more, so that no more than 3 / `WINDOW` of all
    pairs of document and pre-token are missing from any count. Pre-tokens of more
    than `LONGEST` code points are left out.
    """

    def flush(window: Counter) -> pa.RecordBatch:
        least = 1 + 3 * len(window) // WINDOW
        words = [w for w, n in window.items() if n >= least and len(w) <= LONGEST]
        return pa.RecordBatch.from_arrays([pa.array(words, pa.string()), pa.array([window[w] for w in words], pa.int64())], names=["pre", "df"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        window: Counter = Counter()
        for whole in batches:
            for part in pieces(whole, "_text"):
                for text in part.column(0).to_pylist():
                    window.update(set(pre_tokens(text or "")))
                    if len(window) >= WINDOW:
                        yield flush(window)
                        window = Counter()
        yield flush(window)

    return texts.select(F.col(text_col).cast("string").alias("_text")).mapInArrow(lean(run), "pre string, df long").groupBy("pre").agg(F.sum("df").alias("df"))


def frequent_pieces(texts: DataFrame, model_file: str, entries: int, text_col: str = "text") -> dict[str, int]:
    """Numbers of pieces of the pre-tokens in most documents, `entries` at most.

    They are taken by eighths of octaves of their document frequency, of which there
    are some hundreds at most, so nothing is sorted and the bound holds whatever the data.
    """
    found = materialise(document_frequencies(texts, text_col), "pre-tokens")
    level = F.floor(F.log2("df") * 8)
    least, total = None, 0
    for row in sorted(found.groupBy(level.alias("level")).count().collect(), reverse=True):
        total += row["count"]
        if total > entries:
            break
        least = row.level
    if least is None:
        return {}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = PieceCounter(model_file)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(counter.count(batch.column(0).to_pylist()), pa.int64())], names=["pre", "n"])

    return dict(map(tuple, found.filter(level >= least).select("pre").mapInArrow(lean(run), "pre string, n long").collect()))


def count_tokens(docs: DataFrame, model_file: str, limit: int = 4096, id_col: str = "doc_id", text_col: str = "text", frequent: int = 1 << 18) -> DataFrame:
    """One row per input row: id, n_bytes, n_tokens, over_limit (n_tokens > limit).

    A null text counts as empty: 0 bytes, 0 tokens. Ids may be null or repeat, as rows
    are told apart by their place in the scan: input whose order changes when it is
    read again should be written first. Other columns are not read, whatever their names.
    `model_file` must exist on every executor. The scan for frequent pre-tokens runs when
    this is called; at most `frequent` of them, of at most `LONGEST` code points, are
    broadcast. The number changes what is shuffled, never a count. A pre-token not among
    them is in no more documents than each of them, but for the share that windows miss.
    """
    spark = docs.sparkSession
    bounded_batches(spark)
    known = spark.sparkContext.broadcast(frequent_pieces(docs, model_file, frequent, text_col))
    id_type = field(docs, id_col).dataType
    cut_type = T.StructType([T.StructField("_row", T.LongType()), T.StructField("_id", id_type), T.StructField("_bytes", T.LongType()), T.StructField("_pre", T.StringType()), T.StructField("_n", T.LongType())])
    sum_type = T.StructType([f for f in cut_type if f.name != "_pre"])
    names, sum_names = cut_type.names, sum_type.names

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """For each document a row with the pieces of its frequent pre-tokens, and one for each other pre-token with its frequency."""
        counter, pieces_of = PieceCounter(model_file), known.value
        for whole in batches:
            for part in pieces(whole, "_text"):
                sizes, sums, owners, words, times = [], [], [], [], []
                for row, text in zip(part.column(0).to_pylist(), part.column(2).to_pylist()):
                    frequencies = Counter(pre_tokens(text or ""))
                    others = [w for w in frequencies if w not in pieces_of]
                    long = [w for w in others if len(w) > LONGEST]
                    if long:
                        others = [w for w in others if len(w) <= LONGEST]
                    sizes.append(len((text or "").encode()))
                    sums.append(sum(map(mul, frequencies.values(), map(pieces_of.get, frequencies, repeat(0)))) + sum(map(mul, map(frequencies.__getitem__, long), counter.count(long))))
                    owners += repeat(row, len(others))
                    words += others
                    times += map(frequencies.__getitem__, others)
                n = part.num_rows
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(sizes, pa.int64()), pa.nulls(n, pa.string()), pa.array(sums, pa.int64())], names=names)
                n = len(words)
                yield pa.RecordBatch.from_arrays([pa.array(owners, pa.int64()), pa.nulls(n, part.column(1).type), pa.nulls(n, pa.int64()), pa.array(words, pa.string()), pa.array(times, pa.int64())], names=names)

    def join(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows in the order of their pre-tokens: each is counted once, when it first comes."""
        counter = PieceCounter(model_file)
        last, last_n = None, 0
        for batch in batches:
            coded = batch.column(3).dictionary_encode()
            distinct = coded.dictionary.to_pylist()
            if distinct:
                met = [last_n] if distinct[0] == last else []
                found = met + counter.count(distinct[len(met) :])
                last, last_n = distinct[-1], found[-1]
                factor = np.where(coded.is_valid().to_numpy(False), np.array(found, np.int64)[coded.indices.fill_null(0).to_numpy(False)], 1)
                total = pa.array(factor * batch.column(4).to_numpy(False), pa.int64())
            else:
                total = batch.column(4)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), total], names=sum_names)

    rows = docs.select(F.monotonically_increasing_id().alias("_row"), F.col(id_col).alias("_id"), F.col(text_col).cast("string").alias("_text"))
    place = F.when(F.col("_pre").isNull(), F.xxhash64("_row")).otherwise(F.xxhash64("_pre"))
    sums = rows.mapInArrow(lean(cut), cut_type).repartition(place).sortWithinPartitions("_pre").mapInArrow(lean(join), sum_type)
    whole = sums.groupBy("_row").agg(F.first("_id", ignorenulls=True).alias("_id"), F.max("_bytes").alias("n_bytes"), F.sum("_n").alias("n_tokens"))
    return whole.select(F.col("_id").alias(id_col), "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
