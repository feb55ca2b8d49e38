"""A corpus pipeline over `documents`, every stage written as Parquet and read again.

1. language identification: what the model rejects goes (no letters, or too far from all centroids);
2. line deduplication: lines of ten documents or more lose all copies, in every document;
3. n-gram Jaccard join: of documents linked by similarity the one with the smallest id stays;
4. benchmark decontamination: documents holding an item of `benchmark`, within its edit budget, go;
5. mixing: the rest is sampled to the sources' target weights; documents that are taken stay, with their copies.

All stages but the last return the columns of documents; line deduplication
recounts `n_chars` of texts it changes. Documents with null or empty texts go in
the first stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from heavyhitters.llm.common import materialise
from heavyhitters.llm.decontamination import keep_clean
from heavyhitters.llm.jaccard_join import keep_one
from heavyhitters.llm.language_id import fit, keep_accepted
from heavyhitters.llm.line_dedup import dedup_lines
from heavyhitters.llm.mixing import mix_sources


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return keep_accepted(docs, fit(docs))


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return dedup_lines(docs, min_docs=10, min_key_chars=1, output="documents")


def jaccard_join(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return keep_one(docs, width=5, percent=80)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return keep_clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mix_sources(docs).filter("copies > 0")


STAGES = [("language_id", language_id), ("line_dedup", line_dedup), ("jaccard_join", jaccard_join), ("decontamination", decontamination), ("mixing", mixing)]

#: SQL cannot express the fitted language model or edit distances within texts.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = materialise(stage(spark, docs, sf_dir), f"stage-{name}", "snappy")
    return docs
