"""Stores of summaries and items: formats, partitioned stores, tables and views."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def scratch(spark: SparkSession, tag: str) -> str:
    """A fresh path in the folder that all executors share, deleted when the application ends.

    That is the session's spark.checkpoint.dir, or a folder of this machine where none is set.
    """
    shared = spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or "file://" + os.path.join(tempfile.gettempdir(), "checkpoints")
    path = f"{shared.rstrip('/')}/stores/{tag}-{uuid.uuid4().hex}"
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(hadoop)
    return path


def kept(df: DataFrame, tag: str) -> DataFrame:
    """Written once to the shared folder and read back: cuts the lineage, and outlives the executors."""
    path = scratch(df.sparkSession, tag)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def through(df: DataFrame, form: str, **options: object) -> DataFrame:
    """Write in a format and read back with the same schema, never an inferred one."""
    path = scratch(df.sparkSession, form)
    df.write.format(form).options(**options).save(path)
    return df.sparkSession.read.format(form).schema(df.schema).options(**options).load(path)


def partitioned(df: DataFrame, by: str) -> DataFrame:
    """A store partitioned by a column; filters on it prune folders."""
    path = scratch(df.sparkSession, "partitioned")
    df.write.partitionBy(by).parquet(path)
    return df.sparkSession.read.parquet(path)


def bucketed(df: DataFrame, name: str, by: str, n: int) -> DataFrame:
    """A table bucketed by a column: joins on it do not shuffle again.

    Its files are in the shared folder, not in the warehouse, and go when the application ends.
    """
    df.write.bucketBy(n, by).sortBy(by).option("path", scratch(df.sparkSession, name)).mode("overwrite").saveAsTable(name)
    return df.sparkSession.table(name)
