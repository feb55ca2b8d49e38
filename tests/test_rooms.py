"""More different items than counters: passes that are to be exact deal them into rooms."""

from collections import Counter

from pyspark.sql import functions as F

from heavyhitters.functions import udfs
from heavyhitters.operators import blocks, local
from heavyhitters.streaming import summaries as st


def many(spark, items=130, rows=900):
    return spark.range(rows).select((F.col("id") * F.col("id") % items).alias("item"), F.col("id").alias("key"), F.when(F.col("id") % 3 == 0, "a").otherwise("b").alias("g"))


def counts(df, *columns):
    return Counter(tuple(r) for r in df.select(*columns).collect())


def test_rooms_hold_at_most_k(spark):
    df = many(spark)
    assert blocks.rooms(df, "item", 200) == 1 == blocks.rooms(df.filter("false"), "item", 2)
    for k in (3, 10, 40):
        n = blocks.rooms(df, "item", k, ["g"])
        fullest = df.groupBy("g", blocks.room(F.col("item"), n).alias("r")).agg(F.count_distinct("item").alias("c")).agg(F.max("c")).first()[0]
        assert n > 1 and fullest <= k


def test_sequential_exact_beyond_k(spark):
    df = many(spark).unionByName(many(spark).limit(2).withColumn("item", F.lit(None).cast("long")))
    got = {r.item: (r.est, r.err) for r in local.sequential_exact(df, "item", 10, ["key"]).collect()}
    assert got == {i: (c, 0) for (i,), c in counts(df, "item").items()}
    assert {r.err for r in local.sequential(df, "item", 10, ["key"]).collect()} != {0}


def test_grouped_map_beyond_k(spark):
    df = many(spark)
    got = udfs.per_group_sequential(df, "g", "item", "key", 10, blocks.rooms(df, "item", 10, ["g"])).collect()
    assert {(r.g, r.item): r.est for r in got} == counts(df, "g", "item") and {r.err for r in got} == {0}


def test_udaf_beyond_k(spark):
    df = many(spark)
    rooms = blocks.rooms(df, "item", 10, ["g"])
    got = df.groupBy("g", blocks.room(F.col("item"), rooms)).agg(udfs.summary_agg(10)("item").alias("c")).select("g", F.inline("c")).collect()
    assert {(r.g, r.item): r.est for r in got} == counts(df, "g", "item") and {r.err for r in got} == {0}


def test_state_beyond_k_over_several_batches(spark, tmp_path):
    """A batch updates the states it meets; the states of others must not be lost with it."""
    df = many(spark)
    for g in ("a", "b"):
        df.filter(F.col("g") == g).coalesce(1).write.mode("append").parquet(str(tmp_path))
    stream = spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path))
    states = st.stateful_summary(stream, "g", "item", 10, "key", rooms=blocks.rooms(df, "item", 10, ["g"]))
    got = st.run_available_now(states, "update", keys=("key", "room")).select("key", F.inline(F.arrays_zip("items", "ests", "errs"))).collect()
    assert {(r[0], r[1]): r[2] for r in got} == counts(df, "g", "item") and {r[3] for r in got} == {0}
