"""Item sequences over the given tables.

Each workload is (spark, sf_dir) -> DataFrame[item, key]: `key` is a bigint by which
rows are dealt into blocks without sorting (block = key mod p). ORDER names the
columns of the serial order where one is needed.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: Separators of tokens, the same class in every engine.
BLANKS = "[ \\t\\n\\r\\f]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokens(text: Column) -> Column:
    """Lower-cased words between blanks."""
    return F.filter(F.split(F.lower(text), BLANKS), lambda w: w != "")


def baskets(rows: DataFrame, basket: list[Column], order: list[str], item: str) -> DataFrame:
    """(basket columns, pos, item): each basket's items in order, as one array, then serially again."""
    packed = rows.groupBy(*basket).agg(F.array_sort(F.collect_list(F.struct(*order, item))).alias("_b"))
    names = [c for c in packed.columns if c != "_b"]
    return packed.select(*names, F.posexplode(F.transform("_b", lambda x: x[item])).alias("pos", "item"))


def clicks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Transactions of a user and day, items event_type:k."""
    e = table(spark, sf_dir, "events").withColumn("what", F.concat_ws(":", "event_type", F.get_json_object("props", "$.k")))
    return baskets(e, [F.col("user_id"), F.to_date("ts").alias("day")], ["ts", "event_id"], "what").select("item", F.col("user_id").alias("key"))


def values(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whole part of the event value."""
    return table(spark, sf_dir, "events").select(F.floor("value").cast("bigint").alias("item"), F.col("event_id").alias("key"))


def parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Retail baskets: parts of an order; almost uniform."""
    return table(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("item"), F.col("l_orderkey").alias("key"))


def suppliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("item"), F.col("l_orderkey").alias("key"))


def gaps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Minutes since the user's previous event; a missing one is 0."""
    before = F.lag("ts").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    e = table(spark, sf_dir, "events").withColumn("before", before)
    seconds = F.unix_timestamp(F.col("ts").cast("timestamp")) - F.unix_timestamp(F.col("before").cast("timestamp"))
    return e.select(F.coalesce(F.call_function("div", seconds, F.lit(60).cast("bigint")), F.lit(0)).cast("bigint").alias("item"), F.col("event_id").alias("key"))


def labelled_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Length of a labelled document, 0 for one without label."""
    labels = table(spark, sf_dir, "labels").select("doc_id", F.lit(1).alias("labelled"))
    d = table(spark, sf_dir, "documents").select("doc_id", "n_chars").join(labels, "doc_id", "left")
    return d.select(F.when(F.col("labelled").isNotNull(), F.col("n_chars")).otherwise(F.lit(0)).alias("item"), F.col("doc_id").alias("key"))


def two_attributes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All whole event values, then all whole unit prices, without the sentinel 999."""
    one = values(spark, sf_dir)
    two = table(spark, sf_dir, "lineitem").select(F.floor(F.col("l_extendedprice") / F.col("l_quantity")).cast("bigint").alias("item"), F.col("l_orderkey").alias("key"))
    return one.unionByName(two).filter("item <> 999")


def thousandths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two real attributes scaled by 1000 to integers; almost every item is unique."""
    scaled = lambda c: F.floor(F.col(c) * 1000 + 0.5).cast("bigint").alias("item")
    one = table(spark, sf_dir, "events").select(scaled("value"), F.col("event_id").alias("key"))
    return one.unionByName(table(spark, sf_dir, "part").select(scaled("p_retailprice"), F.col("p_partkey").alias("key")))


def words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").select(F.explode(tokens(F.col("text"))).alias("item"), F.col("doc_id").alias("key"))


def word_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Adjacent words of a document."""
    d = table(spark, sf_dir, "documents").select("doc_id", tokens(F.col("text")).alias("t"))
    pairs = F.zip_with(F.slice("t", 1, F.greatest(F.size("t") - 1, F.lit(0))), F.slice("t", 2, F.greatest(F.size("t") - 1, F.lit(0))), lambda a, b: F.concat_ws(" ", a, b))
    return d.select(F.explode(pairs).alias("item"), F.col("doc_id").alias("key"))


def chat_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "conversations").select(F.explode(tokens(F.col("text"))).alias("item"), F.col("conv_id").alias("key"))


def lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").select(F.explode(F.split("text", "\n")).alias("item"), F.col("doc_id").alias("key"))


def hosts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "pages").select(F.regexp_extract("url", "^[a-z]+://([^/:?#]+)", 1).alias("item"), F.col("page_id").alias("key"))


def tags(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Names of HTML tags."""
    return table(spark, sf_dir, "pages").select(F.explode(F.regexp_extract_all("html", F.lit("<([a-z][a-z0-9]*)"), F.lit(1))).alias("item"), F.col("page_id").alias("key"))


def flows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users as flow keys, with the event type as a group."""
    return table(spark, sf_dir, "events").select(F.col("user_id").alias("item"), F.col("event_id").alias("key"), "event_type")


def customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers of orders, with the order's worth in cents as a weight."""
    return table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("item"), F.col("o_orderkey").alias("key"), F.floor(F.col("o_totalprice") * 100 + 0.5).cast("bigint").alias("cents"))


def nations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nation of each order's customer."""
    c = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    n = table(spark, sf_dir, "nation").select("n_nationkey", "n_name")
    o = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    joined = o.join(c, o.o_custkey == c.c_custkey).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey"))  # nations are 25
    return joined.select(F.col("n_name").alias("item"), F.col("o_orderkey").alias("key"))


def ship_days(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Composite key: return flag, line status, shipping day."""
    return table(spark, sf_dir, "lineitem").select(F.concat_ws("|", "l_returnflag", "l_linestatus", F.date_format("l_shipdate", "yyyy-MM-dd")).alias("item"), F.col("l_orderkey").alias("key"))


def brand_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of different brands in an order, each pair of lines once."""
    p = table(spark, sf_dir, "part").select("p_partkey", "p_brand")
    l = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").join(p, F.col("l_partkey") == F.col("p_partkey")).select("l_orderkey", "p_brand").distinct()  # noqa: E741
    pair = l.alias("a").join(l.alias("b"), (F.col("a.l_orderkey") == F.col("b.l_orderkey")) & (F.col("a.p_brand") < F.col("b.p_brand")))
    return pair.select(F.concat_ws("+", "a.p_brand", "b.p_brand").alias("item"), F.col("a.l_orderkey").alias("key"))


def classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Label of a vector with the signs of its first four dimensions."""
    sign = F.transform(F.slice("embedding", 1, 4), lambda x: F.when(x < 0, F.lit("-")).otherwise(F.lit("+")))
    return table(spark, sf_dir, "embeddings").select(F.concat(F.col("label").cast("string"), F.array_join(sign, "")).alias("item"), F.col("vec_id").alias("key"))


WORKLOADS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "clicks": clicks, "values": values, "parts": parts, "suppliers": suppliers, "gaps": gaps, "labelled_sizes": labelled_sizes, "two_attributes": two_attributes, "thousandths": thousandths,
    "words": words, "word_pairs": word_pairs, "chat_words": chat_words, "lines": lines, "hosts": hosts, "tags": tags, "flows": flows, "customers": customers, "nations": nations, "ship_days": ship_days, "brand_pairs": brand_pairs, "classes": classes,
}

#: SQL of each workload: (item, key).
_TOKENS = "list_filter(regexp_split_to_array(lower({0}), '[ \\t\\n\\r\\f]+'), lambda w: w <> '')"
SQL: dict[str, str] = {
    "clicks": "SELECT event_type || ':' || json_extract_string(props, '$.k') AS item, user_id AS key FROM events",
    "values": "SELECT floor(value)::BIGINT AS item, event_id AS key FROM events",
    "parts": "SELECT l_partkey AS item, l_orderkey AS key FROM lineitem",
    "suppliers": "SELECT l_suppkey AS item, l_orderkey AS key FROM lineitem",
    "gaps": "SELECT coalesce((epoch_us(date_trunc('second', ts)) // 1000000 - epoch_us(date_trunc('second', lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id))) // 1000000) // 60, 0)::BIGINT AS item, event_id AS key FROM events",
    "labelled_sizes": "SELECT CASE WHEN l.doc_id IS NOT NULL THEN n_chars ELSE 0 END::BIGINT AS item, d.doc_id AS key FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id",
    "two_attributes": "SELECT * FROM (SELECT floor(value)::BIGINT AS item, event_id AS key FROM events UNION ALL SELECT floor(l_extendedprice / l_quantity)::BIGINT, l_orderkey FROM lineitem) WHERE item <> 999",
    "thousandths": "SELECT floor(value * 1000 + 0.5::DOUBLE)::BIGINT AS item, event_id AS key FROM events UNION ALL SELECT floor(p_retailprice * 1000 + 0.5::DOUBLE)::BIGINT, p_partkey FROM part",
    "words": f"SELECT unnest({_TOKENS.format('text')}) AS item, doc_id AS key FROM documents",
    "word_pairs": f"SELECT unnest(CASE WHEN len(t) < 2 THEN []::VARCHAR[] ELSE list_transform(range(1, len(t)), lambda i: t[i] || ' ' || t[i + 1]) END) AS item, doc_id AS key FROM (SELECT {_TOKENS.format('text')} AS t, doc_id FROM documents)",
    "chat_words": f"SELECT unnest({_TOKENS.format('text')}) AS item, conv_id AS key FROM conversations",
    "lines": "SELECT unnest(string_split(text, chr(10))) AS item, doc_id AS key FROM documents",
    "hosts": "SELECT regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS item, page_id AS key FROM pages",
    "tags": "SELECT unnest(regexp_extract_all(html, '<([a-z][a-z0-9]*)', 1)) AS item, page_id AS key FROM pages",
    "flows": "SELECT user_id AS item, event_id AS key, event_type FROM events",
    "customers": "SELECT o_custkey AS item, o_orderkey AS key, floor(o_totalprice * 100 + 0.5::DOUBLE)::BIGINT AS cents FROM orders",
    "nations": "SELECT n_name AS item, o_orderkey AS key FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey",
    "ship_days": "SELECT l_returnflag || '|' || l_linestatus || '|' || strftime(l_shipdate, '%Y-%m-%d') AS item, l_orderkey AS key FROM lineitem",
    "brand_pairs": "WITH l AS (SELECT DISTINCT l_orderkey, p_brand FROM lineitem JOIN part ON l_partkey = p_partkey) SELECT a.p_brand || '+' || b.p_brand AS item, a.l_orderkey AS key FROM l a JOIN l b ON a.l_orderkey = b.l_orderkey AND a.p_brand < b.p_brand",
    "classes": "SELECT label::VARCHAR || array_to_string(list_transform(embedding[1:4], lambda x: CASE WHEN x < 0 THEN '-' ELSE '+' END), '') AS item, vec_id AS key FROM embeddings",
}

#: Workloads whose items are numbers.
NUMERIC = ("values", "parts", "suppliers", "gaps", "labelled_sizes", "two_attributes", "thousandths", "customers", "flows")
#: Serial order of the source rows, total up to equal items.
ORDER: dict[str, list[str]] = {"values": ["ts", "event_id"], "parts": ["l_orderkey", "l_linenumber", "l_partkey"], "suppliers": ["l_orderkey", "l_linenumber", "l_suppkey"], "customers": ["o_orderdate", "o_orderkey"]}
