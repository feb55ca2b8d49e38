"""Content-addressed WARC archive.

Two tables hold an archive: `payloads` keeps each distinct payload once under a
strong digest (SHA-256), `headers` keeps the exact header bytes of every record
with the key of its payload. A record is rebuilt by joining the two; what is
read back is verified against the digest and length its header states.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialise, new_path

CRLF = "\r\n"


@dataclass(frozen=True)
class Archive:
    """Where an archive stands."""

    path: str

    def headers(self, spark: SparkSession) -> DataFrame:
        return spark.read.parquet(f"{self.path}/headers")

    def payloads(self, spark: SparkSession) -> DataFrame:
        return spark.read.parquet(f"{self.path}/payloads")


def _line(name: str, value: Column) -> Column:
    """A header line, or nothing where the value is null; breaks in it are escaped."""
    clean = F.regexp_replace(F.regexp_replace(value.cast("string"), "\r", "%0D"), "\n", "%0A")
    return F.coalesce(F.concat(F.lit(f"{name}: "), clean, F.lit(CRLF)), F.lit(""))


def _urn(page: Column) -> Column:
    return F.concat(F.lit("<urn:page:"), F.coalesce(page.cast("string"), F.lit("null")), F.lit(">"))


def write_archive(pages: DataFrame, path: str | None = None, min_revisit_bytes: int = 1000, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", date: str = "1970-01-01T00:00:00Z") -> Archive:
    """Write one record per row; equal payloads of at least `min_revisit_bytes` become revisits.

    The payload is the html in UTF-8, empty for a null. Of equal payloads the row
    with the largest id is the response (nulls are smallest); rows that repeat that
    id with that payload are responses too. A null url has no target line. Columns
    other than the three are ignored.
    """
    spark = pages.sparkSession
    path = path or new_path(spark, "warc")
    payload = F.encode(F.coalesce(F.col(html_col).cast("string"), F.lit("")), "UTF-8")
    base = pages.select(F.col(id_col).alias("page_id"), F.col(url_col).cast("string").alias("url"), payload.alias("payload"))
    base = base.select("*", F.sha2("payload", 256).alias("key"), F.octet_length("payload").cast("long").alias("n"))
    slot = F.concat_ws(":", "key", F.coalesce(F.col("page_id").cast("string"), F.lit("null")))
    narrow = materialise(base.select("page_id", "url", "key", "n", F.sha1("payload").alias("sha1"), slot.alias("slot")), "warc-index")
    holders = narrow.groupBy("key").agg(F.max("page_id").alias("holder"))
    slots = holders.select(F.concat_ws(":", "key", F.coalesce(F.col("holder").cast("string"), F.lit("null"))).alias("slot"))
    payloads = base.select(slot.alias("slot"), "key", "payload").join(slots.hint("shuffle_hash"), "slot", "left_semi")
    if not narrow.groupBy("slot").count().filter("count > 1").isEmpty():  # rows that repeat id and payload
        payloads = payloads.dropDuplicates(["slot"])
    payloads.select("key", "payload").write.option("compression", "zstd").parquet(f"{path}/payloads")

    rows = narrow.join(holders, "key")
    revisit = (F.col("n") >= min_revisit_bytes) & ~F.col("page_id").eqNullSafe(F.col("holder"))
    kind = F.when(revisit, F.lit("revisit")).otherwise(F.lit("response"))
    header = F.concat(
        F.lit(f"WARC/1.1{CRLF}"),
        _line("WARC-Type", kind),
        _line("WARC-Record-ID", _urn(F.col("page_id"))),
        _line("WARC-Date", F.lit(date)),
        _line("WARC-Target-URI", F.col("url")),
        _line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), F.col("sha1"))),
        _line("WARC-Profile", F.when(revisit, F.lit("http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"))),
        _line("WARC-Refers-To", F.when(revisit, _urn(F.col("holder")))),
        _line("Content-Type", F.when(~revisit, F.lit("text/html"))),
        _line("Content-Length", F.when(revisit, F.lit(0)).otherwise(F.col("n"))),
        F.lit(CRLF),
    )
    rows.select("page_id", F.encode(header, "UTF-8").alias("header"), "key", revisit.alias("is_revisit")).write.option("compression", "zstd").parquet(f"{path}/headers")
    return Archive(path)


def read_records(spark: SparkSession, archive: Archive) -> DataFrame:
    """(page_id, key, head_bytes, record binary): every record as its exact bytes, header, block and end mark.

    A stored payload that does not match the strong digest it stands under fails the query.
    """
    whole = F.when(F.sha2("payload", 256) == F.col("key"), F.col("payload")).otherwise(F.raise_error(F.concat(F.lit("payload differs from its key "), F.col("key"))).cast("binary"))
    end = F.encode(F.lit(CRLF + CRLF), "UTF-8")
    headers = archive.headers(spark).withColumn("head_bytes", F.octet_length("header"))
    full = headers.filter(~F.col("is_revisit")).join(archive.payloads(spark), "key").select("page_id", "key", "head_bytes", F.concat("header", whole, end).alias("record"))
    return full.unionByName(headers.filter("is_revisit").select("page_id", "key", "head_bytes", F.concat("header", end).alias("record")))


def _said(name: str, pattern: str) -> Column:
    return F.nullif(F.regexp_extract("head", f"\r\n{name}: {pattern}\r\n", 1), F.lit(""))


def parse_records(records: DataFrame) -> DataFrame:
    """(page_id, record_type, refers, stated, n, digest, block): what the bytes say, digests recomputed."""
    head = F.decode(F.substring(F.col("record"), F.lit(1), F.col("head_bytes")), "UTF-8")
    parsed = records.select("page_id", "record", "head_bytes", head.alias("head"))
    parsed = parsed.select("*", _said("Content-Length", "([0-9]+)").cast("int").alias("n"))
    block = F.substring(F.col("record"), F.col("head_bytes") + 1, F.col("n"))
    parsed = parsed.select("page_id", "head", block.alias("block"))
    return parsed.select("page_id", _said("WARC-Type", "([a-z]+)").alias("record_type"), _said("WARC-Refers-To", "<urn:page:([^>]*)>").alias("refers"), _said("WARC-Payload-Digest", "sha1:([0-9a-f]+)").alias("stated"), F.octet_length("block").cast("long").alias("n"), F.sha1("block").alias("digest"), "block")


def archive_index(spark: SparkSession, archive: Archive) -> DataFrame:
    """(page_id, payload_bytes, payload_digest, record_type, refers_to) of every record read back.

    A revisit takes length and digest of the response that it refers to. A payload
    that does not match the digest in its header fails the query.
    """
    kind = archive.headers(spark).schema["page_id"].dataType
    records = parse_records(read_records(spark, archive)).drop("block")
    same = F.col("digest") == F.col("stated")
    checked = F.when(same, F.col("digest")).otherwise(F.raise_error(F.concat(F.lit("payload digest differs in record "), F.coalesce(F.col("page_id").cast("string"), F.lit("null")))))
    full = records.filter("record_type = 'response'").select("page_id", F.col("n").alias("payload_bytes"), checked.alias("payload_digest"))
    targets = full.filter(F.col("payload_bytes") > 0).dropDuplicates(["page_id", "payload_digest"])
    again = records.filter("record_type = 'revisit'").select(F.col("page_id").alias("_page"), F.col("refers").cast(kind).alias("refers_to"), "stated")
    again = again.join(targets, (F.col("refers_to") == F.col("page_id")) & (F.col("stated") == F.col("payload_digest"))).select(F.col("_page").alias("page_id"), "payload_bytes", "payload_digest", F.lit("revisit").alias("record_type"), "refers_to")
    return full.select("*", F.lit("response").alias("record_type"), F.lit(None).cast(kind).alias("refers_to")).unionByName(again)
