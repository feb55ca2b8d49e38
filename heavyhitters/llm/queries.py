"""The registered queries of this subpackage, with SQL where SQL can say the same."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .line_dedup import dedup_lines

    return dedup_lines(_table(spark, sf_dir, "documents"), min_docs=10, min_key_chars=1)


def op2_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .warc import archive_index, write_archive

    return archive_index(spark, write_archive(_table(spark, sf_dir, "pages"), min_revisit_bytes=1000))


def op3_exact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .exact_topk import exact_top_k

    return exact_top_k(_table(spark, sf_dir, "embeddings"), k=20, scale=64, every=20)


def op4_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .mixing import mix_sources

    return mix_sources(_table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from .token_counts import count_tokens

    return count_tokens(_table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"), limit=4096)


def op5_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .suffix_dedup import dedup_strings

    return dedup_strings(_table(spark, sf_dir, "documents"), length=50)


def _bucket(modulus: int):
    """crc32 of the id's text, modulo."""
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % modulus


def op6_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .language_id import fit, predict

    docs = _table(spark, sf_dir, "documents")
    model = fit(docs.filter(_bucket(4) != 2))
    return predict(docs, model).select("doc_id", F.coalesce(_bucket(4) == 2, F.lit(False)).alias("held_out"), "lang_pred", "score", "rejected")


def op7_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .decontamination import find_items

    return find_items(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .quality import fit, score

    docs = _table(spark, sf_dir, "documents")
    model = fit(docs, _table(spark, sf_dir, "labels").filter(_bucket(5) != 0))
    return score(docs, model, threshold=0.3).select("doc_id", F.coalesce(_bucket(5) == 0, F.lit(False)).alias("held_out"), "score", "predicted")


def op10_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .jaccard_join import jaccard_components

    return jaccard_components(_table(spark, sf_dir, "documents"), width=5, percent=80)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (op1_line_dedup, op2_warc, op3_exact_topk, op4_mixing, op5_suffix_dedup, op6_language_id, op7_decontamination, op8_quality, op9_token_counts, op10_jaccard_join)}

SPACE = r"[\x20\x09-\x0D]"
WORD = r"[^\x20\x09-\x0D]+"
#: A-Z to a-z only, whatever the collation.
LOWER = "translate({}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

ORACLE_SQL: dict[str, str] = {
    "op1_line_dedup": rf"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, string_split(coalesce(text, ''), chr(10)) AS lines FROM documents),
l AS (SELECT r, doc_id, unnest(lines) AS line, unnest(range(len(lines))) AS pos FROM d),
k AS (SELECT *, {LOWER.format(f"regexp_replace(regexp_replace(line, '^{SPACE}+', ''), '{SPACE}+$', '')")} AS key FROM l),
hot AS (SELECT key FROM k WHERE length(key) >= 1 GROUP BY key HAVING count(DISTINCT r) >= 10)
SELECT doc_id, count(*) AS n_lines, count(hot.key) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE hot.key IS NULL), '')) AS kept_sha256
FROM k LEFT JOIN hot USING (key) GROUP BY r, doc_id
""",
    "op2_warc": """
WITH p AS (SELECT page_id, coalesce(html, '') AS html, strlen(coalesce(html, ''))::BIGINT AS n FROM pages),
m AS (SELECT *, max(page_id) OVER (PARTITION BY html) AS holder FROM p)
SELECT page_id, n AS payload_bytes, sha1(html) AS payload_digest,
       CASE WHEN n >= 1000 AND page_id <> holder THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN n >= 1000 AND page_id <> holder THEN holder END AS refers_to
FROM m
""",
    "op3_exact_topk": """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(64 * x::DOUBLE)) AS w FROM embeddings
           WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, list_inner_product(q.w, c.w)::BIGINT AS score
      FROM v q JOIN v c ON q.vec_id % 20 = 0 AND q.vec_id <> c.vec_id),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s)
SELECT query_id, rank::INTEGER AS rank, vec_id, score FROM r WHERE rank <= 20
""",
    "op4_mixing": rf"""
WITH d AS (SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '{WORD}')), 0)::BIGINT AS size,
                  (('0x' || substr(md5('7:' || coalesce(doc_id::VARCHAR, '')), 1, 13))::BIGINT::DOUBLE + 0.5) / 4503599627370496.0 AS u FROM documents),
g AS (SELECT source, sum(size)::BIGINT AS s FROM d GROUP BY source),
w AS (SELECT *, 3 * s AS cap, ((row_number() OVER (ORDER BY source ASC NULLS LAST) - 1) % 3 + 1)::BIGINT AS w, (SELECT sum(size)::BIGINT FROM d) AS total FROM g),
a AS (SELECT x.source, x.s, x.cap, x.w, x.total,
             coalesce(sum(y.cap) FILTER (WHERE y.cap * x.w < x.cap * y.w), 0)::BIGINT AS below,
             sum(y.w) FILTER (WHERE y.cap * x.w >= x.cap * y.w)::BIGINT AS weight FROM w x, w y GROUP BY ALL),
lv AS (SELECT total - below AS rest, weight AS left_w FROM a WHERE (total - below) * w <= cap * weight ORDER BY cap::DOUBLE / w LIMIT 1),
t AS (SELECT source, s, least(CASE WHEN w * rest > cap * left_w THEN cap::DOUBLE ELSE (w * rest)::DOUBLE / left_w::DOUBLE END, cap::DOUBLE) AS target FROM a, lv),
x AS (SELECT *, CASE WHEN size > 0 THEN length(bin(size)) ELSE 0 END::DOUBLE AS g FROM d),
c AS (SELECT t.source, target, g, sum(size)::BIGINT AS cs FROM x JOIN t ON x.source IS NOT DISTINCT FROM t.source WHERE size > 0 GROUP BY ALL),
v AS (SELECT *, (target - 3 * coalesce(sum(cs) OVER (PARTITION BY source ORDER BY g DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT)
             / sum(g * cs) OVER (PARTITION BY source ORDER BY g DESC ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM c),
z AS (SELECT source, arg_max(level, g) AS level FROM v WHERE level * g <= 3 GROUP BY source),
e AS (SELECT c.source, c.g, cs, least(c.g * coalesce(z.level, 'inf'::DOUBLE), 3.0) AS copies FROM c LEFT JOIN z ON c.source IS NOT DISTINCT FROM z.source),
f AS (SELECT *, floor(copies)::BIGINT AS whole, copies - floor(copies) AS pi FROM e),
h AS (SELECT t.source, s, target, greatest(target - coalesce(sure, 0), 0.0) AS lack FROM t LEFT JOIN (SELECT source, sum(whole * cs)::BIGINT AS sure FROM f GROUP BY source) y ON t.source IS NOT DISTINCT FROM y.source),
r AS (SELECT doc_id, size, s, target, lack, h.source, coalesce(whole, 0) AS whole, pi, CASE WHEN pi > 0 THEN (u / (1 - u)) / (pi / (1 - pi)) END AS q
      FROM x JOIN h ON x.source IS NOT DISTINCT FROM h.source LEFT JOIN f ON x.source IS NOT DISTINCT FROM f.source AND x.g = f.g),
o AS (SELECT *, sum(size) OVER (PARTITION BY source ORDER BY q NULLS LAST, doc_id NULLS FIRST, size ROWS UNBOUNDED PRECEDING) AS upto FROM r)
SELECT doc_id, size, s AS source_size, target, (size * (whole + (CASE WHEN q IS NOT NULL AND lack > 0 AND 2 * upto - size <= 2 * lack THEN 1 ELSE 0 END)))::BIGINT AS taken FROM o
""",
    "op10_jaccard_join": rf"""
WITH RECURSIVE w AS (SELECT row_number() OVER () AS r, doc_id, regexp_extract_all({LOWER.format("coalesce(text, '')")}, '{WORD}') AS ws FROM documents),
s AS (SELECT r, doc_id, CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 5 THEN [array_to_string(ws, ' ')]
      ELSE list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i + 4], ' ')) END AS sh FROM w),
e AS (SELECT DISTINCT r, unnest(sh) AS g FROM s),
n AS (SELECT s.r, s.doc_id, count(e.g) AS n FROM s LEFT JOIN e USING (r) GROUP BY s.r, s.doc_id),
i AS (SELECT a.r AS x, b.r AS y, count(*) AS c FROM e a JOIN e b ON a.g = b.g AND a.r < b.r GROUP BY a.r, b.r),
l AS (SELECT x, y FROM i JOIN n p ON p.r = x JOIN n q ON q.r = y WHERE 100 * c >= 80 * (p.n + q.n - c)),
both_ways AS (SELECT x, y FROM l UNION ALL SELECT y, x FROM l),
reach AS (SELECT r, r AS t FROM n UNION SELECT reach.r, b.y FROM reach JOIN both_ways b ON reach.t = b.x)
SELECT n.doc_id, n.n AS n_shingles, min(m.doc_id) AS component_id
FROM n JOIN reach ON reach.r = n.r JOIN n m ON m.r = reach.t GROUP BY n.r, n.doc_id, n.n
""",
}
