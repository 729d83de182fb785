"""The registered queries of this subpackage and the SQL that gives the same rows."""

from __future__ import annotations

from pyspark.sql import functions as F

from .common import table
from .decontaminate import leaks
from .language import identify_documents, identify_pages
from .minhash import near_duplicates
from .mixing import mix
from .rp_forest import near_vectors
from .secret_scan import digest_columns, scan
from .sharding import shard_documents
from .substring_dedup import dedup_substrings
from .toxicity import score_documents
from .warc import archive_pages


def op1_line_dedup(spark, sf_dir):
    """Lines of one to three words stay: in a corpus of any size they repeat by chance in clean texts."""
    return dedup_substrings(table(spark, sf_dir, "documents"), least_line=4)


def op2_latent_leaks(spark, sf_dir):
    return leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op3_toxic_segments(spark, sf_dir):
    """Learns from labelled rows whose checksum has another remainder than 1; the others are held out."""
    rest = F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(3))
    scored = score_documents(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), rest != 1)
    spans = F.array_join(F.transform(F.filter("segments", lambda s: s["tail"] <= 0.01), lambda s: F.concat_ws(":", s["start"].cast("string"), s["end"].cast("string"))), ",")
    return scored.select("doc_id", F.coalesce(rest == 1, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"), spans.alias("spans"))


def op4_arc_to_warc(spark, sf_dir):
    return archive_pages(table(spark, sf_dir, "pages")).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op5_fast_sketch_near_dups(spark, sf_dir):
    return near_duplicates(table(spark, sf_dir, "documents"))


def op6_secret_scan(spark, sf_dir):
    return digest_columns(scan(table(spark, sf_dir, "documents")))


def op7_forest_near_vectors(spark, sf_dir):
    return near_vectors(table(spark, sf_dir, "embeddings"))


def op8_language(spark, sf_dir):
    return identify_documents(table(spark, sf_dir, "documents"))


def page_language(spark, sf_dir):
    """The same fusion with markup, address and host evidence of web pages."""
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text", "lang")
    return identify_pages(table(spark, sf_dir, "pages"), docs)


def op9_cube_mix(spark, sf_dir):
    return mix(table(spark, sf_dir, "documents"))


def op10_lpt_shards(spark, sf_dir):
    return shard_documents(table(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_line_dedup, op2_latent_leaks, op3_toxic_segments, op4_arc_to_warc, op5_fast_sketch_near_dups, op6_secret_scan, op7_forest_near_vectors, op8_language, op9_cube_mix, op10_lpt_shards, page_language)}

ORACLE_SQL = {
    "op4_arc_to_warc": """
WITH p AS (SELECT page_id, coalesce(html, '') AS body FROM pages),
h AS (SELECT page_id, CAST(octet_length(encode(body)) AS BIGINT) AS payload_bytes, sha1(body) AS hex FROM p),
d AS (SELECT page_id, payload_bytes, hex,
  list_aggregate(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
    CAST(((CAST('0x' || substr(hex, CAST(i * 5 // 4 + 1 AS BIGINT), 2) AS INTEGER) >> CAST(3 - (i * 5) % 4 AS INTEGER)) & 31) + 1 AS BIGINT), 1)), 'string_agg', '') AS payload_digest
  FROM h),
r AS (SELECT *, row_number() OVER (PARTITION BY hex ORDER BY page_id NULLS LAST) AS rn,
  first_value(page_id) OVER (PARTITION BY hex ORDER BY page_id NULLS LAST) AS first_id FROM d)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN rn = 1 THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN rn = 1 THEN NULL ELSE first_id END AS refers_to FROM r
""",
}
