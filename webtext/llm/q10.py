"""op10: every page through archives and back."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from webtext.llm.common import fresh_path, read
from webtext.llm.warc import read_payloads, write_archives


def op10_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = fresh_path(spark, "archives")
    write_archives(read(spark, sf_dir, "pages").select("page_id", "url", "html"), path)
    return read_payloads(spark, path).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "status")


SQL = """
WITH p AS (SELECT page_id, encode(coalesce(html, '')) AS body FROM pages),
d AS (SELECT page_id, octet_length(body)::BIGINT AS payload_bytes, sha256(body) AS payload_digest FROM p),
m AS (SELECT *, CASE WHEN payload_bytes >= 100 THEN min(page_id) OVER (PARTITION BY payload_digest) END AS first_id FROM d)
SELECT page_id, payload_bytes, payload_digest,
       CASE WHEN page_id > first_id THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN page_id > first_id THEN first_id END AS refers_to, 'ok' AS status
FROM m
"""
