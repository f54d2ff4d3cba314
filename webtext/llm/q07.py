"""op7: the shard of every document."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from webtext.llm.common import read
from webtext.llm.sharding import assign

#: Bytes of text in a shard; small, so that the given tables are split too.
LIMIT = 1 << 20


def op7_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return assign(read(spark, sf_dir, "documents").select("doc_id", "text"), LIMIT)


SQL = f"""
WITH d AS (SELECT doc_id, octet_length(encode(coalesce(text, '')))::BIGINT AS n_bytes, ('0x' || substr(md5(doc_id::VARCHAR), 1, 15))::BIGINT AS h FROM documents),
p AS (SELECT doc_id, n_bytes, h, depth, h >> (60 - depth) AS prefix FROM d, range(0, 41) AS r(depth)),
s AS (SELECT depth, prefix, sum(n_bytes)::BIGINT AS shard_bytes, count(*)::BIGINT AS shard_rows FROM p GROUP BY 1, 2),
f AS (SELECT doc_id, any_value(n_bytes) AS n_bytes, any_value(h) AS h, min(depth) AS depth FROM p JOIN s USING (depth, prefix) WHERE shard_bytes <= {LIMIT} GROUP BY doc_id)
SELECT doc_id, CASE WHEN f.depth = 0 THEN '' ELSE lpad(bin(h >> (60 - f.depth)), f.depth::INT, '0') END AS shard, f.depth::INT AS depth, n_bytes, shard_bytes, shard_rows, true AS fits
FROM f JOIN s ON s.depth = f.depth AND s.prefix = h >> (60 - f.depth)
"""
