"""Stream, source, sink and SQL-surface queries."""

import tempfile
from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import functions as F

from webtext.functions.blocks import chunk
from webtext.functions.dom import parse
from webtext.operators import extract as X
from webtext.operators import templates as T
from webtext.plans.extraction import MAIN
from webtext.plans.registry import query
from webtext.sources import archive
from webtext.sqlapi import register
from webtext.streaming import events as S

_BIN = "SELECT (epoch(time_bucket(INTERVAL {w}, ts)))::BIGINT AS start, event_type, count(*)::BIGINT AS n FROM events GROUP BY 1, 2"


def _events(t):
    return S.timed(S.file_stream(t.spark, f"{t.dir}/events.parquet"))


@query("stream_tumbling", _BIN.format(w="1 HOUR"))
def _(t):
    return S.drain(S.windowed(_events(t), "1 hour"), "complete")


@query("stream_sliding", "SELECT (epoch(time_bucket(INTERVAL 15 MINUTE, ts)) - 900 * k)::BIGINT AS start, event_type, count(*)::BIGINT AS n FROM events, range(4) r(k) GROUP BY 1, 2")
def _(t):
    return S.drain(S.windowed(_events(t), "1 hour", "15 minutes"), "complete")


@query("stream_session", """WITH x AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 10 MINUTE THEN 0 ELSE 1 END AS s FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
  y AS (SELECT user_id, ts, sum(s) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM x)
  SELECT user_id, floor(epoch(min(ts)))::BIGINT AS start, count(*)::BIGINT AS n FROM y GROUP BY user_id, g""")
def _(t):
    return S.drain(S.sessions(_events(t), "10 minutes"), "complete")


@query("stream_dedup", "SELECT count(DISTINCT html)::BIGINT AS n FROM pages")
def _(t):
    """Pages replayed twice; copies by hash are removed by state."""
    p = S.file_stream(t.spark, f"{t.dir}/pages.parquet").select(F.sha2("html", 256).alias("h"), "page_id")
    twice = p.select("h", F.explode(F.array(F.lit(0), F.lit(1))).alias("copy"))
    return S.drain(twice.dropDuplicates(["h"]).select("h")).agg(F.count("*").alias("n"))


@query("stream_join", "SELECT v.event_id AS view_id, p.event_id AS purchase_id FROM events v JOIN events p ON v.user_id = p.user_id AND v.event_type = 'view' AND p.event_type = 'purchase' AND p.ts >= v.ts AND p.ts <= v.ts + INTERVAL 1 HOUR")
def _(t):
    return S.drain(S.purchases_after_views(_events(t)))


@query("stream_late", "SELECT event_type, count(*)::BIGINT AS n FROM events GROUP BY 1")
def _(t):
    """A watermark wider than the data's span drops nothing, whatever the order of arrival."""
    shuffled = _events(t).groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n")).select("event_type", "n")
    return S.drain(shuffled, "complete").groupBy("event_type").agg(F.sum("n").alias("n"))


@query("stream_extract", MAIN)
def _(t):
    out, mark = S.shared_folder(t.spark, "webtext-extracted-"), S.shared_folder(t.spark, "webtext-mark-")
    S.extract_into(S.file_stream(t.spark, f"{t.dir}/pages.parquet"), out, lambda b: X.core(b).select("page_id", "main_text"), mark)
    return t.spark.read.schema("page_id long, main_text string").parquet(out).select("page_id", "main_text")


@query("stream_new_template")
def _(t):
    folder = tempfile.mkdtemp(prefix="webtext-index-")
    T.index(t("pages")).select("host", "sig", "page_id").write.parquet(f"{folder}/idx.parquet")
    stream = t.spark.readStream.schema("host string, sig string, page_id long").parquet(f"{folder}/idx.parquet")
    return S.drain(S.first_templates(stream))


@query("warc_roundtrip", "SELECT page_id, url, sha256(html) AS sha FROM pages")
def _(t):
    folder = tempfile.mkdtemp(prefix="webtext-archive-")
    archive.write(t("pages"), folder)
    archive.register(t.spark)
    return t.spark.read.format("page_archive").load(folder).select("page_id", "url", F.sha2("payload", 256).alias("sha"))


@query("sink_roundtrip", "SELECT lang, count(*)::BIGINT AS n FROM documents GROUP BY 1")
def _(t):
    """Partitioned by language; one partition rewritten with dynamic overwrite."""
    folder = tempfile.mkdtemp(prefix="webtext-sink-")
    archive.write_layout(t("documents"), f"{folder}/d")
    archive.write_layout(t("documents").where("lang = 'fr'"), f"{folder}/d")
    return t.spark.read.parquet(f"{folder}/d").groupBy("lang").agg(F.count("*").alias("n"))


@query("sql_surface", MAIN)
def _(t):
    register(t.spark)
    t("pages").createOrReplaceTempView("webtext_pages")
    return t.spark.sql("SELECT page_id, main_text(html) AS main_text FROM webtext_pages")


@query("udtf_blocks", "SELECT page_id, (len(string_split(html, '<p>')) + 3)::BIGINT AS n FROM pages")
def _(t):
    register(t.spark)
    t("pages").createOrReplaceTempView("webtext_pages")
    return t.spark.sql("SELECT page_id, count(*) AS n FROM webtext_pages, LATERAL html_blocks(html) GROUP BY page_id")


@query("udf_scalar", "SELECT page_id, (len(string_split(html, '<p>')) + 3)::BIGINT AS n FROM pages")
def _(t):
    @F.arrow_udf("long")
    def n_blocks(page: pa.Array) -> pa.Array:
        return pa.array([len(chunk(parse(x.as_py()))) for x in page], pa.int64())

    return t("pages").select("page_id", n_blocks("html").alias("n"))


@query("udf_pandas", "SELECT doc_id, length(text)::BIGINT AS n FROM documents")
def _(t):
    @F.pandas_udf("long")
    def n_chars(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:  # resolved when the function is wrapped
        for s in parts:
            yield s.str.len()

    return t("documents").select("doc_id", n_chars("text").alias("n"))
