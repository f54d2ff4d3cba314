"""Queries against their SQL on the smallest tables, and plans."""

import math
import os

import duckdb
import pytest

from webtext.plans import CATALOGUE

SF = "/root/testdata/sf0.001"
SAMPLE = [
    "extract_core", "page_blocks", "fsm_output_valid", "tag_inventory", "canonical_url", "inference_share", "propagated_main", "markdown", "html_render", "code_blocks", "code_language", "table_markdown", "list_markdown",
    "formula_modes", "thread_extract", "rulebook_main", "strip_all_text", "exact_dedup", "lang_vote", "q_reasons", "q_gram_repetition", "fuzzy_dedup", "attrition_rows", "benchmark_overlap", "token_budget", "rouge5_rulebook",
    "ratio_histogram", "stratified_pairs", "teds_tables", "lm_cross_entropy", "budget_curve", "join_interval", "join_asof", "join_salted", "track_cube", "win_range_frame", "set_except_all", "fn_json", "stream_session", "stream_join", "warc_roundtrip", "udtf_blocks",
]


def _plain(v):
    if isinstance(v, float):
        return None if math.isnan(v) else int(v) if v == int(v) else round(v, 6)
    return v if v is None or isinstance(v, (int, str, bool)) else str(v)


@pytest.mark.parametrize("name", SAMPLE)
def test_query_equals_sql(spark, name):
    q = CATALOGUE[name]
    con = duckdb.connect()
    for f in os.listdir(SF):
        con.execute(f"CREATE VIEW {f.split('.')[0]} AS SELECT * FROM '{SF}/{f}'")
    df = q.run(spark, SF)
    cur = con.execute(q.sql)
    names = [d[0] for d in cur.description]
    assert sorted(names) == sorted(df.columns)
    order = sorted(names)
    got = sorted(repr([_plain(r[n]) for n in order]) for r in df.collect())
    assert got == sorted(repr([_plain(r[names.index(n)]) for n in order]) for r in cur.fetchall())


def test_a_wrong_labelling_is_caught(spark):
    """Labelling blocks by whether documents hold their text must fail: advertisements are lines of documents too."""
    from pyspark.sql import functions as F

    from webtext.operators import extract as X

    lines = spark.read.parquet(f"{SF}/documents.parquet").select(F.explode(F.split("text", "\n")).alias("line")).distinct()
    b = X.blocks(spark.read.parquet(f"{SF}/pages.parquet")).where("tag = 'div' or path like '%div.ad%'")
    text = F.trim(F.regexp_replace("raw_html", "<[^>]*>", ""))
    assert b.withColumn("line", text).join(lines, "line", "left_semi").count() > 0


def test_plans(spark):
    plan = lambda n: CATALOGUE[n].run(spark, SF)._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(lang)" in plan("proj_filter")
    for name in ("exact_dedup", "join_interval", "join_asof", "join_salted", "propagated_main"):
        assert "CartesianProduct" not in plan(name) and "BroadcastNestedLoopJoin" not in plan(name)
    physical = plan("exact_dedup").split("== Physical Plan ==")[1]
    assert all("text" not in line for line in physical.splitlines() if "Exchange" in line)


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() == 50
    assert set(e.oracle_sql()) <= set(e.queries())
