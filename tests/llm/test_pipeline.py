"""The corpus pipeline, stage by stage, against brute force on the smallest table."""

from collections import Counter

from pyspark.sql import functions as F

import corpus_pipeline
from webtext.llm import bagminhash, linefreq

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    kept = corpus_pipeline.quality(spark, docs, SF)
    texts = {r.doc_id: r.text for r in docs.collect()}
    m = {i: linefreq.plain_measures(t[:8000]) for i, t in texts.items() if len(t) < 8000}
    failed = {i for i, x in m.items() if x["n_words"] < 20 or 100 * x["n_repeat_words"] > 30 * x["n_words"]}
    ids = {r.doc_id for r in kept.collect()}
    assert kept.columns == docs.columns and not failed & ids
    verdict = {r.doc_id for r in linefreq.judge(docs).where("kept").collect()}
    assert ids == verdict and len(set(m) - failed - ids) <= 0.02 * len(m)
    left = corpus_pipeline.near_duplicate(spark, kept, SF)
    classes = bagminhash.plain_classes({r.doc_id: r.text for r in kept.collect()})
    assert left.columns == docs.columns and sorted(r.doc_id for r in left.collect()) == sorted(set(classes.values()))
    mixed = corpus_pipeline.mixing(spark, left, SF)
    times = Counter(r.doc_id for r in mixed.collect())
    assert mixed.columns == docs.columns and set(times) <= set(classes.values()) and max(times.values()) <= 2
    ids = corpus_pipeline.encoding(spark, mixed, SF)
    assert ids.count() == mixed.count() and {"doc_id", "n_tokens"} <= set(ids.columns)


def test_run(spark):
    assert corpus_pipeline.run(spark, SF).where(F.col("n_tokens") > 0).count() > 50


def test_odd_and_empty_input(spark, odd_docs, no_docs):
    """Every stage on rows of null, empty, long and repeated texts, with columns named as the stages name their own."""
    clash = {c: F.lit(1) for c in ("removed", "kept", "m_id", "times", "nth", "own_id", "_id", "h", "size", "words_left")}
    docs = odd_docs.select("doc_id", "text", "source", F.length("text").cast("long").alias("n_chars"), F.lit("en").alias("lang")).withColumns(clash)
    kept = corpus_pipeline.quality(spark, docs, SF)
    # 3 and 4 are too short, 5 repeats itself, as do the words of the null id
    assert kept.columns == docs.columns and sorted(r.doc_id for r in kept.collect()) == [7, 8]
    left = corpus_pipeline.near_duplicate(spark, docs, SF)
    got = [r.doc_id for r in left.collect()]
    assert left.columns == docs.columns and sorted(got, key=str) == [1, 3, 5, 6, 7, None]
    mixed = corpus_pipeline.mixing(spark, docs, SF)
    assert mixed.columns == docs.columns and mixed.where("doc_id in (1, 2, 9)").isEmpty()
    assert corpus_pipeline.encoding(spark, docs, SF).count() == docs.count()
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, no_docs.withColumn("n_chars", F.lit(0).cast("long")), SF).count() == 0
