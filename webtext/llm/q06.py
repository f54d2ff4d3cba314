"""op6: measures and verdict of every document."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from webtext.llm.common import read
from webtext.llm.linefreq import Limits, measured_once, verdicts


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The measures and the verdict on every row of documents; null texts have no words, a null source is a host."""
    docs = read(spark, sf_dir, "documents").select("doc_id", "text", "source")
    return verdicts(measured_once(docs), Limits()).select(
        F.col("_id").alias("doc_id"), "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "words_left"
    )
