"""op5: scores of every document under a model of six sevenths of them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from webtext.llm.common import read
from webtext.llm.ngram import held_out, score


def op5_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score and score of every document; null texts have their end token alone, repeated rows are rows."""
    docs = read(spark, sf_dir, "documents").select("doc_id", held_out("doc_id").alias("held_out"), (~held_out("doc_id")).alias("learn"), "text")
    scores, tokens = score(docs, "learn")
    return scores.drop("learn").withColumn("train_tokens", F.lit(tokens).cast("long"))
