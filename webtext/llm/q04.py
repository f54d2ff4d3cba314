"""op4: the near-duplicate class of every document."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from webtext.llm.bagminhash import near_duplicates
from webtext.llm.common import read


def op4_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(read(spark, sf_dir, "documents").select("doc_id", "text")).select(F.col("_id").alias("doc_id"), "class_id")
