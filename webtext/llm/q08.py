"""op8: how many words of every document the mix takes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from webtext.llm.common import read
from webtext.llm.mixing import mix


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(read(spark, sf_dir, "documents").select("doc_id", "source", "text"))[0].drop("source")
