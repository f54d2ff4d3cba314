"""op3: every document as audio, read back, with features."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from webtext.llm.audio import audio_features, to_wav
from webtext.llm.common import read


def op3_audio(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents").select("doc_id", F.octet_length(F.coalesce("text", F.lit(""))).cast("long").alias("n_bytes"), to_wav("text").alias("media"))
    out = docs.withColumn("f", audio_features("media"))
    payload = F.col("f.payload")
    return out.select(
        "doc_id",
        "n_bytes",
        F.octet_length(payload).cast("long").alias("payload_bytes"),
        F.sha2(payload, 256).alias("payload_sha256"),
        F.crc32(F.substring(payload, -64, 64)).alias("tail_crc32"),
        F.octet_length("media").cast("long").alias("media_bytes"),
        F.sha2("media", 256).alias("media_sha256"),
        F.concat_ws(":", F.col("f.n_frames"), F.size("f.active"), F.crc32("f.tensors")).alias("feature"),
    )
