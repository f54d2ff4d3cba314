"""Small pieces the training-data operators share."""

from __future__ import annotations

import gc
import tempfile
import uuid

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from webtext.session import ship

#: One word, in Java's and RE2's spelling: a run of anything but ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return ship(spark).read.parquet(f"{sf_dir}/{table}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: the session's spark.checkpoint.dir.

    Only where the cluster names none (tests, local mode) a folder of our own is made and set.
    """
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if named is None:
        named = tempfile.mkdtemp(prefix="webtext-checkpoint-")
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(named)
    return named


def fresh_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark).rstrip('/')}/{tag}-{uuid.uuid4().hex}"


def cut(df: DataFrame) -> DataFrame:
    """Materialises df in the shared folder and cuts its lineage; survives the loss of executors."""
    shared_dir(ship(df.sparkSession))
    return df.checkpoint(eager=True)


def freed(spark: SparkSession) -> None:
    """Lets go of the shuffle files of what was cut off: Spark removes them when the driver has collected the plans that made them.

    A driver with room to spare may not do that for a whole run, while every shuffle leaves files of each of its tasks.
    """
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def blobs(column: pa.Array) -> list[bytes | None]:
    """The UTF-8 bytes of a string column, None for null."""
    return column.cast(pa.large_binary()).to_pylist()


class WordHashes(dict):
    """word -> 64-bit hash, remembering at most `room` words."""

    def __init__(self, room: int = 300_000, seed: int = 0):
        super().__init__()
        self.room, self.seed = room, seed

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.room:
            self.clear()
        value = self[word] = xxhash.xxh3_64_intdigest(word, self.seed)
        return value


def row_key(id_col: str = "doc_id", text_col: str = "text"):
    """Two columns that tell rows of different content apart even where ids repeat or are null."""
    return [F.col(id_col).alias("_id"), F.xxhash64(F.coalesce(F.col(text_col), F.lit(""))).alias("_th")]


def same_key(left: DataFrame, right: DataFrame):
    return left["_id"].eqNullSafe(right["_id"]) & (left["_th"] == right["_th"])
