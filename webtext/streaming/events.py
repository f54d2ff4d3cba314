"""Streams over events and pages (L3; W16)."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def file_stream(spark: SparkSession, path: str, per_trigger: int = 1000) -> DataFrame:
    """Parquet files that arrive at path: the files of a folder, or one file (its folder is filtered to it)."""
    table = spark.read.parquet(path)
    stream = spark.readStream.schema(table.schema).option("maxFilesPerTrigger", per_trigger)
    name = path.rstrip("/").rpartition("/")[2]
    if all(f.rstrip("/").rpartition("/")[2] == name for f in table.inputFiles()):
        return stream.option("pathGlobFilter", name).parquet(path.rstrip("/").rpartition("/")[0])
    return stream.parquet(path)


def shared_folder(spark: SparkSession, prefix: str) -> str:
    """A new folder that driver and executors see: below the session's checkpoint folder if it has one."""
    base = spark.sparkContext.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    return f"{base.rstrip('/')}/{prefix}{uuid.uuid4().hex}" if base else tempfile.mkdtemp(prefix=prefix)


#: State on disk with bounded memory: kept as objects, a state per key fills the heap as the number of keys grows. Restored after the start.
STATE = {
    "spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
    "spark.sql.streaming.stateStore.rocksdb.boundedMemoryUsage": "true",
    "spark.sql.streaming.stateStore.rocksdb.maxMemoryUsageMB": "256",
}


def drain(stream: DataFrame, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Runs what is available now and returns its rows. They are written to files batch by batch, so none meet on the driver.

    complete: a batch replaces those before it. append: a repeated batch overwrites its own folder.
    """
    spark = stream.sparkSession
    out = shared_folder(spark, "webtext-drained-")

    def one(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/all" if mode == "complete" else f"{out}/all/batch={number}")

    spark.createDataFrame([], stream.schema).write.parquet(f"{out}/all" if mode == "complete" else f"{out}/all/batch=-1")  # no batch, no rows
    writer = stream.writeStream.foreachBatch(one).outputMode(mode).option("checkpointLocation", checkpoint or shared_folder(spark, "webtext-stream-")).trigger(availableNow=True)
    before = {k: spark.conf.get(k, None) for k in STATE}
    for k, v in STATE.items():
        spark.conf.set(k, v)
    try:
        q = writer.start()  # a query keeps the settings it was started with
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{out}/all").select(*stream.columns)


def timed(events: DataFrame, late: str = "40 days") -> DataFrame:
    """Event time as a timestamp (watermarks do not take timestamp_ntz)."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)


def windowed(events: DataFrame, width: str, slide: str | None = None) -> DataFrame:
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.unix_timestamp("w.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str) -> DataFrame:
    return events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.unix_timestamp("w.start").alias("start"), "n")


def purchases_after_views(events: DataFrame, within: str = "1 hour") -> DataFrame:
    """Stream-stream join with watermarks on both sides."""
    v = events.where("event_type = 'view'").select(F.col("user_id").alias("vu"), F.col("ts").alias("vt"), F.col("event_id").alias("view_id"))
    p = events.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("pt"), F.col("event_id").alias("purchase_id"))
    return v.join(p, F.expr(f"vu = user_id AND pt >= vt AND pt <= vt + interval {within}")).select("view_id", "purchase_id")


def first_templates(index: DataFrame) -> DataFrame:
    """host, sig, page_id at the first sight of each signature of a host; what a host has shown is its state."""

    def run(key, batches, state):
        seen = set(state.get[0].split(",")) if state.exists else set()
        out = []
        for pdf in batches:
            for sig, page_id in sorted(zip(pdf["sig"], pdf["page_id"], strict=True), key=lambda x: x[1]):
                if sig not in seen:
                    seen.add(sig)
                    out.append((key[0], sig, page_id))
        state.update((",".join(sorted(seen)),))
        yield pd.DataFrame(out, columns=["host", "sig", "page_id"])

    return index.groupBy("host").applyInPandasWithState(run, "host string, sig string, page_id long", "seen string", "append", "NoTimeout")


def extract_into(stream: DataFrame, path: str, extract: Callable[[DataFrame], DataFrame], checkpoint: str) -> None:
    """Arriving pages, extracted per micro-batch; a repeated batch overwrites its own folder, so results are exactly once."""

    def one(batch: DataFrame, number: int) -> None:
        extract(batch).write.mode("overwrite").parquet(f"{path}/batch={number}")

    q = stream.writeStream.foreachBatch(one).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
