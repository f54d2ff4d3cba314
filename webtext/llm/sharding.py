"""Sharding by extendible hashing, in DataFrame operations only.

A directory over the leading bits of a 60-bit hash. A bucket is the set of rows that share a prefix; it is split on the next bit
only while it holds more than `limit` bytes, so a shard is the shortest prefix whose rows fit. Sums by prefix are
taken from cells of a fixed depth (a few cells for each shard wanted); cells that are still too large, and only they, are summed
again some bits deeper. Rows that share all bits (repeated keys) cannot be split by hashing and are dealt to numbered
overflow pages. Only ids, hashes and sizes are shuffled.

Edge cases: null text has no bytes; null ids are hashed by their text; a single row above the limit is a shard of its own, marked
`fits` = false; rows of no bytes are placed as others; an empty table gives no shards.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from webtext.llm.common import cut

BITS, STEP = 60, 8


def _prefix(depth):
    return F.shiftright("h", BITS - depth) if isinstance(depth, int) else F.expr(f"shiftright(h, cast({BITS} - {depth} as int))")


def hashed(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", *more: Column) -> DataFrame:
    """doc_id, h, n_bytes of each row, and more columns of it."""
    key = F.md5(F.coalesce(F.col(id_col).cast("string"), F.concat(F.lit("text:"), F.coalesce(F.col(text_col), F.lit("")))).cast("binary"))
    return docs.select(F.col(id_col).alias("doc_id"), F.conv(F.substring(key, 1, 15), 16, 10).cast("long").alias("h"), F.octet_length(F.coalesce(F.col(text_col), F.lit(""))).cast("long").alias("n_bytes"), *more)


def directory(rows: DataFrame, limit: int) -> tuple[DataFrame, list[int]]:
    """cell_depth, cell, depth of each cell that has found its shard (depth -1: overflow pages), and the depths used."""
    total = rows.agg(F.coalesce(F.sum("n_bytes"), F.lit(0))).first()[0]
    top = min(BITS, max(0, math.ceil(math.log2(max(1, total / limit)))) + 3)
    low, found, depths, left = 0, None, [], rows
    while True:
        depths.append(top)
        cells = left.groupBy(_prefix(top).alias("cell")).agg(F.sum("n_bytes").alias("bytes"))
        upper = cells.select("cell", "bytes", F.explode(F.sequence(F.lit(low), F.lit(top))).alias("depth")).withColumn("up", F.expr(f"shiftright(cell, {top} - depth)"))
        sums = upper.groupBy("depth", "up").agg(F.sum("bytes").alias("sum")).where(F.col("sum") <= limit)
        best = upper.join(sums, ["depth", "up"]).groupBy("cell").agg(F.min("depth").alias("depth"))
        placed = cut(cells.join(best, "cell", "left").select(F.lit(top).alias("cell_depth"), "cell", "depth"))
        open_cells = placed.where("depth is null").select("cell")
        last = top == BITS
        done = placed.select("cell_depth", "cell", F.coalesce("depth", F.lit(-1)).alias("depth")) if last else placed.where("depth is not null")
        found = done if found is None else found.unionByName(done)
        if last or open_cells.isEmpty():
            return found, depths
        left = left.join(open_cells.withColumnRenamed("cell", "open"), _prefix(top) == F.col("open"), "left_semi")
        low, top = top + 1, min(BITS, top + STEP)


def assign(docs: DataFrame, limit: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, shard (the bits of its prefix, and `+page` for overflow), depth, n_bytes, shard_bytes, shard_rows, fits of each row."""
    out = _dealt(hashed(docs, id_col, text_col), limit)
    sizes = out.groupBy("shard").agg(F.sum("n_bytes").alias("shard_bytes"), F.count("*").alias("shard_rows"))
    return out.join(sizes, "shard").select("doc_id", "shard", F.col("depth").cast("int").alias("depth"), "n_bytes", "shard_bytes", "shard_rows", (F.col("shard_bytes") <= limit).alias("fits"))


def _dealt(rows: DataFrame, limit: int) -> DataFrame:
    """rows (doc_id, h, n_bytes and others) with depth and shard; the directory is made of hashes and sizes alone."""
    found, depths = directory(rows.select("h", "n_bytes"), limit)
    parts = []
    for d in depths:
        own = found.where(F.col("cell_depth") == d).select("cell", "depth")
        parts.append(rows.withColumn("cell", _prefix(d)).join(own, "cell").drop("cell"))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    split = out.where("depth >= 0").withColumn("page", F.lit(None).cast("long"))
    same = W.Window.partitionBy("h")
    nth, largest = F.row_number().over(same.orderBy("n_bytes", "doc_id")), F.max("n_bytes").over(same)
    over = out.where("depth < 0").withColumn("page", F.floor((nth - 1) / F.greatest(F.lit(1), F.floor(F.lit(limit) / F.greatest(largest, F.lit(1))))).cast("long")).withColumn("depth", F.lit(BITS))
    out = split.unionByName(over)
    bits = F.when(F.col("depth") == 0, "").otherwise(F.lpad(F.bin(F.expr(f"shiftright(h, cast({BITS} - depth as int))")), F.col("depth").cast("int"), F.lit("0")))
    return out.withColumn("shard", F.concat(bits, F.coalesce(F.concat(F.lit("+"), F.col("page").cast("string")), F.lit("")))).drop("h", "page")


def write_shards(docs: DataFrame, path: str, limit: int, id_col: str = "doc_id", text_col: str = "text") -> None:
    """Writes docs partitioned by shard, one task for each shard; each row goes to the shard or overflow page that `assign` deals it."""
    key = hashed(docs, id_col, text_col, F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    _dealt(key, limit).select("row.*", F.concat(F.lit("s"), "shard").alias("shard")).repartition("shard").write.partitionBy("shard").parquet(path)
