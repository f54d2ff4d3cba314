"""Connected components by hooking to the least neighbour and contraction; each round is written out and its lineage cut."""

from __future__ import annotations

import tempfile
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from webtext.session import ship

#: Edges that one task joins at most; more are contracted by rounds of joins until no more are left.
ONE_TASK_EDGES = 10_000


def cut(df: DataFrame) -> DataFrame:
    """A checkpoint in the session's shared folder; one of our own only where none is set."""
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(df.sparkSession.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="webtext-checkpoint-"))
    return df.checkpoint(eager=True)


def least_labels(edges: list[tuple]) -> dict:
    """The least node of its component for each node of the edges."""
    top = {}

    def find(x):
        while top[x] != x:
            top[x] = x = top[top[x]]
        return x

    for u, v in edges:
        a, b = sorted((find(top.setdefault(u, u)), find(top.setdefault(v, v))))
        top[b] = a
    return {x: find(x) for x in list(top)}


def components(edges: DataFrame) -> DataFrame:
    """node, comp (its component's least node) of the nodes of edges (u, v)."""
    ship(edges.sparkSession)
    kind = edges.schema["u"].dataType.simpleString()
    left = cut(edges.where("u <> v").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct())
    labels = None

    def moved(labels: DataFrame | None, new: DataFrame) -> DataFrame:
        to = new.select(F.col("node").alias("comp"), F.col("comp").alias("next"))
        return new if labels is None else cut(labels.join(to, "comp", "left").select("node", F.coalesce("next", "comp").alias("comp")))

    while left.count() > ONE_TASK_EDGES:
        both = left.unionByName(left.select(F.col("v").alias("u"), F.col("u").alias("v")))
        # least by hash: along a chain of rising ids the least neighbour would move only two nodes a round
        first = F.least(F.struct(F.xxhash64("u"), F.col("u").alias("n")), F.col("p"))["n"]
        parent = both.groupBy("u").agg(F.min(F.struct(F.xxhash64("v"), F.col("v").alias("n"))).alias("p")).select("u", first.alias("p"))
        upper = parent.select(F.col("u").alias("p"), F.col("p").alias("pp"))
        parent = cut(parent.join(upper, "p").select(F.col("u").alias("node"), F.col("pp").alias("comp")))
        labels = moved(labels, parent)
        u, v = (parent.select(F.col("node").alias(n), F.col("comp").alias(f"c{n}")) for n in "uv")
        left = cut(left.join(u, "u").join(v, "v").where("cu <> cv").select(F.least("cu", "cv").alias("u"), F.greatest("cu", "cv").alias("v")).distinct())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = least_labels([e for b in batches for e in zip(b.column("u").to_pylist(), b.column("v").to_pylist(), strict=True)])
        yield pa.record_batch([pa.array(list(x), b) for x, b in ((found, ids), (found.values(), ids))], ["node", "comp"])

    ids = to_arrow_type(edges.schema["u"].dataType)
    last = moved(labels, cut(left.coalesce(1).mapInArrow(run, f"node {kind}, comp {kind}")))
    if labels is None:
        return last
    return last.join(last.groupBy("comp").agg(F.min("node").alias("least")), "comp").select("node", F.col("least").alias("comp"))
