"""Connected components by hooking to the least neighbour and contraction."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from webtext.llm.common import cut
from webtext.operators.components import least_labels

#: Edges that one task joins at most (16 bytes each); more are contracted by rounds of joins until no more are left.
ONE_TASK_EDGES = 50_000


def _joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    found = least_labels([e for b in batches for e in zip(b.column("u").to_pylist(), b.column("v").to_pylist(), strict=True)])
    yield pa.record_batch([pa.array(list(x), pa.int64()) for x in (found, found.values())], ["node", "comp"])


def components(edges: DataFrame) -> DataFrame:
    """node, comp (the least node of its component) for the nodes of edges (u, v: hashes, so in no order of their own).

    Each round every node takes its least neighbour as parent and the parent's parent after that; edges are carried over to
    the parents, and those within one node vanish. The graph shrinks by a constant factor a round on average; what is small is
    joined in one task, as each round's shuffles leave files of every task on disk. Minima are
    summed before they are shuffled, so a node with very many neighbours costs no more than others. Null ends and loops are
    ignored; no edges give no rows.
    """
    left = cut(edges.where("u is not null and v is not null and u <> v").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct())
    labels = None

    def moved(new: DataFrame) -> DataFrame:
        to = new.select(F.col("node").alias("comp"), F.col("comp").alias("next"))
        return cut(new if labels is None else labels.join(to, "comp", "left").select("node", F.coalesce("next", "comp").alias("comp")))

    while left.count() > ONE_TASK_EDGES:
        both = left.unionByName(left.select(F.col("v").alias("u"), F.col("u").alias("v")))
        parent = both.groupBy("u").agg(F.min("v").alias("p")).select("u", F.least("u", "p").alias("p"))
        upper = parent.select(F.col("u").alias("p"), F.col("p").alias("pp"))
        parent = cut(parent.join(upper, "p").select(F.col("u").alias("node"), F.col("pp").alias("comp")))
        labels = moved(parent)
        u, v = parent.select(F.col("node").alias("u"), F.col("comp").alias("cu")), parent.select(F.col("node").alias("v"), F.col("comp").alias("cv"))
        over = left.join(u, "u").join(v, "v").where("cu <> cv")
        left = cut(over.select(F.least("cu", "cv").alias("u"), F.greatest("cu", "cv").alias("v")).distinct())
    return moved(left.coalesce(1).mapInArrow(_joined, "node long, comp long"))
