"""A trained linear block labeller (B2) and its improvement loop (B12): stand-ins for the published 0.6B model."""

from __future__ import annotations

from pyspark.ml.classification import LogisticRegression
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from webtext.functions.blocks import chunk
from webtext.functions.dom import parse
from webtext.functions.scoring import FEATURES, features
from webtext.operators.components import cut
from webtext.operators.passes import row_pass


def examples(pages: DataFrame) -> DataFrame:
    """page_id, url, block_id, x (features and those of both neighbours), gold."""

    def run(page_id, url, page):
        blocks = chunk(parse(page))
        own = features(blocks)
        none = [0.0] * len(FEATURES)
        return [
            (page_id, url, b.block_id, f + (own[k - 1] if k else none) + (own[k + 1] if k + 1 < len(own) else none), int("/article" in f"/{b.node.path()}/"))
            for k, (b, f) in enumerate(zip(blocks, own, strict=True))
        ]

    return row_pass(pages.select("page_id", "url", "html"), run, "page_id long, url string, block_id int, x array<double>, gold int", many=True)


def fit(train: DataFrame, context: bool = True):
    """Logistic regression on the examples; without context the neighbours are left out. Fitted on labelled pages only, which are few."""
    x = F.col("x") if context else F.slice("x", 1, len(FEATURES))
    return LogisticRegression(featuresCol="v", labelCol="gold", maxIter=25, regParam=0.001).fit(train.select(array_to_vector(x).alias("v"), "gold"))


def predict(model, examples_: DataFrame, context: bool = True) -> DataFrame:
    x = F.col("x") if context else F.slice("x", 1, len(FEATURES))
    out = model.transform(examples_.withColumn("v", array_to_vector(x)))
    return out.select("page_id", "block_id", "gold", F.col("prediction").cast("int").alias("label"), vector_to_array("probability")[1].alias("p"))


def block_f1(judged: DataFrame) -> DataFrame:
    n = lambda g, y: F.count(F.when((F.col("gold") == g) & (F.col("label") == y), 1))
    x = judged.agg(n(1, 1).alias("tp"), n(0, 1).alias("fp"), n(1, 0).alias("fn"))
    return x.withColumn("f1", F.round(2 * F.col("tp") / (2 * F.col("tp") + F.col("fp") + F.col("fn")), 4))


def improve(pool: DataFrame, held: DataFrame, start: int = 1, rounds: int = 3) -> DataFrame:
    """round, n_train (pages), n_failed, tp, fp, fn, f1 on held. The first model is fitted on `start` pages of pool, in the order of a hash.

    Each round lists the pool's pages with a wrong block and adds them to the training set; the set of ids is written out each round.
    """
    ids = cut(pool.select("page_id").distinct().orderBy(F.xxhash64("page_id", F.lit("start")), "page_id").limit(start))
    out = None
    for k in range(rounds):
        model = fit(pool.join(ids, "page_id", "left_semi"))
        failed = cut(predict(model, pool).where("gold <> label").select("page_id").distinct())
        row = block_f1(predict(model, held)).withColumns({"round": F.lit(k), "n_train": F.lit(ids.count()), "n_failed": F.lit(failed.count())})
        out = row if out is None else out.unionByName(row)
        ids = cut(ids.unionByName(failed).distinct())
    return out
