"""The corpus pipeline: quality rules, near-duplicates, mixing, encoding.

Each stage takes (spark, docs, sf_dir), its predecessor's documents, and returns documents of the same columns (the last: ids).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from webtext.llm.bagminhash import near_duplicates
from webtext.llm.common import cut, fresh_path, row_key
from webtext.llm.linefreq import clean_text, judge
from webtext.llm.mixing import mix, repeats
from webtext.llm.q09 import tokenised
from webtext.session import ship


def packed(docs: DataFrame, *names: str) -> DataFrame:
    """The named columns, and all columns of each row as `row`, so that no other name can clash with a stage's own."""
    return docs.select(*names, F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the rules, without their boilerplate lines; n_chars follows the text where lines went.

    A null text has no words and is rejected; a null source is a host; repeated rows are one; no rows give no rows.
    """
    ship(spark)
    kept = judge(packed(docs, "doc_id", "source", "text")).where("kept").withColumn("cleaned", clean_text("text", "removed"))
    row = F.col("row").withField("text", F.col("cleaned"))
    if "n_chars" in docs.columns:
        row = F.when(F.col("removed").isNull(), F.col("row")).otherwise(row.withField("n_chars", F.length("cleaned").cast(docs.schema["n_chars"].dataType)))
    return kept.select(row.alias("row")).select("row.*")


def near_duplicate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class: the one with the smallest id (of several such, the least by hash of its text).

    Null ids come last; texts without words are one class; no rows give no rows.
    """
    ship(spark)
    found = near_duplicates(docs.select("doc_id", "text"))
    order = F.struct(F.col("_id").isNull(), "_id", "_th")
    first = cut(found.groupBy(F.coalesce("class_id", "node").alias("c"), F.col("class_id").isNull().alias("nameless")).agg(F.min(order).alias("one"), F.count("*").alias("n")).select("one._id", "one._th"))
    own = packed(docs, row_key()[0].cast("long").alias("own_id"), row_key()[1].alias("own_th"))
    kept = own.join(first, F.col("own_id").eqNullSafe(F.col("_id")) & (F.col("own_th") == F.col("_th")), "left_semi")
    repeated = not found.groupBy("_id", "_th").count().where("count > 1").isEmpty()
    return (kept.dropDuplicates(["own_id", "own_th"]) if repeated else kept).select("row.*")


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them: a document whose words are taken n times over is n rows.

    Documents without words are not taken; a null source is the last source; rows that share id and source are taken alike.
    """
    ship(spark)
    asked = mix(docs.select("doc_id", "source", "text"))[0].groupBy("doc_id", "source").agg(F.sum("size").alias("size"), F.sum("taken").alias("taken"))
    asked = asked.select(F.col("doc_id").alias("m_id"), F.col("source").alias("m_source"), repeats(F.col("size"), F.col("taken"), F.col("doc_id")).alias("times")).where("times > 0")
    out = packed(docs, "doc_id", "source").join(asked, F.col("doc_id").eqNullSafe(F.col("m_id")) & F.col("source").eqNullSafe(F.col("m_source")))
    return out.select("row", F.explode(F.sequence(F.lit(1), F.col("times"))).alias("nth")).select("row.*")


def encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256 and decoded_sha256 of each row; a null text is an empty one."""
    ship(spark)
    return tokenised(docs)


STAGES = [("quality", quality), ("near_duplicates", near_duplicate), ("mixing", mixing), ("encoding", encoding)]

#: Registers, automaton and permutations have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = ship(spark).read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        path = fresh_path(spark, f"stage-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
