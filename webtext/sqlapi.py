"""The SQL surface: functions to call from spark.sql."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from webtext.functions.blocks import assemble, block_rows
from webtext.functions.content import markdown, plain_text, units
from webtext.functions.scoring import lexicon
from webtext.session import ship


def _main(page: str | None) -> str:
    root, blocks, _ = block_rows(page)
    return assemble(root, [b for b, (other, main) in zip(blocks, lexicon(blocks), strict=True) if main > other])


def register(spark: SparkSession) -> None:
    """main_html, main_text, page_markdown (scalar) and html_blocks (table function)."""
    ship(spark)

    def scalar(fn):
        @F.arrow_udf("string")
        def run(page: pa.Array) -> pa.Array:
            return pa.array([fn(x.as_py()) for x in page], pa.string())

        return run

    spark.udf.register("main_html", scalar(_main))
    spark.udf.register("main_text", scalar(lambda page: plain_text(_main(page))))
    spark.udf.register("page_markdown", scalar(lambda page: markdown(units(_main(page)))))

    @F.udtf(returnType="block_id int, tag string, simplified string, truncated boolean")
    class Blocks:
        def eval(self, page: str):
            for r in block_rows(page)[2]:
                yield r["block_id"], r["tag"], r["simplified"], r["truncated"]

    spark.udtf.register("html_blocks", Blocks)
