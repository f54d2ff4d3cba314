"""One Arrow pass over a table with a Python function per row. Rows are independent; nothing is shuffled."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from webtext.session import ship

#: Bytes of input values that are turned into output rows at a time.
BATCH_BYTES = 8 << 20


def row_pass(df: DataFrame, fn: Callable[..., list[tuple] | tuple | None], schema: str, many: bool = False, batch_bytes: int = BATCH_BYTES) -> DataFrame:
    """fn gets the values of df's columns and returns a row (or rows, if many; or None for no row) of schema."""
    ship(df.sparkSession)
    fields = to_arrow_schema(StructType.fromDDL(schema))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            step = max(1, int(batch.num_rows * batch_bytes / max(batch_bytes, batch.nbytes)))
            for at in range(0, batch.num_rows, step):
                part = batch.slice(at, step)
                rows = []
                for values in zip(*(c.to_pylist() for c in part.columns), strict=True):
                    got = fn(*values)
                    if got is not None:
                        rows.extend(got) if many else rows.append(got)
                columns = zip(*rows, strict=True) if rows else [[] for _ in fields]
                yield pa.record_batch([pa.array(c, f.type) for c, f in zip(columns, fields, strict=True)], schema=fields)

    return df.mapInArrow(run, schema)


def distinct_rows(df: DataFrame) -> DataFrame:
    """The distinct rows of df and their number (copies), dealt over the tasks of a shuffle: for costly passes over rows that repeat.

    A table of one file is one task; what is dealt here is worked on by all.
    """
    columns = df.columns
    key = F.sha2(F.concat_ws("|", *[F.coalesce(F.sha2(F.col(c).cast("string"), 256), F.lit("null")) for c in columns]), 256)
    x = df.select(key.alias("row_key"), *columns).groupBy("row_key").agg(*[F.first(c).alias(c) for c in columns], F.count("*").alias("copies"))
    return x.select(*columns, "copies").repartition(4 * df.sparkSession.sparkContext.defaultParallelism)
