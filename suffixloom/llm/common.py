"""Helpers shared by the training-data operators: scratch tables, Arrow maps, checked broadcasts."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..scratch import discard, scratch_path, shuffles_dropped, stored  # noqa: F401

#: A side is broadcast only if its measured size is at most this.
BROADCAST_LIMIT_BYTES = 32 << 20


def rows_within(df: DataFrame, row_bytes: int, limit: int = BROADCAST_LIMIT_BYTES) -> bool:
    """Whether df, counted now, has at most limit bytes at row_bytes a row. Call it on stored tables."""
    return df.count() * row_bytes <= limit


def maybe_broadcast(df: DataFrame, row_bytes: int, limit: int = BROADCAST_LIMIT_BYTES) -> DataFrame:
    """df with a broadcast hint if its measured size allows it, else df as it is (a shuffle join, split by AQE)."""
    return F.broadcast(df) if rows_within(df, row_bytes, limit) else df


def slices(batches: Iterator[pa.RecordBatch], rows: int = 1024) -> Iterator[pa.RecordBatch]:
    """The same rows in smaller batches, so that what a task holds beside its input stays small."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


def arrow_map(df: DataFrame, rows: Callable[[pa.RecordBatch], dict[str, list]], schema: str) -> DataFrame:
    """mapInArrow by a function from a batch to columns of Python values, one entry for each column of schema."""
    spark_schema = df.sparkSession.createDataFrame([], schema).schema
    from pyspark.sql.pandas.types import to_arrow_schema

    arrow_schema = to_arrow_schema(spark_schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            columns = rows(batch)
            yield pa.RecordBatch.from_arrays([pa.array(columns[f.name], f.type) for f in arrow_schema], schema=arrow_schema)

    return df.mapInArrow(run, spark_schema)


def utf8(column: pa.Array) -> list[bytes]:
    """The bytes of a string column; null counts as empty."""
    return [b"" if x is None else x for x in column.cast(pa.binary()).to_pylist()]
