"""Global positions of rows that are sorted within ordered partitions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..scratch import stored

_ROW_BITS = 33  # monotonically_increasing_id() has the partition above these bits and the row below


def with_positions(ordered: DataFrame, label: str = "ordered") -> DataFrame:
    """ordered with pos. The rows are written once along with where they stand; counts of partitions (a row each) do the rest.

    scratch of what comes back is the path that was written, and rows their number."""
    written = stored(ordered.withColumn("at", F.monotonically_increasing_id()), label)
    split = written.withColumns({"chunk": F.shiftright("at", _ROW_BITS), "row": F.col("at").bitwiseAND((1 << _ROW_BITS) - 1)}).drop("at")
    counts = sorted((r["chunk"], r["count"]) for r in split.groupBy("chunk").count().collect())
    starts, total = [], 0
    for chunk, n in counts:
        starts.append((chunk, total))
        total += n
    offsets = ordered.sparkSession.createDataFrame(starts, "chunk long, start long")
    out = split.join(F.broadcast(offsets), "chunk").withColumn("pos", F.col("start") + F.col("row")).drop("chunk", "row", "start")
    out.scratch, out.rows = written.scratch, total
    return out
