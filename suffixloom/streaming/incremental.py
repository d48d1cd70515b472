"""Streams of new reads and of event strings."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.refs import RefLayout
from ..operators.suffixes import expand_refs


def read_stream(spark: SparkSession, path: str, schema: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def stream_refs(reads: DataFrame, alphabet, width: int, layout: RefLayout = RefLayout()) -> DataFrame:
    """Codes and references of new reads: stateless, so it appends."""
    return expand_refs(reads, alphabet, width, layout)


def windowed_groups(events: DataFrame, ts: str, text: str, length: str, slide: str | None = None, late: str | None = None) -> DataFrame:
    """(start, value, n): sizes of groups of equal strings for each event-time window, tumbling or sliding; the same code serves
    tables and streams. With late, rows that much behind are dropped from a stream."""
    df = events.withWatermark(ts, late) if late else events
    window = F.window(ts, length, slide) if slide else F.window(ts, length)
    return df.groupBy(window.alias("w"), F.col(text).alias("value")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "value", "n")


def sessions(events: DataFrame, ts: str, key: str, gap: str, late: str | None = None) -> DataFrame:
    """(key, start, n): sessions of a key by gaps."""
    df = events.withWatermark(ts, late) if late else events
    return df.groupBy(F.session_window(ts, gap).alias("w"), F.col(key).alias("key")).agg(F.count("*").alias("n")).select("key", F.col("w.start").alias("start"), "n")


def distinct_reads(reads: DataFrame, ts: str, late: str) -> DataFrame:
    """Reads once each, remembered for as long as they may come late."""
    return reads.withWatermark(ts, late).dropDuplicatesWithinWatermark(["read_id"])


def late_rows(events: DataFrame, arrival: str, ts: str, key: str, late: str) -> DataFrame:
    """(key, n, late): rows of a key, and those that came more than late behind the latest before them, as a watermark would drop them."""
    order = Window.partitionBy(key).orderBy(arrival).rowsBetween(Window.unboundedPreceding, -1)
    seen = events.select(F.col(key).alias("key"), F.col(ts).alias("ts"), F.max(ts).over(order).alias("seen"))
    return seen.groupBy("key").agg(F.count("*").alias("n"), F.count_if(F.col("ts") < F.col("seen") - F.expr(f"INTERVAL {late}")).alias("late"))


def merge_runs(spark: SparkSession, runs: list[str], path: str, parts: int = 32) -> None:
    """Sorted runs (code, ref, slen), as days of new reads leave them, merged into one sorted index."""
    spark.read.schema("code long, ref long, slen int").parquet(*runs).repartitionByRange(parts, "code", "ref").sortWithinPartitions("code", "ref").write.mode("overwrite").parquet(path)
