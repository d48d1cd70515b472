"""Sampled range boundaries, routing by them, and balance."""

from __future__ import annotations

from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.refs import RefLayout
from ..scratch import stored
from .positions import with_positions

#: Fixed values of the sampling order: a multiplicative hash of the reference.
MULTIPLIER, INNER, OUTER = 2654435761, 1 << 31, 1 << 32


def sampling_order(ref: Column) -> Column:
    return F.pmod(F.pmod(ref, F.lit(INNER)) * MULTIPLIER, F.lit(OUTER))


def sample_keys(refs: DataFrame, n: int) -> DataFrame:
    """The n keys of smallest hash: repeatable whatever the partitions; a bounded top-n, merged from each task's own."""
    return refs.select("code", "ref", sampling_order(F.col("ref")).alias("h")).orderBy("h", "ref").limit(n).select("code", "ref")


def sample_boundaries(refs: DataFrame, parts: int, per_part: int = 10_000) -> list[int]:
    """parts - 1 cut points: every per_part-th key of a sorted sample of parts * per_part keys. Only they come to the driver."""
    keys = stored(sample_keys(refs, parts * per_part), "sampled-keys")
    step = max(1, min(per_part, keys.count() // parts or 1))
    placed = with_positions(keys.repartitionByRange("code").sortWithinPartitions("code", "ref"), "sampled-order")
    at = F.col("pos") + 1
    rows = placed.where((at % step == 0) & (at / step < parts)).select("code", (at / step).cast("int").alias("i")).collect()  # parts - 1 rows at most
    return [r["code"] for r in sorted(rows, key=lambda r: r["i"])]


def sample_reads(reads: DataFrame, alphabet, width: int, per_read: int = 1, layout: RefLayout = RefLayout()) -> DataFrame:
    """Keys at hashed offsets of each read: a sample for boundaries that needs no expansion of all suffixes."""
    offsets = F.explode(F.transform(F.sequence(F.lit(1), F.lit(per_read)), lambda i: F.pmod(F.xxhash64(F.col("read_id"), i), F.length("seq") + 1).cast("int"))).alias("off")
    at = reads.select("read_id", "seq", offsets)
    head = F.substring(F.col("seq"), F.col("off") + 1, F.lit(width))
    return at.select(alphabet.encode(head, width).alias("code"), layout.pack(F.col("read_id"), F.col("off")).alias("ref"))


def read_boundaries(reads: DataFrame, alphabet, width: int, parts: int, layout: RefLayout = RefLayout(), apart: bool = False) -> list[int]:
    """Up to parts - 1 cut points from one suffix of each read, by a mergeable sketch of quantiles: nothing is expanded twice, and cut points alone come to the driver.

    With apart, a code that is found more than once, as it fills a part, gets a part of its own."""
    if parts < 2:
        return []
    keys = sample_reads(reads, alphabet, width, 1, layout)
    found = keys.agg(F.percentile_approx("code", [i / parts for i in range(1, parts)], 10 * parts).alias("cuts")).first()["cuts"]
    return _with_those_apart(found or []) if apart else sorted(set(found or []))


def _with_those_apart(found: list) -> list:
    """found in order, without repeats; before what is repeated also the number below it."""
    below = lambda c: c - 1 if not isinstance(c, tuple) else (c[0], c[1] - 1)
    return sorted(set(found) | {below(c) for c, n in Counter(found).items() if n > 1})


def pair_boundaries(reads: DataFrame, alphabet, width: int, longer: list[int], span: tuple[int | None, int | None], parts: int, layout: RefLayout = RefLayout()) -> list[tuple[int, int]]:
    """Cut points as pairs (code, more) as expand_refs has them with longer and span, pairs that fill a part by themselves: from 100 sampled suffixes a part, which come to the driver."""
    offset = F.pmod(F.xxhash64("read_id"), F.length("seq") + 1).cast("int")
    head = reads.select("read_id", F.substring(F.col("seq"), offset + 1, F.lit(2 * width)).alias("head"))
    code, more = alphabet.encode(alphabet.window(F.col("head"), 0, width), width), alphabet.encode(alphabet.window(F.col("head"), width, width), width)
    pairs = head.select(F.xxhash64("read_id", F.lit(1)).alias("h"), code.alias("code"), more.alias("more"))
    low, high = span
    pairs = pairs if low is None else pairs.where(F.col("code") > low)
    pairs = pairs if high is None else pairs.where(F.col("code") <= high)
    known = set(longer)
    seen = sorted((r["code"], r["more"] if r["code"] in known else 0) for r in pairs.orderBy("h").limit(100 * parts).collect())
    step = max(1, len(seen) // parts)
    return _with_those_apart(seen[step - 1 : -1 : step])


def assign_partition(df: DataFrame, boundaries: list[int], code: str = "code", name: str = "part") -> DataFrame:
    """Adds the number of boundaries below the key, so that equal keys share a part: a balanced tree of comparisons, or
    binary search over Arrow batches where there are many boundaries."""
    if len(boundaries) <= 256:

        def tree(low: int, high: int) -> Column:
            if low == high:
                return F.lit(low)
            mid = (low + high) // 2
            return F.when(F.col(code) <= boundaries[mid], tree(low, mid)).otherwise(tree(mid + 1, high))

        return df.withColumn(name, tree(0, len(boundaries)))
    cuts = np.array(boundaries, np.int64)

    def run(batches):
        for batch in batches:
            found = np.searchsorted(cuts, batch.column(batch.schema.get_field_index(code)).to_numpy(zero_copy_only=False))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(found.astype(np.int32))], names=[*batch.schema.names, name])

    return df.mapInArrow(run, df.schema.simpleString().removeprefix("struct<").removesuffix(">") + f",{name}:int")


def balance_report(routed: DataFrame) -> DataFrame:
    """part, n"""
    return routed.groupBy("part").agg(F.count("*").alias("n"))


def balance_summary(routed: DataFrame, row_bytes: int = 16) -> DataFrame:
    """One row: parts, suffixes, bytes of the largest part, its share of all, and how many times the mean it is."""
    n = balance_report(routed)
    return n.agg(F.count("*").alias("parts"), F.sum("n").alias("suffixes"), (F.max("n") * row_bytes).alias("largest_bytes"), F.round(F.max("n") / F.sum("n"), 6).alias("largest_share"), F.round(F.max("n") / F.avg("n"), 6).alias("over_mean"))


def shard_of(read_id: Column, instances: int) -> Column:
    return F.pmod(read_id, F.lit(instances))
