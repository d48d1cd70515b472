"""Sorting groups: suffixes of the same prefix code."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def sorting_groups(refs: DataFrame) -> DataFrame:
    """code, n"""
    return refs.groupBy("code").agg(F.count("*").alias("n"))


def mark_groups(rows: DataFrame, keys: list[str], asked: str | None = None, keep_keys: bool = False) -> DataFrame:
    """rows, sorted within partitions by keys, of which equal ones share a partition, as ref and back (and, with keep_keys, keys): how many rows before it the first
    of its group stands. back is null in groups of one, and where asked is false. Rows are compared with their neighbours as they
    pass, and one of them is held: no group is gathered or counted."""

    def run(batches):
        held, back, shared = None, 0, False
        for batch in batches:
            if not batch.num_rows:
                continue
            batch = batch if held is None else pa.Table.from_batches([held, batch]).combine_chunks().to_batches()[0]
            n = batch.num_rows
            same = np.ones(n - 1, bool)
            for i in range(len(keys)):
                key = batch.column(i).to_numpy(zero_copy_only=False)
                same &= key[1:] == key[:-1]
            # the first row's group may have begun in an earlier batch
            at = np.arange(n)
            backs = at - np.maximum.accumulate(np.concatenate([[-back], np.where(same, -back, at[1:])]))
            in_group = np.concatenate([[shared], same]) | np.concatenate([same, [False]])
            yield marked(batch.slice(0, n - 1), backs[:-1], in_group[:-1])
            held, back, shared = batch.slice(n - 1), int(backs[-1]), bool(in_group[-1])
        if held is not None:
            yield marked(held, np.array([back]), np.array([shared]))

    def marked(batch, backs, in_group):
        wanted = in_group if asked is None else in_group & batch.column(len(keys) + 1).to_numpy(zero_copy_only=False)
        columns = batch.columns[: len(keys) + 1] if keep_keys else [batch.column(len(keys))]
        return pa.RecordBatch.from_arrays([*columns, pa.array(backs, pa.int64(), mask=~wanted)], names=names)

    names = [*(keys if keep_keys else []), "ref", "back"]
    kinds = ", ".join(f"{k} {'long' if k in ('ref', 'back') else rows.schema[k].dataType.simpleString()}" for k in names)
    return rows.select(*keys, "ref", *([asked] if asked else [])).mapInArrow(run, kinds)


def group_histogram(refs: DataFrame) -> DataFrame:
    """Groups by the power of two of their size: bucket, groups, suffixes."""
    bucket = F.length(F.bin("n")) - 1
    return sorting_groups(refs).groupBy(bucket.cast("int").alias("bucket")).agg(F.count("*").alias("groups"), F.sum("n").alias("suffixes"))


def largest_groups(refs: DataFrame, k: int) -> DataFrame:
    return sorting_groups(refs).orderBy(F.desc("n"), "code").limit(k)


def oversize_groups(refs: DataFrame, limit: int) -> DataFrame:
    return sorting_groups(refs).where(F.col("n") > limit)


def accumulate_groups(groups: DataFrame, limit: int = 1_600_000, mode: str = "exact", range_col: str | None = None) -> DataFrame:
    """Consecutive groups gathered until their suffixes pass the limit: batch_id, groups, suffixes (and range_col).

    exact closes a batch with the group that passes the limit. Each range (range_col; one for all without) is a pass of its own over
    its sorted groups, that steps from batch to batch by binary search and holds a batch's totals only, as each reducer
    gathers the groups of its range. bucketed divides the running sum, which needs no sequential pass.
    """
    keyed = groups.withColumn("range", F.col(range_col) if range_col else F.lit(0))
    if mode == "bucketed":
        order = Window.partitionBy("range").orderBy("code").rowsBetween(Window.unboundedPreceding, -1)
        before = F.coalesce(F.sum("n").over(order), F.lit(0))
        out = keyed.withColumn("batch_id", F.floor(before / limit)).groupBy("range", "batch_id").agg(F.count("*").alias("groups"), F.sum("n").alias("suffixes"))
    else:

        def run(batches):
            range_, batch_id, groups, total = None, 0, 0, 0
            for table in batches:
                rows = []
                ranges, sizes = table.column(0).to_numpy(), table.column(1).to_numpy()
                edges = [*(np.flatnonzero(np.diff(ranges)) + 1), len(ranges)] if len(ranges) else []
                for first, last in zip([0, *edges], edges):
                    if ranges[first] != range_:
                        if groups:
                            rows.append((range_, batch_id, groups, total))
                        range_, batch_id, groups, total = int(ranges[first]), 0, 0, 0
                    sums, at, base = np.cumsum(sizes[first:last]), 0, 0
                    while at < len(sums):
                        # the group with which the batch passes the limit closes it
                        end = int(np.searchsorted(sums, limit - total + base, side="right"))
                        if end >= len(sums):
                            groups, total, at = groups + len(sums) - at, total + int(sums[-1]) - base, len(sums)
                        else:
                            rows.append((range_, batch_id, groups + end + 1 - at, total + int(sums[end]) - base))
                            batch_id, groups, total, at, base = batch_id + 1, 0, 0, end + 1, int(sums[end])
                yield batch_of(rows)
            if groups:
                yield batch_of([(range_, batch_id, groups, total)])

        def batch_of(rows):
            columns = zip(*rows) if rows else [[]] * 4
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=["range", "batch_id", "groups", "suffixes"])

        ordered = keyed.select(F.col("range").cast("long").alias("range"), "code", "n").repartition("range").sortWithinPartitions("range", "code").select("range", "n")
        out = ordered.mapInArrow(run, "range long, batch_id long, groups long, suffixes long")
    out = out.withColumnRenamed("range", range_col) if range_col else out
    return out if range_col else out.drop("range")
