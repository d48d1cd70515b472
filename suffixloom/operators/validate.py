"""Checks of a finished suffix array."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def validate_order(sa: DataFrame) -> DataFrame:
    """(pos, ref, suffix) -> one row: violations, n, sum_ref. Rows are compared as they pass, and where two runs of positions meet."""
    return joined_orders(order_of_range(sa))


def order_of_range(sa: DataFrame) -> DataFrame:
    """The same of a range of positions, with its first and last row as (pos, suffix, ref); null if there are none.

    Rows with consecutive positions, as they lie in files, are a run: of it travel only its sums and its two ends, which meet their neighbours'.
    """
    row = "struct<pos:bigint,suffix:string,ref:bigint>"
    runs = sa.select("pos", "suffix", "ref").mapInArrow(_runs, f"violations long, n long, sum_ref long, first {row}, last {row}")
    sums, none = ("violations", "n", "sum_ref"), [F.lit(0).cast("long")] * 3
    begin = F.struct(F.col("first.pos").alias("at"), *sums, F.col("first").alias("begins"), F.lit(None).cast(row).alias("ends"))
    end = F.struct((F.col("last.pos") + 1).alias("at"), *(z.alias(c) for c, z in zip(sums, none)), F.lit(None).cast(row).alias("begins"), F.col("last").alias("ends"))
    met = runs.select(F.explode(F.array(begin, end)).alias("edge")).select("edge.*").groupBy("at").agg(*(F.sum(c).alias(c) for c in sums), F.max("begins").alias("begins"), F.max("ends").alias("ends"))
    wrong = _out_of_order("ends", "begins")
    total = [(F.sum("violations") + F.count_if(wrong)).alias("violations"), F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.coalesce(F.sum("sum_ref"), F.lit(0)).alias("sum_ref")]
    return met.agg(*total, F.min_by("begins", F.when(F.col("begins").isNotNull(), F.col("at"))).alias("first"), F.max_by("ends", F.when(F.col("ends").isNotNull(), F.col("at"))).alias("last"))


def _out_of_order(before: str, after: str) -> Column:
    """Whether the row before may not stand there."""
    same = (F.col(f"{before}.suffix") == F.col(f"{after}.suffix")) & (F.col(f"{before}.ref") >= F.col(f"{after}.ref"))
    return (F.col(f"{before}.suffix") > F.col(f"{after}.suffix")) | same


def _runs(batches):
    """(pos, suffix, ref) -> a row for each run of consecutive positions: violations in it, n, sum_ref, first and last row."""
    held = run = None  # the last row so far, and the run it ends
    for batch in batches:
        if not batch.num_rows:
            continue
        rows = batch if held is None else pa.Table.from_batches([held, batch]).combine_chunks().to_batches()[0]
        pos, suffix, ref = rows.column(0).to_numpy(), rows.column(1), rows.column(2).to_numpy()
        before, after = suffix.slice(0, len(pos) - 1), suffix.slice(1)
        wrong = pc.greater(before, after).to_numpy(zero_copy_only=False)
        wrong |= pc.equal(before, after).to_numpy(zero_copy_only=False) & (ref[:-1] >= ref[1:])
        at = lambda i: {"pos": int(pos[i]), "suffix": suffix[i].as_py(), "ref": int(ref[i])}  # noqa: B023, E731
        cuts, done = np.flatnonzero(pos[1:] != pos[:-1] + 1) + 1, []
        for first, last in zip([0, *cuts.tolist()], [*cuts.tolist(), len(pos)]):
            own = (int(wrong[first : last - 1].sum()), last - first, int(ref[first:last].sum()))
            if first == 0 and run is not None:  # its row that is held was counted before
                run = (run[0] + own[0], run[1] + own[1] - 1, run[2] + own[2] - int(ref[0]), run[3], at(last - 1))
            else:
                done += [run] if run is not None else []
                run = (*own, at(first), at(last - 1))
        if done:
            yield _batch_of(done)
        held = rows.slice(len(pos) - 1)
    if run is not None:
        yield _batch_of([run])


def _batch_of(runs: list[tuple]) -> pa.RecordBatch:
    row = pa.struct([("pos", pa.int64()), ("suffix", pa.string()), ("ref", pa.int64())])
    kinds = {"violations": pa.int64(), "n": pa.int64(), "sum_ref": pa.int64(), "first": row, "last": row}
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*runs), kinds.values())], names=list(kinds))


def joined_orders(ranges: DataFrame) -> DataFrame:
    """One row of the rows of ranges, a few: where two meet, the last row of one and the first of the next are compared as well."""
    before = F.lag("last").over(Window.orderBy("first.pos"))
    met = ranges.where("n > 0").withColumn("before", before)
    wrong = _out_of_order("before", "first")
    zero = lambda c: F.coalesce(F.sum(c), F.lit(0))
    return met.agg((zero("violations") + F.count_if(wrong)).alias("violations"), zero("n").alias("n"), zero("sum_ref").alias("sum_ref"))


def neighbours(sa: DataFrame) -> DataFrame:
    """(pos, ref) -> pos, ref, before, after: the references next to each, in blocks that share their edge rows."""
    block = 1 << 14
    own = sa.select("pos", "ref", (F.col("pos") / block).cast("long").alias("block"), F.lit(True).alias("own"))
    last = own.where(F.col("pos") % block == block - 1).withColumns({"block": F.col("block") + 1, "own": F.lit(False)})
    first = own.where((F.col("pos") % block == 0) & (F.col("pos") > 0)).withColumns({"block": F.col("block") - 1, "own": F.lit(False)})
    order = Window.partitionBy("block").orderBy("pos")
    both = own.unionByName(last).unionByName(first).withColumns({"before": F.lag("ref").over(order), "after": F.lead("ref").over(order)})
    return both.where("own").select("pos", "ref", "before", "after")


def digest(sa: DataFrame, block: int = 10_000) -> DataFrame:
    """(pos, ref) -> block, n, sum_ref, weighted: whole numbers that change if any reference moves."""
    return sa.groupBy((F.col("pos") / block).cast("long").alias("block")).agg(F.count("*").alias("n"), F.sum("ref").alias("sum_ref"), F.sum((F.col("pos") % block + 1) * (F.col("ref") % 1_000_003)).alias("weighted"))


def joined_digests(digests: DataFrame) -> DataFrame:
    """The digest of all rows from digests of ranges of them, which may share blocks."""
    return digests.groupBy("block").agg(*(F.sum(c).alias(c) for c in ("n", "sum_ref", "weighted")))
