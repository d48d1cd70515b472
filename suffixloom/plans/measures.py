"""Cost measures: the footprint model, disk need, efficiency, the time model, and counters of real runs."""

from __future__ import annotations

import json
import math
import urllib.request

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def merged_segments(files: int, factor: int = 10) -> int:
    """Segments merged early, so that the last pass has at most `factor`: the first pass takes just enough to make the others full."""
    merged, first = 0, True
    while files > factor:
        take = factor
        if first:
            take = (files - 1) % (factor - 1) + 1
            take = factor if take == 1 else take
        merged, files, first = merged + take, files - take + 1, False
    return merged


def spill_count(received_gb: float, heap_gb: float) -> float:
    """Segments on a reducer's disk: each is two thirds of the shuffle buffer, which is 0.7 of the heap."""
    return received_gb / (heap_gb * 0.7 * 2 / 3)


def reduce_side_units(received_gb: float, heap_gb: float, overhead: float = 1.03, factor: int = 10) -> float:
    """Local bytes read (and written) by reducers, in units of the suffix file."""
    segments = spill_count(received_gb, heap_gb)
    return overhead * (1 + merged_segments(math.ceil(segments), factor) / segments) if segments > factor else overhead


def map_side_units(pair_bytes: float, records: float, split_bytes_in_units: float = 1.0, buffer_mb: float = 100, trigger: float = 0.8, factor: int = 10, record_overhead: int = 16) -> tuple[float, float]:
    """(reads, writes) of a mapper's spills in units of its output; bookkeeping for each record fills the buffer too."""
    spills = math.ceil(records * (pair_bytes + record_overhead) / (buffer_mb * 1e6 * trigger))
    if spills <= 1:
        return 0.0, split_bytes_in_units
    early = merged_segments(spills, factor) / spills
    return (1 + early) * split_bytes_in_units, (2 + early) * split_bytes_in_units


def scheme_units(pair_bytes: int, length: int, spills: int, factor: int = 10, output_units: float = 1.01) -> dict[tuple[str, str], float]:
    """The seven counters by (side, counter) for reads of one length, in units of their suffixes: only pairs are spilled and shuffled."""
    pair = pair_bytes / ((1 + length) / 2)
    early = merged_segments(spills, factor) / spills
    one = {("map", "dfs_read"): 2 / (1 + length), ("reduce", "dfs_write"): output_units, ("reduce", "shuffle"): pair}
    return one | {("map", "local_read"): pair * (1 + early), ("map", "local_write"): pair * (2 + early), ("reduce", "local_read"): pair, ("reduce", "local_write"): pair}


def to_units(sums: DataFrame, base: str, digits: int = 2) -> DataFrame:
    """Bytes in columns of sums as multiples of the column base, which goes."""
    return sums.select(*(F.round(F.col(c) / F.col(base), digits).alias(c) for c in sums.columns if c != base))


def placement_plan(disks_gb: list[float], most: int) -> list[int]:
    """Files for a node of each disk size, in proportion to the smallest, most of them at most."""
    return [min(most, round(gb / min(disks_gb))) for gb in disks_gb]


def phase_split(minutes: float, percent: dict[str, float]) -> dict[str, float]:
    return {phase: minutes * share / 100 for phase, share in percent.items()}


def accesses(fetched: DataFrame, layout, shards: int) -> DataFrame:
    """(ref, tail) -> shard, n, symbols: lookups of each shard and what they fetch."""
    shard = F.pmod(layout.read_id(F.col("ref")), F.lit(shards))
    return fetched.groupBy(shard.alias("shard")).agg(F.count("*").alias("n"), F.sum(F.length("tail")).alias("symbols"))


def access_profile(accessed: DataFrame) -> DataFrame:
    """accesses() of all shares -> one row: lookups, symbols of each, lookups of the busiest and idlest shard, symbols that memory serves."""
    by = accessed.groupBy("shard").agg(F.sum("n").alias("n"), F.sum("symbols").alias("symbols"))
    return by.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("lookups"), F.round(F.sum("symbols") / F.sum("n"), 6).alias("symbols_a_lookup"), F.max("n").alias("busiest_shard"), F.min("n").alias("idlest_shard"), F.sum("symbols").alias("memory_symbols"))


def scalability_report(name: str, balance: DataFrame, groups: DataFrame, reads: DataFrame, pair_bytes: int = 16) -> DataFrame:
    """One row: load (largest range over the mean), structure (largest group), space (bytes shuffled over bytes of suffixes)."""
    n = F.length("seq").cast("long")
    load = balance.agg(F.round(F.max("n") / F.avg("n"), 6).alias("load"))
    structure = groups.agg(F.max("n").alias("structure"))
    space = reads.agg(F.round((F.sum(pair_bytes * (n + 1)) / F.sum((n * (n + 1) / 2).cast("long"))), 6).alias("space"))
    return load.join(F.broadcast(structure)).join(F.broadcast(space)).select(F.lit(name).alias("reads_view"), "load", "structure", "space")


def reducer_disk_need(received_gb: float, units: float, output_units: float = 1.01, per_node: int = 2) -> float:
    """GB of disk on a node: temporary data and output of its reducers."""
    return received_gb * per_node * (units + output_units)


def memory_ratio(raw_gb: float, base_gb: float = 256, overhead: float = 1.5) -> float:
    return (base_gb + overhead * raw_gb) / base_gb


def fit_time_model(times: DataFrame) -> DataFrame:
    """(variant, x, t) -> variant, a, b of t = a x + b."""
    return times.groupBy("variant").agg(F.regr_slope("t", "x").alias("a"), F.regr_intercept("t", "x").alias("b"))


def predict(a: float, b: float, x: float, breakdown: float | None) -> float | None:
    """Minutes at size x; none at the breakdown and beyond."""
    return None if breakdown is not None and x >= breakdown else a * x + b


def repeat_stats(times: DataFrame) -> DataFrame:
    """(case_id, t) -> case_id, mean, std."""
    return times.groupBy("case_id").agg(F.avg("t").alias("mean"), F.stddev_samp("t").alias("std"))


def memory_profile(kind: str) -> dict[str, str]:
    """Spark settings that play the part of the heap variants: set them when a session starts."""
    return {
        "default": {"spark.executor.memory": "7g", "spark.executor.cores": "1"},
        "heap": {"spark.executor.memory": "15g", "spark.executor.cores": "1"},
        "tenure": {"spark.executor.memory": "7g", "spark.executor.extraJavaOptions": "-XX:+UseG1GC -XX:MaxTenuringThreshold=0 -Xmn1g"},
    }[kind]


def measured_footprint(spark: SparkSession) -> dict[str, int]:
    """Bytes of the finished stages of this application by counter, from its own status service (needs the UI)."""
    base = f"{spark.sparkContext.uiWebUrl}/api/v1/applications/{spark.sparkContext.applicationId}/stages?status=complete"
    stages = json.load(urllib.request.urlopen(base))
    names = {"dfs_read": "inputBytes", "dfs_write": "outputBytes", "shuffle_read": "shuffleReadBytes", "shuffle_write": "shuffleWriteBytes", "spill": "diskBytesSpilled"}
    return {k: sum(s[v] for s in stages) for k, v in names.items()}


def bottleneck(cpu_s: float, gc_s: float, spill_bytes: float, fetch_wait_s: float, disk_rate: float = 1e8) -> str:
    """The resource that takes the largest share of task time."""
    shares = {"cpu": cpu_s, "memory": gc_s, "disk": spill_bytes / disk_rate, "network": fetch_wait_s}
    return max(shares, key=shares.get)
