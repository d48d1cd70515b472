"""Read stores: where raw reads are kept, and how tails are fetched from them.

put() lays reads out by read number once; a fetch sends references there and tails back.
"""

from __future__ import annotations

import uuid
from typing import Protocol

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.refs import RefLayout
from ..scratch import discard, scratch_path, stored

#: A store is broadcast only if its reads weigh at most this: the driver collects them, builds the hash table and keeps its blocks.
BROADCAST_BYTES = 8 << 20


def weight_of(reads: DataFrame) -> int:
    """Bytes of all reads as rows of a hash table, about."""
    return reads.agg(F.sum(F.octet_length("seq") + 64)).first()[0] or 0


class ReadStore(Protocol):
    def reads(self) -> DataFrame: ...

    def everywhere(self) -> bool: ...

    def kept(self) -> ReadStore: ...


class ShuffleStore:
    """Joined by number wherever the planner likes."""

    def __init__(self, reads: DataFrame):
        self._reads = reads

    def reads(self) -> DataFrame:
        return self._reads.hint("merge")

    def everywhere(self) -> bool:
        """Whether every executor holds all reads."""
        return False

    def kept(self) -> ReadStore:
        """The same with its reads in files, so that reading them again costs little."""
        return type(self)(stored(self._reads, "reads"))


class BroadcastStore(ShuffleStore):
    """Every executor holds all reads, if they are few enough; otherwise as ShuffleStore."""

    def __init__(self, reads: DataFrame):
        super().__init__(reads)
        self._small = weight_of(reads) <= BROADCAST_BYTES

    def reads(self) -> DataFrame:
        return F.broadcast(self._reads) if self._small else super().reads()

    def everywhere(self) -> bool:
        return self._small


class PlacedStore(ShuffleStore):
    """Reads written once in the shared folder, laid out by number modulo instances: several rounds read it."""

    def __init__(self, reads: DataFrame, instances: int = 16):
        super().__init__(stored(reads.repartition(instances, "read_id"), "reads"))

    def kept(self) -> ReadStore:
        return self


class BucketedStore(ShuffleStore):
    """Reads as a table bucketed by number: a fetch sorts and sends references only, the reads stay where they lie."""

    def __init__(self, reads: DataFrame, instances: int = 16):
        spark, name = reads.sparkSession, f"reads_{uuid.uuid4().hex}"
        reads.write.bucketBy(instances, "read_id").sortBy("read_id").option("path", scratch_path(spark, "reads-bucketed")).saveAsTable(name)
        super().__init__(spark.table(name))

    def kept(self) -> ReadStore:
        return self


class AutoStore(BroadcastStore):
    """Reads written once, then on every executor if they are few enough, else joined by number; the constructions' default."""

    def __init__(self, reads: DataFrame):
        # expansion multiplies a file's reads about a hundredfold, so files stay small; what reads are made from is read once
        held = stored(reads, "reads")
        files = max(16, weight_of(held) // (32 << 20))
        if held.rdd.getNumPartitions() < files:
            first, held = held, stored(held.repartition(files, "read_id"), "reads-dealt")
            discard(first)
        super().__init__(held)

    def kept(self) -> ReadStore:
        return self


STORES = {"auto": AutoStore, "shuffle": ShuffleStore, "broadcast": BroadcastStore, "placed": PlacedStore, "bucketed": BucketedStore}


def fetch_tails(refs: DataFrame, store: ReadStore, layout: RefLayout = RefLayout(), skip: int = 0, whole: bool = False) -> DataFrame:
    """refs with tail: the suffix without its first skip symbols. The cut is made where read and reference meet, so
    only tails travel on; with whole=True the read itself travels and is cut afterwards."""
    own = store.reads().select(F.col("read_id").alias("store_id"), "seq")
    joined = refs.join(own, layout.read_id(F.col("ref")) == F.col("store_id")).drop("store_id")
    if whole:
        return joined.withColumnRenamed("seq", "read")
    return joined.withColumn("tail", F.substring(F.col("seq"), layout.offset(F.col("ref")).cast("int") + 1 + skip, F.length("seq"))).drop("seq")
