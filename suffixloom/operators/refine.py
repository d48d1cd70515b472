"""Longer prefixes for groups that need them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.refs import RefLayout
from ..scratch import stored
from .suffixes import expand_refs


def next_codes(refs: DataFrame, reads: DataFrame, alphabet, width: int, begin: int, layout: RefLayout) -> DataFrame:
    """refs with code (units begin .. begin + width - 1 of each suffix) and ended (whether the suffix ends in them)."""
    own = reads.select(F.col("read_id").alias("store_id"), "seq")
    joined = refs.join(own, layout.read_id(F.col("ref")) == F.col("store_id")).drop("store_id")
    suffix = F.substring(F.col("seq"), layout.offset(F.col("ref")).cast("int") + 1, F.length("seq"))
    head = alphabet.window(suffix, begin, width)
    return joined.withColumns({"code": alphabet.encode(head, width), "ended": alphabet.units(head) < width}).drop("seq")


def refine_until_unique(reads: DataFrame, alphabet, width: int, layout: RefLayout = RefLayout(), max_rounds: int = 64) -> tuple[DataFrame, list[int]]:
    """(ref, path) of every suffix, where ordering by path, then ref, is the order of suffixes; and the unresolved after each round.

    Each round appends eight bytes to references whose path others share; text never leaves the store. Counts are
    partial aggregates, and a hot path's join is split by AQE.
    """
    first = expand_refs(reads, alphabet, width, layout)
    open_ = first.select("ref", F.array("code").alias("path"), (F.col("slen") < width).alias("ended"))
    done, left = None, []
    for r in range(1, max_rounds + 1):
        counts = open_.groupBy("path").agg(F.count("*").alias("n"))
        judged = stored(open_.join(counts, "path"), f"refine-{r}")
        settled = judged.where("n = 1 OR ended").select("ref", "path")
        done = settled if done is None else done.unionByName(settled)
        rest = judged.where("n > 1 AND NOT ended").select("ref", "path")
        left.append(rest.count())
        if not left[-1]:
            return done, left
        open_ = next_codes(rest, reads, alphabet, width, r * width, layout).select("ref", F.concat("path", F.array("code")).alias("path"), "ended")
    raise RuntimeError(f"groups still share a path after {max_rounds} rounds")


def refine_groups(reads: DataFrame, alphabet, widths: tuple[int, int], limit: int, layout: RefLayout = RefLayout()) -> DataFrame:
    """(code, more, n): groups by the first width, and those above the limit by the second as well (more is null elsewhere)."""
    narrow, wide = widths
    refs = expand_refs(reads, alphabet, narrow, layout)
    large = refs.groupBy("code").agg(F.count("*").alias("n")).where(F.col("n") > limit).select("code")
    big = refs.join(large, "code", "left_semi").select("ref", F.col("code").alias("head"))
    more = next_codes(big, reads, alphabet, wide - narrow, narrow, layout).groupBy(F.col("head").alias("code"), F.col("code").alias("more")).agg(F.count("*").alias("n"))
    small = refs.join(large, "code", "left_anti").groupBy("code").agg(F.count("*").alias("n")).select("code", F.lit(None).cast("long").alias("more"), "n")
    return small.unionByName(more)


def rank_doubling(reads: DataFrame, layout: RefLayout = RefLayout(), max_rounds: int = 40) -> DataFrame:
    """(ref, rank) of every suffix by doubling compared lengths: for long strings, where prefixes of prefixes repeat.

    A rank is the number of suffixes that are smaller, so equal ones share it; it comes from positions in a range sort.
    """
    from .positions import with_positions

    at = reads.select("read_id", F.posexplode(F.split(F.concat("seq", F.lit("\0")), "")).alias("off", "c")).where("c <> ''")
    ranks = at.select(layout.pack(F.col("read_id"), F.col("off")).alias("ref"), F.when(F.col("c") == "\0", 0).otherwise(F.ascii("c") + 1).cast("long").alias("rank"))
    ranks = stored(ranks, "doubling-0")
    reach = 1
    for r in range(1, max_rounds + 1):
        ahead = ranks.select((F.col("ref") - reach).alias("ref"), F.col("rank").alias("next"))
        # an offset below zero would point into another read: a suffix that ends within reach has no next
        paired = ranks.join(ahead.where(layout.offset(F.col("ref")) < F.lit(layout.stride - reach)), "ref", "left").select("ref", "rank", F.coalesce("next", F.lit(-1)).alias("next"))
        keys = paired.groupBy("rank", "next").agg(F.count("*").alias("n"))
        placed = with_positions(keys.repartitionByRange("rank", "next").sortWithinPartitions("rank", "next"), f"doubling-keys-{r}")
        new = paired.join(placed.select("rank", "next", "pos"), ["rank", "next"]).select("ref", F.col("pos").alias("rank"))
        ranks = stored(new, f"doubling-{r}")
        distinct = placed.count()
        if r > 1 and distinct == before:
            return ranks
        before, reach = distinct, reach * 2
        if reach >= layout.stride:
            return ranks
    return ranks
