"""What a suffix array is for: search, repeats, common prefixes, the transform column, seeds, copied passages."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.alphabet import Bytes
from ..functions.refs import RefLayout
from ..scratch import discard, shuffles_dropped, stored
from . import blocks, suffixes
from .partitioning import assign_partition, read_boundaries
from .suffixes import by_shares, in_share, shares_of


def search(reads: DataFrame, patterns: DataFrame, alphabet, width: int, layout: RefLayout = RefLayout()) -> DataFrame:
    """(pattern_id, ref) of all places of patterns (pattern_id, pattern) of any length but zero; null and empty patterns have none.

    A pattern is met by the code of its first symbols, width of them at most, in an equi-join: a suffix offers one head for each
    length that occurs (width of them at most, a row each comes to the driver). Only longer patterns are then compared with reads.
    """
    from .suffixes import expand_refs

    n = F.least(F.length("pattern"), F.lit(width))
    known = patterns.where(F.length("pattern") > 0).select("pattern_id", "pattern", n.alias("m"))
    lengths = sorted(r["m"] for r in known.select("m").distinct().collect())
    heads = known.withColumn("want", alphabet.encode(F.col("pattern"), width))
    if not alphabet.whole_symbols:
        raise ValueError("search needs codes of whole symbols")
    refs = expand_refs(reads, alphabet, width, layout)
    cut = lambda m: F.col("code") - F.pmod("code", F.lit(alphabet.base ** (width - m)))
    offered = refs.select("ref", "slen", F.explode(F.array(*(F.struct(F.lit(m).alias("m"), cut(m).alias("want")) for m in lengths))).alias("head")) if lengths else refs.select("ref", "slen", F.struct(F.lit(0).alias("m"), F.col("code").alias("want")).alias("head"))
    met = offered.where("slen >= head.m").select("ref", F.col("head.m").alias("m"), F.col("head.want").alias("want")).join(heads, ["m", "want"]).select("pattern_id", "pattern", "ref")
    own = reads.select(F.col("read_id").alias("store_id"), "seq")
    long = met.where(F.length("pattern") > width).join(own, layout.read_id(F.col("ref")) == F.col("store_id"))
    fits = long.where(F.substring(F.col("seq"), layout.offset(F.col("ref")).cast("int") + 1, F.length("pattern")) == F.col("pattern"))
    return met.where(F.length("pattern") <= width).select("pattern_id", "ref").unionByName(fits.select("pattern_id", "ref"))


def store_index(reads: DataFrame, alphabet, width: int, path: str, parts: int = 32, layout: RefLayout = RefLayout()) -> None:
    """(code, ref, slen) sorted by code over range-partitioned files, whose least and greatest codes let a search skip nearly all of them."""
    from .suffixes import expand_refs

    # a range exchange would make all codes twice, once for its sample
    refs = assign_partition(expand_refs(reads, alphabet, width, layout), read_boundaries(reads, alphabet, width, parts, layout))
    with shuffles_dropped(reads.sparkSession):
        refs.repartitionById(parts, F.col("part")).drop("part").sortWithinPartitions("code", "ref").write.mode("overwrite").option("compression", "zstd").parquet(path)


def _spans(intervals: list[tuple[int, int]], most: int) -> list[tuple[int, int]]:
    """At most so many intervals that hold all of the given ones, without the widest gaps between them."""
    merged: list[list[int]] = []
    for low, high in sorted(intervals):
        if merged and low <= merged[-1][1] + 1:
            merged[-1][1] = max(merged[-1][1], high)
        else:
            merged.append([low, high])
    gaps = sorted(range(1, len(merged)), key=lambda i: merged[i][0] - merged[i - 1][1], reverse=True)[: most - 1]
    edges = [0, *sorted(gaps), len(merged)]
    return [(merged[i][0], merged[j - 1][1]) for i, j in zip(edges, edges[1:])]


def search_index(spark: SparkSession, path: str, reads: DataFrame, patterns: list[tuple[int, str]], alphabet, width: int, layout: RefLayout = RefLayout()) -> DataFrame:
    """(pattern_id, ref) by a stored index, for a stated list of patterns of at least one symbol: each is an interval of codes, which
    goes down to the scan. Only patterns longer than the width look at reads."""
    if not patterns:
        return spark.createDataFrame([], "pattern_id long, ref long")
    code = lambda p: sum((alphabet.symbols.index(c) + 1) * alphabet.base ** (width - 1 - i) for i, c in enumerate(p[:width]))
    span = lambda p: alphabet.base ** max(0, width - len(p))
    bounds = [(i, p, code(p), code(p) + span(p) - 1) for i, p in patterns if set(p[:width]) <= set(alphabet.symbols)]
    if not bounds:
        return spark.createDataFrame([], "pattern_id long, ref long")
    # codes are parted by the intervals' ends, found by binary search; each part meets the patterns that hold it by its number
    ends = sorted({x for _, _, low, high in bounds for x in (low - 1, high)})
    at = {x: n for n, x in enumerate(ends)}
    holds = [(part, i, p) for i, p, low, high in bounds for part in range(at[low - 1] + 1, at[high] + 1)]
    wanted = F.broadcast(spark.createDataFrame(holds, "part int, pattern_id long, pattern string"))
    inside = F.lit(False)
    for low, high in _spans([(low, high) for _, _, low, high in bounds], 32):
        inside = inside | F.col("code").between(low, high)
    refs = assign_partition(spark.read.schema("code long, ref long, slen int").parquet(path).where(inside), ends)
    met = refs.join(wanted, "part").where(F.col("slen") >= F.least(F.length("pattern"), F.lit(width)))
    own = reads.select(F.col("read_id").alias("store_id"), "seq")
    long = met.where(F.length("pattern") > width).join(own, layout.read_id(F.col("ref")) == F.col("store_id"))
    fits = long.where(F.substring(F.col("seq"), layout.offset(F.col("ref")).cast("int") + 1, F.length("pattern")) == F.col("pattern"))
    return met.where(F.length("pattern") <= width).select("pattern_id", "ref").unionByName(fits.select("pattern_id", "ref"))


def common_prefix_with_previous(sa: DataFrame) -> DataFrame:
    """(pos, ref, suffix) -> pos, ref, lcp: length of the common prefix with the suffix before.

    Positions are dealt in blocks; a block's last row is copied to the next, so that no window spans the table.
    """
    block = 1 << 14
    own = sa.select("pos", "ref", "suffix", (F.col("pos") / block).cast("long").alias("block"))
    edge = own.where(F.col("pos") % block == block - 1).withColumns({"block": F.col("block") + 1, "ref": F.lit(None).cast("long")})
    before = F.lag("suffix").over(Window.partitionBy("block").orderBy("pos"))
    both = own.unionByName(edge).withColumn("prev", before)
    # doubling search on the length by comparing heads: log2 steps of native comparisons
    length = F.least(F.length("suffix"), F.length("prev"))
    longest = sa.agg(F.max(F.length("suffix"))).first()[0] or 0
    steps = F.array(*(F.lit(1 << k) for k in reversed(range(max(1, longest.bit_length())))))
    found = F.aggregate(steps, F.lit(0), lambda n, s: F.when((n + s <= length) & (F.substring(F.col("suffix"), F.lit(1), n + s) == F.substring(F.col("prev"), F.lit(1), n + s)), n + s).otherwise(n))
    return both.where(F.col("ref").isNotNull()).select("pos", "ref", F.coalesce(F.when(F.col("prev").isNull(), 0).otherwise(found), F.lit(0)).alias("lcp"))


def repeats(reads: DataFrame, k: int, at_least: int = 2, layout: RefLayout = RefLayout()) -> DataFrame:
    """(gram, n): substrings of k symbols that occur at_least times."""
    held = stored(reads.select("read_id", layout.sound(F.col("read_id"), F.col("seq")).alias("seq")), "reads")
    total = held.agg(F.coalesce(F.sum(F.length("seq") + 1), F.lit(0))).first()[0]
    if held.where(F.contains("seq", F.lit("\0"))).limit(1).count():
        # blocks of codes have no room for NUL
        at = held.where(F.length("seq") >= k).select("seq", F.explode(F.sequence(F.lit(1), F.length("seq") - k + 1)).alias("at"))
        by_text = at.select(F.substring(F.col("seq"), F.col("at"), F.lit(k)).alias("gram"))
        return by_shares(total, lambda share: (by_text if share is None else by_text.where(in_share(F.col("gram"), share))).groupBy("gram").agg(F.count("*").alias("n")).where(F.col("n") >= at_least), "repeats")
    shares, slices = shares_of(total, fetches=True), blocks.slices_of(total)
    parts = max(8, blocks.parts_of(total // shares))
    cuts = read_boundaries(held, Bytes, 7, shares * parts, layout)
    packed = stored(blocks.packed(held, Bytes, layout, slices, max(16, slices // 8)), "reads-packed")
    discard(held)
    step = -(-(len(cuts) + 1) // shares)
    edges = [None, *cuts[step - 1 :: step], None]

    def one(share):
        low, high = edges[share[0]], edges[share[0] + 1]
        return blocks.grams(packed, 7, k, at_least, [c for c in cuts if (low is None or c > low) and (high is None or c < high)], (low, high))

    if len(edges) == 2:
        return one((0, 1))
    out = [suffixes.stored(one((i, len(edges) - 1)), "repeats") for i in range(len(edges) - 1)]
    discard(packed)
    return reduce(DataFrame.unionByName, out)


def transform_column(sa: DataFrame, reads: DataFrame, layout: RefLayout = RefLayout()) -> DataFrame:
    """(pos, ref, before): the symbol ahead of each suffix, empty at a read's start; in order of pos it is the Burrows-Wheeler column."""
    own = reads.select(F.col("read_id").alias("store_id"), "seq")
    off = layout.offset(F.col("ref")).cast("int")
    return sa.join(own, layout.read_id(F.col("ref")) == F.col("store_id")).select("pos", "ref", F.when(off == 0, "").otherwise(F.substring(F.col("seq"), off, F.lit(1))).alias("before"))


def seeds(forward: DataFrame, reverse: DataFrame, k: int) -> DataFrame:
    """(read_id, other_id, off): the first k symbols of each reverse read found in forward reads."""
    at = forward.where(F.length("seq") >= k).select("read_id", F.explode(F.sequence(F.lit(0), F.length("seq") - k)).alias("off"), "seq")
    grams = at.select("read_id", "off", F.substring(F.col("seq"), F.col("off") + 1, F.lit(k)).alias("seed"))
    heads = reverse.where(F.length("seq") >= k).select(F.col("read_id").alias("other_id"), F.substring("seq", 1, k).alias("seed"))
    return grams.join(heads, "seed").select("read_id", "other_id", "off")


def copied_passages(texts: DataFrame, items: DataFrame, id_col: str, item_col: str, seed: int = 32) -> DataFrame:
    """(item_id, id) of passages found verbatim in whole texts: seeds of the passages' heads meet the texts' windows by hash.

    A passage shorter than seed is a seed of its own length, so texts offer windows of each length that occurs (seed of them at
    most, a row each comes to the driver). Null and empty passages have no place.
    """
    known = items.select(F.col(item_col).alias("item_id"), F.col("text").alias("passage"), F.least(F.length("text"), F.lit(seed)).alias("m")).where("m > 0")
    lengths = sorted(r["m"] for r in known.select("m").distinct().collect())
    heads = known.withColumn("h", F.xxhash64("m", F.substring(F.col("passage"), F.lit(1), F.col("m"))))
    at = texts.select(F.col(id_col).alias("id"), F.col("text").alias("body"))

    def windows(m: int):
        all_of = F.transform(F.sequence(F.lit(1), F.length("body") - m + 1), lambda i: F.xxhash64(F.lit(m), F.substring(F.col("body"), i, F.lit(m))))
        return F.when(F.length("body") >= m, F.array_distinct(all_of)).otherwise(F.array().cast("array<bigint>"))

    offered = F.concat(*map(windows, lengths)) if lengths else F.array().cast("array<bigint>")
    pairs = at.select("id", F.explode(offered).alias("h")).join(heads.select("item_id", "h"), "h").select("id", "item_id").distinct()
    return pairs.join(at, "id").join(heads.select("item_id", "passage"), "item_id").where(F.contains("body", F.col("passage"))).select("item_id", "id")
