"""The two constructions: by materialised suffixes, and by references."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.alphabet import DNA, prefix_key
from ..functions.refs import RefLayout
from ..operators import blocks
from ..operators.grouping import mark_groups
from ..operators.partitioning import assign_partition, pair_boundaries, read_boundaries, sample_boundaries, sample_reads
from ..operators.positions import with_positions
from ..operators.refine import refine_until_unique
from ..operators.store import STORES, fetch_tails
from ..operators.suffixes import MOST_SHARES, expand_refs, expand_suffixes, shares_of
from ..scratch import discard, scratch_path, shuffles_dropped, stored


def materialized_suffix_array(source: DataFrame, parts: int = 32, key_width: int = 10, emit: str = "ref", layout: RefLayout = RefLayout()) -> DataFrame:
    """(pos, ref[, suffix]) by a range sort of all suffix texts. source: reads, or suffixes (ref, suffix) made before."""
    suffixes = source if "suffix" in source.columns else expand_suffixes(source, layout)
    # ranges are of whole key groups, as equal keys share a partition
    ordered = suffixes.withColumn("key", prefix_key(F.col("suffix"), key_width)).repartitionByRange(parts, "key").sortWithinPartitions("suffix", "ref")
    return with_positions(ordered.select("ref", "suffix") if emit == "suffix" else ordered.select("ref"), "materialized")


def write_suffixes(reads: DataFrame, layout: RefLayout = RefLayout()) -> str:
    """The suffix file of a baseline that has its suffixes made beforehand; returns the path."""
    path = scratch_path(reads.sparkSession, "suffixes")
    expand_suffixes(reads, layout).write.parquet(path)
    return path


def read_suffixes(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("ref long, suffix string").parquet(path)


def indexed_suffix_array(reads: DataFrame, alphabet=DNA, width: int = 23, int_key: bool = False, parts: int = 32, store: str = "auto", short_rule: bool = True, singleton_rule: bool = True, whole_reads: bool = False, explicit_ranges: bool = False, per_part: int = 1000, emit: str = "ref", layout: RefLayout = RefLayout(), longer_above: int = 1_600_000, then: Callable[[DataFrame], DataFrame] = lambda sa: sa) -> DataFrame:
    """(pos, ref[, suffix]): keys and references are shuffled, text is looked up only for groups that need it.

    A suffix shorter than the prefix is its prefix (short_rule), and a group of one is in order (singleton_rule): neither asks the
    store. For the others the tail behind the prefix is fetched. No group is ever gathered: partitions are sorted externally. Groups above
    longer_above suffixes that would fill a large part of a range get a prefix of twice the width before they are dealt.

    Many suffixes are taken in shares of consecutive codes, so that exchanges and text of one share at a time lie on disk. then is
    applied to the rows of each share before they are written: what needs a summary only need not keep the array.
    """
    spark, held = reads.sparkSession, STORES[store](reads)
    total = held.reads().agg(F.coalesce(F.sum(F.length("seq") + 1), F.lit(0))).first()[0]
    shares = shares_of(total * (2 if emit == "suffix" else 1), fetches=True)  # all text travels
    in_blocks = emit == "ref" and not held.everywhere() and alphabet.byte_ranks() is not None
    if in_blocks:
        held = held.kept()
        # bytes are coded less densely than few symbols, and whole reads weigh more than tails
        weight = 3 if whole_reads or not alphabet.whole_symbols else 1
        shares = min(shares_of(total * weight, fetches=True), MOST_SHARES * weight)
    in_one = emit == "ref" and singleton_rule and not whole_reads
    parts_in_all = shares * max(parts, blocks.parts_of(total // shares)) if in_blocks else parts
    longer = oversize_codes(held.reads(), alphabet, width, parts_in_all, longer_above, layout) if (in_one or in_blocks) and not (int_key or explicit_ranges) else []
    # a range exchange would make all codes twice, once for its sample
    parts = max(parts, blocks.parts_of(total // shares)) if in_blocks and not explicit_ranges else parts
    cuts = read_boundaries(held.reads(), alphabet, width, shares * (1 if longer or explicit_ranges else parts), layout, apart=in_blocks and not (longer or explicit_ranges))
    step = -(-(len(cuts) + 1) // shares)
    edges = [None, *cuts[step - 1 :: step], None]
    skip, out, start = (width if emit != "suffix" and alphabet.whole_symbols else 0), [], 0
    slices = blocks.slices_of(total)
    # made once, and read by every share
    packed = stored(blocks.packed(held.reads(), alphabet, layout, slices, max(16, slices // 8)), "reads-packed") if in_blocks else None
    for low, high in zip(edges, edges[1:]):
        if in_blocks:
            refs = blocks.refs_sampled(packed, alphabet, width, layout, (low, high), parts * per_part) if explicit_ranges else None
        else:
            refs = expand_refs(held.reads(), alphabet, width, layout, int_key, longer=longer or None, span=(low, high))
        inner = sample_boundaries(refs, parts, per_part) if explicit_ranges else None if longer else [c for c in cuts if (low is None or c > low) and (high is None or c < high)]
        if in_blocks:
            inner = pair_boundaries(held.reads(), alphabet, width, longer, (low, high), parts, layout) if inner is None else inner
            rows, placed = _in_blocks(packed, held, alphabet, width, layout, inner, longer or None, (low, high), short_rule, singleton_rule, whole_reads, slices, skip, start)
        elif in_one:
            rows, placed = _in_one_exchange(refs, held, width if short_rule else 0, parts, skip, width, layout, inner, start)
        else:
            rows = placed = _with_text(refs, held, width, skip, short_rule, singleton_rule, whole_reads, emit, layout, inner, start)
        if len(edges) == 2:
            return then(rows)
        start += placed.rows
        with shuffles_dropped(spark):
            out.append(stored(then(rows), "share"))
        discard(placed)
    if in_blocks:
        discard(packed)
    return reduce(DataFrame.unionByName, out)


def _with_text(refs: DataFrame, held, width: int, skip: int, short_rule: bool, singleton_rule: bool, whole_reads: bool, emit: str, layout: RefLayout, cuts: list[int], start: int) -> DataFrame:
    """(pos, ref[, suffix]), positions from start on: text is looked up first and dealt to code ranges along with its references."""
    none = refs.where(F.lit(False)).select("code", "ref")
    if emit == "suffix":
        ambiguous, settled = refs, none
    else:
        full, settled = (refs.where(F.col("slen") >= width), refs.where(F.col("slen") < width).select("code", "ref")) if short_rule else (refs, none)
        ambiguous = full
        if singleton_rule:
            # one aggregation gives both the groups of one, with their reference, and the codes to look up; a hot code is one
            # row a task before the shuffle, and its join is split by AQE
            groups = full.groupBy("code").agg(F.count("*").alias("n"), F.min("ref").alias("ref"))
            settled = settled.unionByName(groups.where("n = 1").select("code", "ref"))
            ambiguous = full.join(groups.where("n > 1").select("code"), "code", "left_semi")
    fetched = fetch_tails(ambiguous, held, layout, skip, whole_reads)
    if whole_reads:
        fetched = fetched.withColumn("tail", _cut(layout, skip)).drop("read")
    rows = settled.select("code", "ref", F.lit(None).cast("string").alias("tail")).unionByName(fetched.select("code", "ref", "tail"))
    ordered = assign_partition(rows, cuts).repartitionById(len(cuts) + 1, F.col("part")).sortWithinPartitions("code", "tail", "ref")
    return _placed(ordered.select("ref", F.col("tail").alias("suffix")) if emit == "suffix" else ordered.select("ref"), start)


def _placed(ordered: DataFrame, start: int) -> DataFrame:
    """with_positions from start on."""
    written = with_positions(ordered, "indexed")
    out = written.withColumn("pos", F.col("pos") + start) if start else written
    out.scratch, out.rows = written.scratch, written.rows
    return out


def oversize_codes(reads: DataFrame, alphabet, width: int, parts: int, limit: int, layout: RefLayout) -> list[int]:
    """Codes whose groups a sample of one suffix a read puts above limit and above a quarter of a range: 4 * parts of them at most."""
    n, total = reads.agg(F.count("*"), F.coalesce(F.sum(F.length("seq") + 1), F.lit(0))).first()
    if total <= limit:
        return []
    least = max(limit, total / parts / 4) * n / total
    seen = sample_reads(reads, alphabet, width, 1, layout).groupBy("code").agg(F.count("*").alias("n")).where(F.col("n") > least)
    return [r["code"] for r in seen.orderBy(F.desc("n"), "code").limit(4 * parts).select("code").collect()]


def _in_one_exchange(refs: DataFrame, held, least: int, parts: int, skip: int, width: int, layout: RefLayout, cuts: list[int] | None, start: int) -> tuple[DataFrame, DataFrame]:
    """(pos, ref), positions from start on, and the table behind it: references are dealt to code ranges once, and groups are told there, where they stand sorted.

    What is settled has its position at once; only groups that need text travel further, to the reads and back to their
    group, which the position of its first row stands for. Groups with longer prefixes are told apart by those, so that they spread over ranges.
    """
    keys = ["code", "more"] if "more" in refs.columns else ["code"]
    full = F.when(F.col("far"), F.col("slen") >= 2 * width).otherwise(F.col("slen") >= width) if "more" in refs.columns else F.col("slen") >= width
    needed = refs.select(*keys, "ref", *([full.alias("full")] if least else []))
    dealt = needed.repartitionByRange(parts, *keys) if cuts is None else assign_partition(needed, cuts).repartitionById(len(cuts) + 1, F.col("part"))
    # sorted by codes first: a part's number is the same in all its rows, and would leave the sort nothing to go by
    placed = _placed(mark_groups(dealt.sortWithinPartitions(*keys, "ref"), keys, "full" if least else None), start)
    tails = fetch_tails(placed.where("back IS NOT NULL").select("ref", (F.col("pos") - F.col("back")).alias("first")), held, layout, skip)
    moved = F.col("first") + F.row_number().over(Window.partitionBy("first").orderBy("tail", "ref")) - 1
    return placed.where("back IS NULL").select("ref", "pos").unionByName(tails.select("ref", moved.alias("pos"))), placed


def _in_blocks(packed: DataFrame, held, alphabet, width: int, layout: RefLayout, cuts: list, longer: list[int] | None, span: tuple[int | None, int | None], short_rule: bool, singleton_rule: bool, whole_reads: bool, slices: int, skip: int, start: int) -> tuple[DataFrame, DataFrame]:
    """(pos, ref), positions from start on, and the table behind it: as _in_one_exchange, with references and what follows them in blocks.

    Groups too large to be ordered as arrays are looked up and sorted row by row."""
    placed, starts, kinds = blocks.place(packed, alphabet, width, layout, cuts, longer, span, short_rule, singleton_rule, slices)
    starts = {part: start + n for part, n in starts.items()}
    rows = blocks.positions_of(placed, blocks.SETTLED, starts).select("pos", "ref")
    if blocks.SHARED in kinds:
        rows = rows.unionByName(blocks.shared_positions(placed, packed, alphabet, width, layout, starts, whole_reads))
    if blocks.VAST in kinds:
        tails = fetch_tails(blocks.positions_of(placed, blocks.VAST, starts, "first"), held, layout, skip, whole_reads)
        tails = tails.withColumn("tail", _cut(layout, skip)) if whole_reads else tails
        moved = F.col("first") + F.row_number().over(Window.partitionBy("first").orderBy("tail", "ref")) - 1
        rows = rows.unionByName(tails.select("ref", moved.alias("pos")))
    return rows, placed


def _cut(layout: RefLayout, skip: int):
    """What a whole read has of a suffix behind its first skip symbols."""
    return F.substring(F.col("read"), layout.offset(F.col("ref")).cast("int") + 1 + skip, F.length("read"))


def refined_suffix_array(reads: DataFrame, alphabet=DNA, width: int = 23, parts: int = 32, layout: RefLayout = RefLayout()) -> DataFrame:
    """(pos, ref) by lengthening prefixes only where groups share them; eight bytes a round and reference, never text."""
    paths, _ = refine_until_unique(reads, alphabet, width, layout)
    return with_positions(paths.repartitionByRange(parts, "path", "ref").sortWithinPartitions("path", "ref").select("ref"), "refined")


def suffix_array_in_passes(reads: DataFrame, boundaries: list[int], alphabet=DNA, width: int = 23, parts: int = 32, layout: RefLayout = RefLayout()) -> list[DataFrame]:
    """One (ref, code) ordered frame for each code range, low to high: each pass shuffles only the references of its range."""
    edges = [None, *boundaries, None]
    out = []
    for low, high in zip(edges, edges[1:]):
        refs = expand_refs(reads, alphabet, width, layout)
        if low is not None:
            refs = refs.where(F.col("code") > low)
        if high is not None:
            refs = refs.where(F.col("code") <= high)
        tails = fetch_tails(refs, STORES["shuffle"](reads), layout, width if alphabet.whole_symbols else 0)
        out.append(tails.repartitionByRange(parts, "code", "tail", "ref").sortWithinPartitions("code", "tail", "ref").select("code", "ref"))
    return out
