"""Expansion of reads into suffixes or into references."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.alphabet import max_prefix_width
from ..functions.refs import RefLayout
from ..scratch import stored


#: Suffixes that are dealt out in one go; more are taken in shares, so that shuffles of one share at a time lie on disk.
SHARE_SUFFIXES = 200_000_000
#: The same where text of references is fetched or sorted, which takes several times the disk.
FETCH_SUFFIXES = 64_000_000
#: The most shares of references that are made from packed reads: each goes over all reads, so that more would grow with the square of the input.
MOST_SHARES = 16
#: Bytes of reads that are coded at once.
_PIECE = 1 << 18


def in_share(head: Column, share: tuple[int, int]) -> Column:
    """Whether a suffix with this head is in the i-th of n shares."""
    return F.pmod(F.xxhash64(head), F.lit(share[1])) == share[0]


def shares_of(total: int, fetches: bool = False) -> int:
    """How many shares so many suffixes are taken in."""
    return max(1, -(-total // (min(SHARE_SUFFIXES, FETCH_SUFFIXES) if fetches else SHARE_SUFFIXES)))


def by_shares(total: int, make: Callable[[tuple[int, int] | None], DataFrame], label: str, fetches: bool = False) -> DataFrame:
    """make(None), or the rows of all shares of total suffixes, each written before the next begins."""
    n = shares_of(total, fetches)
    if n < 2:
        return make(None)
    parts = [stored(make((i, n)), label) for i in range(n)]
    return reduce(DataFrame.unionByName, parts)


def expand_suffixes(reads: DataFrame, layout: RefLayout = RefLayout(), include_empty: bool = True, max_len: int | None = 1000) -> DataFrame:
    """(ref, suffix): every suffix as text. Null reads, reads that don't fit the layout and those above max_len fail at run time; the last as their suffixes would be quadratic."""
    last = F.length("seq") if include_empty else F.length("seq") - 1
    rows = reads.select("read_id", layout.sound(F.col("read_id"), F.col("seq")).alias("seq"))
    rows = rows.where(F.length("seq") > 0) if not include_empty else rows
    if max_len is not None:
        rows = rows.select("read_id", F.when(F.length("seq") <= max_len, F.col("seq")).otherwise(F.raise_error(F.lit(f"a read is longer than {max_len}: cut it first"))).alias("seq"))
    at = rows.select("read_id", "seq", F.explode(F.sequence(F.lit(0), last)).alias("off"))
    return at.select(layout.pack(F.col("read_id"), F.col("off")).alias("ref"), F.substring(F.col("seq"), F.col("off") + 1, F.length("seq")).alias("suffix"))


def expand_refs(reads: DataFrame, alphabet, width: int, layout: RefLayout = RefLayout(), int_key: bool = False, include_empty: bool = True, longer: list[int] | None = None, share: tuple[int, int] | None = None, span: tuple[int | None, int | None] = (None, None)) -> DataFrame:
    """(code, ref, slen): code of each suffix's first width symbols; slen = units of it, width at most. The text goes no further.

    Null reads, reads that don't fit the layout and symbols outside the alphabet fail at run time. With longer, suffixes with
    one of these codes get a prefix of twice the width: more is the code of its second half (0 for others), and slen counts both.
    With share (i, n), only suffixes of the i-th of n shares, dealt by a hash of their first symbols: equal codes share one.
    With span (low, high), only codes above low and up to high.
    """
    alphabet.fits(width, int_key)
    rows = reads.select("read_id", layout.sound(F.col("read_id"), alphabet.sound(F.col("seq"))).alias("seq"))
    rows = rows if include_empty else rows.where(F.length("seq") > 0)
    kind = "int" if int_key else "long"
    if alphabet.byte_ranks() is not None:
        run = _coder(alphabet, width, layout.stride, int_key, include_empty, longer, share, span)
        return rows.select(F.col("read_id").cast("long"), F.col("seq").alias("text")).mapInArrow(run, f"code {kind}, ref long, slen int" + (", more long, far boolean" if longer is not None else ""))
    last = F.length("seq") if include_empty else F.length("seq") - 1
    at = rows.select("read_id", "seq", F.explode(F.sequence(F.lit(0), last)).alias("off"))
    # a unit is a symbol, and twice the width in symbols holds both halves
    head = at.select("read_id", "off", F.substring(F.col("seq"), F.col("off") + 1, F.lit(2 * width)).alias("head"))
    halves = head.select("read_id", "off", alphabet.window(F.col("head"), 0, width).alias("head"), alphabet.window(F.col("head"), width, width).alias("next"))
    halves = halves if share is None else halves.where(in_share(F.col("head"), share))
    coded = halves.withColumn("code", alphabet.encode(F.col("head"), width, int_key))
    low, high = span
    coded = coded if low is None else coded.where(F.col("code") > low)
    coded = coded if high is None else coded.where(F.col("code") <= high)
    ref = layout.pack(F.col("read_id"), F.col("off")).alias("ref")
    if longer is None:
        return coded.select("code", ref, alphabet.units(F.col("head")).alias("slen"))
    far = F.col("code").isin(longer) if longer else F.lit(False)
    more = F.when(far, alphabet.encode(F.col("next"), width)).otherwise(F.lit(0).cast("long"))
    slen = F.when(far, alphabet.units(F.col("head")) + alphabet.units(F.col("next"))).otherwise(alphabet.units(F.col("head")))
    return coded.select("code", ref, slen.alias("slen"), more.alias("more"), far.alias("far"))


def _windows(ranks: np.ndarray, base: int, width: int) -> np.ndarray:
    """The width ranks from each place on as one number, from numbers of 1, 2, 4 ... ranks; behind the last stand zeros."""

    def ahead(x: np.ndarray, k: int) -> np.ndarray:
        out = np.zeros_like(x)
        out[: max(0, len(x) - k)] = x[k:]
        return out

    out, have, power, held = None, 0, ranks, 1
    while True:
        if width & held:
            out = power if out is None else out * base**held + ahead(power, have)
            have += held
        if 2 * held > width:
            return out
        power, held = power * base**held + ahead(power, held), 2 * held


def _coder(alphabet, width: int, stride: int, int_key: bool, include_empty: bool, longer: list[int] | None, share: tuple[int, int] | None, span: tuple[int | None, int | None], clip: bool = True, check: bool = False):
    """expand_refs over Arrow batches of (read_id, text), where a unit is a byte. Without clip slen is all that is left of the read; check refuses symbols without a rank."""
    ranks, base, symbols_are_bytes, (low, high) = alphabet.byte_ranks(), alphabet.base, alphabet.whole_symbols, span
    reach, codes_of = (width if longer is None else 2 * width), (None if longer is None else np.array(sorted(longer), np.int64))
    # where only some codes are wanted, a few symbols rule most suffixes out before their codes are made
    some = share is not None or low is not None or high is not None
    short = min(width, 8, max_prefix_width(base, 32)) if some else width
    ranks = ranks.astype(np.int32) if some else ranks

    def piece(ids: np.ndarray, raw: np.ndarray, sizes: np.ndarray) -> pa.RecordBatch:
        n = len(ids)
        begin = np.cumsum(sizes) - sizes + np.arange(n) * reach  # each read is followed by zeros, so that no window meets the next
        read = np.repeat(np.arange(n), sizes)
        at = np.arange(len(raw)) + read * reach
        flat = np.zeros(len(raw) + n * reach, ranks.dtype)
        own = ranks[raw]
        if check and not own.all():
            raise ValueError("a read holds NUL or symbols beside the alphabet")
        flat[at] = own
        heads = _windows(flat, base, short)

        def code_at(places: np.ndarray) -> np.ndarray:
            out = 0
            for done in range(0, width, short):
                left = min(short, width - done)
                out = out * base**left + heads[places + done].astype(np.int64) // base ** (short - left)
            return out

        off = None
        if not symbols_are_bytes:
            first = (raw & 0xC0) != 0x80
            at, read = at[first], read[first]
            symbols = np.bincount(read, minlength=n)
            off = np.arange(len(at)) - np.repeat(np.cumsum(symbols) - symbols, symbols)
        if include_empty:
            at, read = np.concatenate([at, begin + sizes]), np.concatenate([read, np.arange(n)])
            off = None if off is None else np.concatenate([off, symbols])
        if some:
            head, kept = heads[at], np.ones(len(at), bool)
            if low is not None:
                kept &= head >= low // base ** (width - short)
            if high is not None:
                kept &= head <= high // base ** (width - short)
            if share is not None:
                kept &= (head.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(33)) % np.uint64(share[1]) == share[0]
            kept = np.flatnonzero(kept)
            own = code_at(at[kept])
            exact = (own > low if low is not None else True) & (own <= high if high is not None else True)
            kept, own = (kept, own) if exact is True else (kept[exact], own[exact])
            at, read, off = at[kept], read[kept], None if off is None else off[kept]
        else:
            own = heads[at]
        off = at - begin[read] if off is None else off
        left = (begin + sizes)[read] - at
        names, columns = ["code", "ref", "slen"], [own.astype(np.int32) if int_key else own, ids[read] * stride + off]
        if codes_of is None:
            columns.append((np.minimum(left, width) if clip else left).astype(np.int32))
        else:
            far = np.isin(own, codes_of)
            names += ["more", "far"]
            more = np.zeros(len(at), np.int64)
            more[far] = code_at(at[far] + width)
            columns += [np.minimum(left, np.where(far, 2 * width, width)).astype(np.int32), more, far]
        return pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=names)

    def run(batches):
        for batch in batches:
            ids, text = batch.column(0).to_numpy(), batch.column(1).cast(pa.large_binary())
            if not len(ids):
                continue
            _, edges, data = text.buffers()
            edges = np.frombuffer(edges, np.int64)[text.offset : text.offset + len(ids) + 1]
            data = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
            first = 0
            while first < len(ids):
                last = max(first + 1, int(np.searchsorted(edges, edges[first] + _PIECE, side="right")) - 1)
                yield piece(ids[first:last], data[edges[first] : edges[last]], np.diff(edges[first : last + 1]))
                first = last

    return run


def self_expansion(reads: DataFrame) -> DataFrame:
    """(reads, raw_bytes, suffix_bytes): suffixes weigh (1 + length) / 2 times their read."""
    n = F.length("seq").cast("long")
    return reads.agg(F.count("*").alias("reads"), F.coalesce(F.sum(n), F.lit(0)).alias("raw_bytes"), F.coalesce(F.sum((n * (n + 1) / 2).cast("long")), F.lit(0)).alias("suffix_bytes"))
