"""References in blocks: arrays of codes and references travel as bytes, a row for each block, and are sorted as arrays.

A block is (part, n, body): body holds n values of each column, one column after the other.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.alphabet import Bytes, max_prefix_width
from ..functions.refs import RefLayout
from ..scratch import stored
from .partitioning import INNER, MULTIPLIER, OUTER
from .suffixes import _coder

#: Suffixes gathered before they are dealt out, and those that a part is meant to hold.
BLOCK, PART = 1 << 20, 1 << 19
#: Groups above so many are not ordered as arrays; parts of one code alone pass in pieces of as many.
GROUP = 1 << 21
#: Bytes of reads among which references are looked up at once.
SLICE = 2 << 20
_ROWS = 1 << 16
#: References whose text is looked up in one go.
_LOOKED_UP = 1 << 17


def parts_of(total: int) -> int:
    """How many parts so many suffixes are dealt to."""
    return max(8, -(-total // PART))


def _body(*arrays: np.ndarray) -> bytes:
    return b"".join(np.ascontiguousarray(a).tobytes() for a in arrays)


def _arrays(body, n: int, kinds: tuple[str, ...]) -> list[np.ndarray]:
    out, at = [], 0
    for kind in kinds:
        out.append(np.frombuffer(body, kind, n, at))
        at += n * np.dtype(kind).itemsize
    return out


def _squeezed(body: bytes) -> bytes:
    """Neighbours in a block have like prefixes, and often tails: far more is saved than where a shuffle compresses."""
    return len(body).to_bytes(8, "little") + pa.compress(body, codec="zstd", asbytes=True)


def _unsqueezed(body: pa.Buffer) -> pa.Buffer:
    return pa.decompress(body.slice(8), int.from_bytes(body.slice(0, 8).to_pybytes(), "little"), codec="zstd")


def _blocks(batches) -> Iterator[tuple]:
    """The rows of batches, with their bodies where they lie."""
    for batch in batches:
        columns = [c.to_pylist() for c in batch.columns[:-1]]
        for i in range(batch.num_rows):
            yield *(c[i] for c in columns), batch.columns[-1][i].as_buffer()


def _rows(names: list[str], kinds: list, *columns: list) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds)], names=names)


def few_of(base: int) -> int:
    """Of how many symbols packed reads are coded in one go: twice those that fit a byte."""
    small = 1
    while base ** (small + 1) <= 256:
        small += 1
    return 2 * small


def packed(reads: DataFrame, alphabet, layout: RefLayout, slices: int, files: int) -> DataFrame:
    """(slice, n, body): reads by number modulo slices, a row for each slice, for place() and shared_positions(), which would make codes of single rows share by share.

    body has the numbers in ascending order, the sizes in units, and the ranks of all units, each read followed by zeros enough for what few_of() codes in one go.
    Null reads, reads that don't fit the layout and symbols without a rank fail at run time.
    """
    ranks, pad = alphabet.byte_ranks().astype(np.uint8), few_of(alphabet.base)

    def run(batches):
        rows = pa.Table.from_batches(list(batches)) if (batches := [b for b in batches if b.num_rows]) else None
        if rows is None:
            return
        part, ids = rows.column(0).to_numpy(), rows.column(1).to_numpy()
        order = np.lexsort((ids, part))
        part, ids = part[order], ids[order]
        text = rows.column(2).cast(pa.large_binary()).combine_chunks()
        text = pa.concat_arrays(text.chunks) if isinstance(text, pa.ChunkedArray) else text
        del rows
        for first, last in _runs_of(part):
            own = text.take(pa.array(order[first:last]))
            _, edges, data = own.buffers()
            sizes = np.diff(np.frombuffer(edges, np.int64)[own.offset : own.offset + last - first + 1])
            raw = np.frombuffer(data, np.uint8, int(sizes.sum())) if data is not None else np.zeros(0, np.uint8)
            flat, coded = np.zeros(len(raw) + (last - first) * pad, np.uint8), ranks[raw]
            if not coded.all():
                raise ValueError("a read holds NUL or symbols beside the alphabet")
            flat[np.arange(len(raw)) + np.repeat(np.arange(last - first) * pad, sizes)] = coded
            yield _rows(["slice", "n", "body"], [pa.int32(), pa.int32(), pa.binary()], [int(part[first])], [last - first], [_body(ids[first:last], sizes.astype(np.int32), flat)])

    text = layout.sound(F.col("read_id"), F.col("seq")).alias("text")
    rows = reads.select(F.pmod(F.col("read_id").cast("long"), F.lit(slices)).cast("int").alias("slice"), F.col("read_id").cast("long"), text)
    return rows.repartitionById(files, F.pmod("slice", F.lit(files))).mapInArrow(run, "slice int, n int, body binary")


def _runs_of(values: np.ndarray) -> list[tuple[int, int]]:
    """Where runs of equal values begin and end."""
    cuts = (np.flatnonzero(values[1:] != values[:-1]) + 1).tolist()
    return list(zip([0, *cuts], [*cuts, len(values)])) if len(values) else []


class PackedReads:
    """A row of packed(): codes of any width from any place on, made where they are wanted from numbers of a few symbols."""

    def __init__(self, n: int, body, alphabet):
        self.base, self.few = alphabet.base, few_of(alphabet.base)
        self.ids, sizes = _arrays(body, n, ("i8", "i4"))
        flat = np.frombuffer(body, np.uint8, offset=12 * n)
        self.begin = np.cumsum(sizes + self.few, dtype=np.int64) - sizes - self.few
        self.end = self.begin + sizes
        ahead = lambda x, k: np.concatenate([x[k:], np.zeros(min(k, len(x)), x.dtype)])
        near, small = flat, self.few // 2
        for i in range(1, small):
            near = near * np.uint8(self.base) + ahead(flat, i)
        self.heads = near.astype(np.uint16) * np.uint16(self.base**small) + ahead(near, small)
        # units that go on a symbol are none of a suffix's beginnings
        goes_on = None if alphabet.whole_symbols else (flat & 0xC0) == 0x80
        self.goes_on = goes_on if goes_on is not None and goes_on.any() else None
        self.before = None if self.goes_on is None else np.cumsum(self.goes_on, dtype=np.int64)

    def codes(self, at: np.ndarray, end: np.ndarray, width: int) -> np.ndarray:
        """Of width units from each place on, up to the end of its read."""
        out = None
        for done in range(0, width, self.few):
            left = min(self.few, width - done)
            head = self.heads[np.minimum(at + done, end)].astype(np.int64)
            head = head if left == self.few else head // self.base ** (self.few - left)
            out = head if out is None else out * self.base**left + head
        return out

    def within(self, width: int, span: tuple[int | None, int | None]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(place, read, code) of the suffixes with a code above low and up to high: a few symbols rule most others out."""
        low, high = span
        far, near = self.base ** max(0, width - self.few), self.base ** max(0, self.few - width)
        kept = np.ones(len(self.heads), bool) if self.goes_on is None else ~self.goes_on
        if low is not None:
            kept &= self.heads >= min(max(0, low // far if far > 1 else (low + 1) * near), 65535)
        if high is not None:
            kept &= self.heads <= min(max(0, high // far if far > 1 else (high + 1) * near - 1), 65535)
        at = np.flatnonzero(kept)
        read = np.searchsorted(self.begin, at, side="right") - 1
        inside = at <= self.end[read]  # not in the zeros behind a read
        if not inside.all():
            at, read = at[inside], read[inside]
        code = self.codes(at, self.end[read], width)
        if low is not None or high is not None:
            exact = np.ones(len(at), bool) if low is None else code > low
            exact = exact if high is None else exact & (code <= high)
            at, read, code = at[exact], read[exact], code[exact]
        return at, read, code

    def offsets(self, at: np.ndarray, read: np.ndarray) -> np.ndarray:
        """How many symbols of its read are before each place."""
        off = at - self.begin[read]
        return off if self.before is None else off - self.before[at] + self.before[self.begin[read]]

    def places(self, read: np.ndarray, off: np.ndarray) -> np.ndarray:
        """Of symbols by their number in their read."""
        if self.before is None:
            return self.begin[read] + off
        symbols = np.flatnonzero(~self.goes_on)
        return symbols[self.begin[read] - self.before[self.begin[read]] + off]


def _dealt(found: Iterator[list[np.ndarray]], part_of: Callable[[list[np.ndarray]], np.ndarray], parts: int) -> Iterator[pa.RecordBatch]:
    """What is found, in blocks of a part each."""
    held, n = [], 0

    def packed(held):
        arrays = [np.concatenate(c) for c in zip(*held)]
        part = part_of(arrays).astype(np.uint16 if parts <= 1 << 16 else np.int64)
        order = np.argsort(part, kind="stable")
        pieces = [(int(part[order[a]]), a, b) for a, b in _runs_of(part[order])]
        arrays = [x[order] for x in arrays]
        return _rows(["part", "n", "body"], [pa.int32(), pa.int32(), pa.binary()], [p for p, _, _ in pieces], [b - a for _, a, b in pieces], [_body(*(x[a:b] for x in arrays)) for _, a, b in pieces])

    for arrays in found:
        held.append(arrays)
        n += len(arrays[0])
        if n >= BLOCK:
            yield packed(held)
            held, n = [], 0
    if n:
        yield packed(held)


def deal(reads: DataFrame, alphabet, width: int, layout: RefLayout, columns: Callable[[pa.RecordBatch], list[np.ndarray]], part_of: Callable[[list[np.ndarray]], np.ndarray], parts: int, share=None) -> DataFrame:
    """Blocks of columns(rows of expand_refs), a part to a partition; with share as there, and failing as there. slen is all that is left of a read."""
    alphabet.fits(width, False)
    run = _coder(alphabet, width, layout.stride, False, True, None, share, (None, None), clip=False, check=True)
    rows = reads.select(F.col("read_id").cast("long"), layout.sound(F.col("read_id"), F.col("seq")).alias("text"))
    return rows.mapInArrow(lambda batches: _dealt(map(columns, run(batches)), part_of, parts), "part int, n int, body binary").repartitionById(parts, F.col("part"))


def refs_sampled(store: DataFrame, alphabet, width: int, layout: RefLayout, span: tuple[int | None, int | None], n: int) -> DataFrame:
    """(code, ref) of suffixes of packed reads within span: of each task the n that come first in the sampling order, so that the first n of all are among them."""

    def run(batches):
        best = [np.empty(0, np.int64)] * 3
        for _, rows, body in _blocks(batches):
            reads = PackedReads(rows, body, alphabet)
            at, read, code = reads.within(width, span)
            ref = reads.ids[read] * layout.stride + reads.offsets(at, read)
            h = ref % INNER * MULTIPLIER % OUTER
            best = [np.concatenate(c) for c in zip(best, (h, ref, code))]
            if len(best[0]) > n:
                first = np.lexsort((best[1], best[0]))[:n]
                best = [c[first] for c in best]
        for i in range(0, len(best[0]), _ROWS):
            yield pa.RecordBatch.from_arrays([pa.array(best[2][i : i + _ROWS]), pa.array(best[1][i : i + _ROWS])], names=["code", "ref"])

    return store.mapInArrow(run, "code long, ref long")


def shared_codes(reads: DataFrame, alphabet, width: int, layout: RefLayout, parts: int, share: tuple[int, int] | None) -> DataFrame:
    """(code, ref, n) of suffixes whose first width symbols others have as well; n is the length of their read in units.

    A code met once is held, with its reference, until it is met again: a code that many share passes as it comes.
    """

    def columns(batch):
        code, ref, left = (batch.column(i).to_numpy() for i in range(3))
        full = left >= width
        code, ref, left = code[full], ref[full], left[full]
        return [code, ref, (ref % layout.stride + left).astype(np.int32)]

    def part_of(arrays):
        return ((arrays[0].astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)) >> np.uint64(32)) % np.uint64(parts)

    def met(batches):
        once, known = [np.empty(0, k) for k in ("i8", "i8", "i4")], np.empty(0, np.int64)
        for arrays in gathered(batches):
            arrays = [np.concatenate(c) for c in zip(once, *arrays)]
            order = np.argsort(arrays[0])
            arrays = [a[order] for a in arrays]
            code = arrays[0]
            same = code[1:] == code[:-1]
            twice = np.concatenate([[False], same]) | np.concatenate([same, [False]])
            if len(known):
                twice |= known[np.minimum(np.searchsorted(known, code), len(known) - 1)] == code
            once, out = [a[~twice] for a in arrays], [a[twice] for a in arrays]
            known = np.union1d(known, out[0])
            for at in range(0, len(out[0]), _ROWS):
                yield pa.RecordBatch.from_arrays([pa.array(a[at : at + _ROWS]) for a in out], names=["code", "ref", "n"])

    def gathered(batches):
        held, n = [], 0
        for _, rows, body in _blocks(batches):
            held.append(_arrays(body, rows, ("i8", "i8", "i4")))
            n += rows
            if n >= 2 * BLOCK:
                yield held
                held, n = [], 0
        if n:
            yield held

    return deal(reads, alphabet, width, layout, columns, part_of, parts, share=share).mapInArrow(met, "code long, ref long, n int")


SETTLED, SHARED, VAST = 0, 1, 2


def slices_of(total: int) -> int:
    """In how many slices reads of so many symbols are looked up."""
    return max(8, -(-total // SLICE))


def apart(cuts: list) -> list[bool]:
    """Whether a part between cuts, whole numbers or pairs of them, holds one value alone."""
    near = lambda a, b: b - a == 1 if not isinstance(a, tuple) else a[0] == b[0] and b[1] - a[1] == 1
    return [False, *(near(a, b) for a, b in zip(cuts, cuts[1:])), False] if cuts else [False]


def place(store: DataFrame, alphabet, width: int, layout: RefLayout, cuts: list, longer: list[int] | None, span: tuple[int | None, int | None], short_rule: bool, singleton_rule: bool, slices: int) -> tuple[DataFrame, dict[int, int], set[int]]:
    """References of packed reads dealt to code ranges in blocks, and sorted there: a stored table, the position at which each part begins, and the kinds that occur.

    The table has (part, kind, key, n, body). SETTLED rows have ref and their place in the part. SHARED ones, whose code others have as well, have
    ref and the place of their group's first, and lie by the slice of reads (key) that holds them; VAST ones are the same of groups above GROUP.
    cuts are codes, or with longer pairs of them. A part that holds one code alone, and more than four times GROUP, passes as it comes.
    """
    kinds = ("i8", "i8", "?") if longer is None else ("i8", "i8", "?", "i8")
    alphabet.fits(width, False)
    low, alone = np.array([c if longer is None else c[0] for c in cuts], np.int64), apart(cuts)
    second, known = np.array([0 if longer is None else c[1] for c in cuts], np.int64), np.array(sorted(longer or ()), np.int64)
    names, types = ["part", "kind", "key", "n", "body"], [pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.binary()]

    def found(batches):
        for _, rows, body in _blocks(batches):
            reads = PackedReads(rows, body, alphabet)
            at, read, code = reads.within(width, span)
            ref, end = reads.ids[read] * layout.stride + reads.offsets(at, read), reads.end[read]
            if longer is None:
                yield [code, ref, end - at >= width]
                continue
            far, more = np.isin(code, known), np.zeros(len(at), np.int64)
            more[far] = reads.codes(at[far] + width, end[far], width)
            yield [code, ref, end - at >= np.where(far, 2 * width, width), more]

    def part_of(arrays):
        part = np.searchsorted(low, arrays[0])
        if longer is not None:
            # the cuts of one code follow each other: only its suffixes are told apart by more
            for first, last in _runs_of(low):
                own = np.flatnonzero(arrays[0] == low[first])
                part[own] = first + np.searchsorted(second[first:last], arrays[3][own])
        return part

    def placed(batches):
        held, n, part, passed = [], 0, None, False
        for part_, rows, body in _blocks(batches):
            assert part in (None, part_), "a partition holds two parts"
            part = part_
            held.append(_arrays(body, rows, kinds))
            n += rows
            if alone[part] and n > (0 if passed else 4 * GROUP) and (not short_rule or held[0][2][0]):
                refs, held, n, passed = np.concatenate([h[1] for h in held]), [], 0, True
                for at in range(0, len(refs), GROUP):
                    own = refs[at : at + GROUP]
                    yield _rows(names, types, [part], [VAST], [0], [len(own)], [_body(own, np.zeros(len(own), np.uint32))])
        if n:
            yield ordered(part, *(np.concatenate(c) for c in zip(*held)))

    def ordered(part, code, ref, full, more=None):
        order = np.argsort(code) if more is None else np.lexsort((more, code))
        code, more = code[order], None if more is None else more[order]
        same = code[1:] == code[:-1]
        same = same if more is None else same & (more[1:] == more[:-1])
        begins = np.concatenate([[True], ~same])
        group = np.cumsum(begins) - 1
        first = np.flatnonzero(begins).astype(np.uint32)
        size = np.diff(np.append(first, len(order)))
        wanted = size[group] > 1 if singleton_rule else np.ones(len(order), bool)
        if short_rule:
            # what ends within the prefix is equal throughout its group
            ends = wanted & ~full[order]
            own = order[ends]
            order[ends] = own[np.lexsort((ref[own], group[ends]))]
            wanted &= ~ends
        ref, first = ref[order], first[group]
        vast = wanted & (size > GROUP)[group]
        shared = np.flatnonzero(wanted & ~vast)
        key = ((ref[shared] // layout.stride) % slices).astype(np.uint16 if slices <= 1 << 16 else np.int64)
        by = np.argsort(key, kind="stable")
        found, begin = np.unique(key[by], return_index=True)
        settled, vast = np.flatnonzero(~wanted), np.flatnonzero(vast)
        out = [(SETTLED, 0, len(settled), _body(ref[settled], settled.astype(np.uint32)))] if len(settled) else []
        for k, a, b in zip(found.tolist(), begin.tolist(), [*begin.tolist()[1:], len(by)]):
            rows = shared[by[a:b]]
            out.append((SHARED, k, b - a, _body(ref[rows], first[rows])))
        out += [(VAST, 0, len(vast), _body(ref[vast], first[vast]))] if len(vast) else []
        return _rows(names, types, [part] * len(out), *zip(*out))

    dealt = store.mapInArrow(lambda batches: _dealt(found(batches), part_of, len(cuts) + 1), "part int, n int, body binary").repartitionById(len(cuts) + 1, F.col("part"))
    out = stored(dealt.mapInArrow(placed, "part int, kind int, key int, n int, body binary"), "placed")
    counts = {(r["part"], r["kind"]): r["n"] for r in out.groupBy("part", "kind").agg(F.sum("n").alias("n")).collect()}
    starts, out.rows = {}, 0
    for part in range(len(cuts) + 1):
        starts[part] = out.rows
        out.rows += sum(counts.get((part, k), 0) for k in (SETTLED, SHARED, VAST))
    return out, starts, {k for _, k in counts}


def positions_of(table: DataFrame, kind: int, starts: dict[int, int], name: str = "pos") -> DataFrame:
    """(ref, name) of the rows of a kind in the table of place(): their place as a position."""

    def run(batches):
        for part, n, body in _blocks(batches):
            ref, at = _arrays(body, n, ("i8", "u4"))
            for i in range(0, n, _ROWS):
                yield pa.RecordBatch.from_arrays([pa.array(ref[i : i + _ROWS]), pa.array(at[i : i + _ROWS].astype(np.int64) + starts[part])], names=["ref", name])

    return table.where(F.col("kind") == kind).select("part", "n", "body").mapInArrow(run, f"ref long, {name} long")


def shared_positions(table: DataFrame, store: DataFrame, alphabet, width: int, layout: RefLayout, starts: dict[int, int], whole: bool = False) -> DataFrame:
    """(ref, pos) of the SHARED rows of the table of place(): what follows the prefix is looked up slice by slice of the packed reads, sent to the parts as
    codes as wide as they fit, and groups are told apart code by code until each holds one row, or equal suffixes, which their references order.

    With whole, the reads themselves travel, and are cut where their group is."""
    base, wide = alphabet.base, max_prefix_width(alphabet.base, 64)
    sent_as = pa.schema([("part", pa.int32()), ("n", pa.int32()), ("body", pa.binary())])
    powers = np.array([base**i for i in range(wide + 1)], np.uint64)

    def fetched(wanted: pa.Table, store: pa.Table) -> pa.Table:
        if not wanted.num_rows:
            return sent_as.empty_table()
        if store.num_rows != 1:
            raise ValueError("a slice of reads is missing, or there twice")
        reads = PackedReads(store.column("n")[0].as_py(), store.column("body")[0].as_buffer(), alphabet)
        counts, parts, bodies = wanted.column("n").to_pylist(), wanted.column("part").to_pylist(), []
        rows = [_arrays(body.as_buffer(), n, ("i8", "u4")) for body, n in zip(wanted.column("body"), counts)]
        held = 0
        for i, n in enumerate(counts):
            held += n
            if held >= _LOOKED_UP or i + 1 == len(counts):
                bodies += looked_up(reads, rows[len(bodies) : i + 1])
                held = 0
        return pa.table([pa.array(parts, pa.int32()), pa.array(counts, pa.int32()), pa.array(bodies, pa.binary())], schema=sent_as)

    def looked_up(reads: PackedReads, rows: list) -> list[bytes]:
        ref, edges = np.concatenate([r for r, _ in rows]), np.cumsum([0, *(len(r) for r, _ in rows)])
        read = np.searchsorted(reads.ids, ref // layout.stride)
        start, end = reads.places(read, ref % layout.stride) + width, reads.end[read]
        first = reads.begin[read] if whole else start
        k = -(-np.maximum(end - first, 0) // wide)
        to = np.cumsum(k)
        behind = np.arange(to[-1]) - np.repeat(to - k, k)
        codes = reads.codes(np.repeat(first, k) + wide * behind, np.repeat(end, k), wide)
        more = [np.stack([start - first, end - first], axis=1).astype(np.int32)] if whole else []
        at = np.append(0, to)
        k = k.astype(np.uint32)
        return [_squeezed(_body(ref[a:b], group, k[a:b], *(m[a:b] for m in more), codes[at[a] : at[b]])) for (_, group), a, b in zip(rows, edges.tolist(), edges[1:].tolist())]

    def cut(k: np.ndarray, spans: np.ndarray, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """k and codes of what whole reads have from the first of their spans on: every code is made of two neighbours."""
        start, size = spans[:, 0].astype(np.int64), spans[:, 1].astype(np.int64)
        begin = np.cumsum(k) - k
        own = -(-np.maximum(size - start, 0) // wide)
        at = np.repeat(begin + start // wide, own) + np.arange(own.sum()) - np.repeat(np.cumsum(own) - own, own)
        off, codes = np.repeat(start % wide, own), np.append(codes, 0).view(np.uint64)
        follows = np.where(at + 1 < np.repeat(begin + k, own), codes[at + 1], np.uint64(0))
        return own, (codes[at] % powers[wide - off] * powers[off] + follows // powers[wide - off]).view(np.int64)

    def ordered(batches):
        held, part = [], None
        for part_, n, body in _blocks(batches):
            assert part in (None, part_), "a partition holds two parts"
            part, body = part_, _unsqueezed(body)
            ref, group, k = _arrays(body, n, ("i8", "u4", "u4"))
            if whole:
                spans = np.frombuffer(body, np.int32, 2 * n, n * 16).reshape(n, 2)
                held.append((ref, group, *cut(k.astype(np.int64), spans, np.frombuffer(body, np.int64, int(k.sum()), n * 24))))
            else:
                held.append((ref, group, k, np.frombuffer(body, np.int64, int(k.sum()), n * 16)))
        if not held:
            return
        ref, group, k, codes = (np.concatenate(c) for c in zip(*held))
        held.clear()
        group, k, begin = group.astype(np.int64), k.astype(np.int64), np.cumsum(k, dtype=np.int64) - k
        place, live, step = np.empty(len(ref), np.int64), np.arange(len(ref)), 0
        while len(live):
            more = k[live] > step
            key = np.zeros(len(live), np.int64)  # below all codes: these suffixes have ended
            key[more] = codes[begin[live[more]] + step]
            by = np.lexsort((key, group[live]))
            live, key, own = live[by], key[by], group[live[by]]
            turns = np.concatenate([[True], own[1:] != own[:-1]])
            at = np.arange(len(live))
            slot = own + at - np.maximum.accumulate(np.where(turns, at, 0))
            begins = turns | np.concatenate([[True], key[1:] != key[:-1]])
            own = slot[np.maximum.accumulate(np.where(begins, at, 0))]
            done = begins & np.append(begins[1:], True)
            equal = ~done & (key == 0)
            by = np.flatnonzero(equal)
            done[by] = True
            live[by] = live[by][np.lexsort((ref[live[by]], own[by]))]
            place[live[done]] = slot[done]
            group[live] = own
            live, step = live[~done], step + 1
        place += starts[part]
        for i in range(0, len(ref), _ROWS):
            yield pa.RecordBatch.from_arrays([pa.array(ref[i : i + _ROWS]), pa.array(place[i : i + _ROWS])], names=["ref", "pos"])

    wanted = table.where(F.col("kind") == SHARED).select(F.col("key").alias("slice"), "part", "n", "body")
    sent = wanted.groupBy("slice").cogroup(store.groupBy("slice")).applyInArrow(fetched, "part int, n int, body binary")
    return sent.repartitionById(len(starts), F.col("part")).mapInArrow(ordered, "ref long, pos long")


def grams(store: DataFrame, width: int, k: int, at_least: int, cuts: list[int], span: tuple[int | None, int | None]) -> DataFrame:
    """(gram, n) of the grams of k symbols that occur at_least times, of packed reads as bytes, of those whose first width bytes are coded within span.

    Grams travel as codes of seven bytes, dealt by cuts of the first; equal ones meet as a part is sorted by a mix of their codes. Rows that share a mix are compared
    code by code, and where any differ they are sorted by their codes, so that a mix that two grams share counts neither wrong. What is counted is held, a row a gram, while
    the rest of a large part passes."""
    low = np.array(cuts, np.int64)

    def found(batches):
        for _, n, body in _blocks(batches):
            reads = PackedReads(n, body, Bytes)
            at, read, code = reads.within(width, span)
            off = reads.offsets(at, read)
            symbols = reads.end - reads.begin
            if reads.before is not None:
                symbols = symbols - reads.before[reads.end] + reads.before[reads.begin]
            whole = np.flatnonzero(symbols[read] - off >= k)
            at, read, code, off = at[whole], read[whole], code[whole], off[whole]
            end = at + k if reads.before is None else np.append(np.flatnonzero(~reads.goes_on), len(reads.heads))
            end = end if reads.before is None else end[at - reads.before[at] + k]
            # grams of as many codes go together
            words = -(-(end - at) // 7)
            for m in np.unique(words).tolist():
                own = np.flatnonzero(words == m)
                rows = np.stack([cut_at(reads, at[own] + 7 * i, reads.end[read[own]], end[own]) for i in range(m)], axis=1)
                yield code[own], rows

    def cut_at(reads, at, stop, end):
        """Codes of seven bytes from each place on, without what is behind the end of a gram."""
        over = np.maximum(at + 7 - end, 0)
        code = reads.codes(at, stop, 7)
        return code if not over.any() else code >> 8 * over << 8 * over

    def dealt(batches):
        held, n = {}, 0
        for code, rows in found(batches):
            held.setdefault(rows.shape[1], []).append((np.searchsorted(low, code).astype(np.int32), rows))
            n += len(code)
            if n >= BLOCK >> 1:
                yield from sent(held)
                held, n = {}, 0
        yield from sent(held)

    def sent(held):
        for m, of in held.items():
            part, rows = np.concatenate([p for p, _ in of]), np.concatenate([r for _, r in of])
            order = np.argsort(part.astype(np.uint16) if len(low) < 1 << 16 else part, kind="stable")
            part, rows = part[order], rows[order]
            pieces = _runs_of(part)
            yield _rows(["part", "m", "n", "body"], [pa.int32(), pa.int32(), pa.int32(), pa.binary()], [int(part[a]) for a, _ in pieces], [m] * len(pieces), [b - a for a, b in pieces], [_body(rows[a:b]) for a, b in pieces])

    def counted(batches):
        held, n, sums = {}, 0, {}
        for _, m, rows, body in _blocks(batches):
            held.setdefault(m, []).append((np.frombuffer(body, np.int64, rows * m).reshape(rows, m), np.ones(rows, np.int64)))
            n += rows
            if n >= 2 * BLOCK:
                held, n = {m: [summed(of)] for m, of in held.items()}, 0
        for m, of in held.items():
            rows, times = summed(of)
            rows, times = rows[times >= at_least], times[times >= at_least]
            for i in range(0, len(rows), _ROWS):
                own = np.ascontiguousarray(rows[i : i + _ROWS].astype(">i8")).view(np.uint8).reshape(-1, m, 8)[:, :, 1:].reshape(-1, 7 * m)
                sizes = np.count_nonzero(own, axis=1)
                seq = pa.StringArray.from_buffers(len(own), pa.py_buffer(np.append(0, np.cumsum(sizes)).astype(np.int32)), pa.py_buffer(own[own > 0].tobytes()))
                yield pa.RecordBatch.from_arrays([seq, pa.array(times[i : i + _ROWS])], names=["gram", "n"])

    def summed(of):
        """Rows without repeats, and how often each occurs."""
        rows, times = np.concatenate([r for r, _ in of]), np.concatenate([t for _, t in of])
        of.clear()
        mix = np.zeros(len(rows), np.uint64)
        for i in range(rows.shape[1]):
            mix = (mix ^ rows[:, i].view(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
            mix ^= mix >> np.uint64(29)
        order = np.argsort(mix)
        mix, rows, times = mix[order], rows[order], times[order]
        same, equal = mix[1:] == mix[:-1], (rows[1:] == rows[:-1]).all(axis=1)
        if (same & ~equal).any():
            order = np.lexsort(rows.T[::-1])
            rows, times = rows[order], times[order]
            equal = (rows[1:] == rows[:-1]).all(axis=1)
        begin = np.flatnonzero(np.append(True, ~equal)) if len(rows) else np.empty(0, np.int64)
        return rows[begin], np.add.reduceat(times, begin) if len(begin) else times

    parts = len(cuts) + 1
    sent_as = store.mapInArrow(dealt, "part int, m int, n int, body binary").repartitionById(parts, F.col("part"))
    return sent_as.mapInArrow(counted, "gram string, n long")
