"""Mixture-controlled packing by deficit round-robin over source queues.

Each source is a queue of tokens in a fixed order. A round has a number of windows; in a round every queue is served
its quantum, its target share of the round's tokens. Window by window each queue earns its share, what it has
earned and not been served is its deficit, and the window's tokens go out so that each queue stays within a token or so of its
due. Deficits carry from window to window, and are zero again at the end of a round, so the
state at any window follows from its number alone: tasks begin anywhere in the stream with the deficits that their first
window inherits. When a queue runs dry, the others share by their targets from the next window on, which starts a new
phase; there are at most as many phases as queues.

Two narrow passes do the work: one encodes and stores ids with running counts, one cuts and places pieces. Between them only
token counts for each task and queue are summed.

Defined results: a null or empty text is the end id alone; a null source is a queue of its own; repeated rows are packed
each; queues beyond max_queues (smallest last) share one queue; other columns are not read; an empty table gives an empty one.
"""

from __future__ import annotations

import json
import zlib
from bisect import bisect_right
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import tiktoken
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from .common import maybe_broadcast, slices, stored

WINDOW = 2048
#: Windows in a round: the finer it is, the closer quanta come to small target shares.
ROUND = 32


@dataclass
class Phase:
    """Windows first to first + windows - 1, served in rounds of one pattern."""

    first: int
    windows: int
    served: np.ndarray  # tokens of each queue served before this phase
    pattern: np.ndarray  # [w, q]: tokens of queue q served in a round before its window w; one row more than windows


def quanta(shares: np.ndarray, tokens: int) -> np.ndarray:
    """Whole numbers in proportion to shares that add up to tokens (largest remainders); at least 1 for a positive share."""
    due = shares / shares.sum() * tokens
    out = np.maximum(np.floor(due).astype(np.int64), (shares > 0).astype(np.int64))
    order = np.argsort(-(due - np.floor(due)), kind="stable")
    order = order[shares[order] > 0]
    i = 0
    while (left := tokens - int(out.sum())) != 0:
        q = order[i % len(order)]
        if left > 0:
            out[q] += 1
        elif out[q] > 1:
            out[q] -= 1
        i += 1
    return out


def round_pattern(quantum: np.ndarray, windows: int = ROUND, window: int = WINDOW) -> np.ndarray:
    """Served tokens before each window of a round, by deficits in units of 1 / windows of a token."""
    served = np.zeros((windows + 1, len(quantum)), np.int64)
    deficit = np.zeros(len(quantum), np.int64)
    for w in range(windows):
        deficit += quantum
        room = quantum - served[w]
        give = np.clip(deficit // windows, 0, room)
        while (left := window - int(give.sum())) != 0:
            # a token more where most is due, or one less where least is
            order = np.argsort((give * windows - deficit) * (1 if left > 0 else -1), kind="stable")
            order = order[(give < room)[order] if left > 0 else (give > 0)[order]][: abs(left)]
            give[order] += 1 if left > 0 else -1
        served[w + 1] = served[w] + give
        deficit -= give * windows
    return served


def schedule(totals: np.ndarray, shares: np.ndarray, window: int = WINDOW, windows: int = ROUND) -> tuple[list[Phase], np.ndarray]:
    """Phases that use up totals, and the tokens of each queue left for the last, partly filled window."""
    phases, served, at = [], np.zeros(len(totals), np.int64), 0
    while True:
        left = totals - served
        if int(left.sum()) < window:
            return phases, left
        pattern = round_pattern(quanta(np.where(left > 0, shares, 0.0), window * windows), windows, window)
        quantum = pattern[-1]
        rounds = int((left[quantum > 0] // quantum[quantum > 0]).min())
        after = rounds * quantum + pattern[:-1]
        full = rounds * windows + int((after[1:] <= left).all(axis=1).sum())
        if full:
            phases.append(Phase(at, full, served.copy(), pattern))
            served = served + (full // windows) * quantum + pattern[full % windows]
            at += full
            left = totals - served
            if int(left.sum()) < window:
                return phases, left
        # the next window would overdraw a queue: it takes what there is, and the rest by what is left of the others
        give = np.minimum(pattern[full % windows + 1] - pattern[full % windows], left)
        while (short := window - int(give.sum())) > 0:
            spare = left - give
            weight = np.where(spare > 0, shares, 0.0)
            give += np.minimum(quanta(weight, short) if short >= int((weight > 0).sum()) else _first(weight, short), spare)
        one = np.vstack([np.zeros_like(give), give])
        phases.append(Phase(at, 1, served.copy(), one))
        served = served + give
        at += 1


def _first(weight: np.ndarray, n: int) -> np.ndarray:
    out = np.zeros(len(weight), np.int64)
    out[np.argsort(-weight, kind="stable")[:n]] = 1
    return out


class Placer:
    """Cuts a run of a queue's tokens at window edges and says where each piece lies."""

    def __init__(self, phases: list[Phase], rest: np.ndarray, window: int = WINDOW):
        self.window, self.phases = window, phases
        self.ends = [p.served + (p.windows // n) * p.pattern[-1] + p.pattern[p.windows % n] for p in phases for n in [len(p.pattern) - 1]]
        # of each phase, by queue: tokens served before each window of a round; and by window: where each queue's slice begins
        self.columns = [p.pattern.T.tolist() for p in phases]
        self.slices = [(np.cumsum(np.diff(p.pattern, axis=0), axis=1) - np.diff(p.pattern, axis=0)).tolist() for p in phases]
        self.starts = [p.served.tolist() for p in phases]
        self.stops = [e.tolist() for e in self.ends]
        self.full = phases[-1].first + phases[-1].windows if phases else 0
        self.begin = (self.ends[-1] if phases else np.zeros(len(rest), np.int64)), np.concatenate([[0], np.cumsum(rest)])
        # the tail is laid out in sequences whose lengths are powers of two, which need no padding
        self.tail, at = [], 0
        left = int(rest.sum())
        while left:
            n = 1 << left.bit_length() - 1
            self.tail.append((at, n))
            at, left = at + n, left - n

    def pieces(self, queue: int, start: int, length: int) -> list[tuple[int, int, int, int]]:
        """(start in the run, length, sequence, offset there) of tokens start.. of a queue."""
        out, at, end = [], start, start + length
        for k, phase in enumerate(self.phases):
            if at >= end:
                break
            if at >= self.stops[k][queue]:
                continue
            column, slices, first = self.columns[k][queue], self.slices[k], self.starts[k][queue]
            n, quantum = len(column) - 1, column[-1]
            r, inside = divmod(at - first, quantum)
            w = r * n + bisect_right(column, inside) - 1
            while at < end and w < phase.windows:
                before, j = first + (w // n) * quantum, w % n
                low, high = before + column[j], before + column[j + 1]
                if high > at:
                    stop = min(high, end)
                    out.append((at - start, stop - at, phase.first + w, slices[j][queue] + at - low))
                    at = stop
                w += 1
        if at < end:
            base, cumulative = self.begin
            spot = int(cumulative[queue]) + at - int(base[queue])
            for i, (first, n) in enumerate(self.tail):
                if at < end and first <= spot < first + n:
                    take = min(end - at, first + n - spot)
                    out.append((at - start, take, self.full + i, spot - first))
                    at, spot = at + take, spot + take
        return out


def byte_level_bytes() -> dict[str, int]:
    """The byte that each character of a byte-level vocabulary stands for: printable Latin-1 stands for itself, and
    the other bytes, in order, are written from U+0100 on."""
    own = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in own]
    return {chr(b): b for b in own} | {chr(0x100 + i): b for i, b in enumerate(rest)}


#: Fixed value: the pattern that the tokenizers library splits by where a file asks for its byte-level split.
BYTE_LEVEL_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


def split_pattern(pre_tokenizer: dict | None) -> str | None:
    """The pattern whose matches the file encodes one by one; None where the file splits otherwise."""
    kind = (pre_tokenizer or {}).get("type")
    if kind == "ByteLevel" and not pre_tokenizer.get("add_prefix_space") and pre_tokenizer.get("use_regex", True):
        return BYTE_LEVEL_PATTERN
    steps = pre_tokenizer.get("pretokenizers", []) if kind == "Sequence" else []
    if [x.get("type") for x in steps] == ["Split", "ByteLevel"]:
        first, second = steps
        plain = first.get("behavior") == "Isolated" and not first.get("invert") and not second.get("add_prefix_space") and second.get("use_regex") is False
        return first.get("pattern", {}).get("Regex") if plain else None
    return None


def apart(added: list[dict]) -> bool:
    """Whether added tokens are found in a text by their bare strings, in one way only."""
    names = [t["content"] for t in added]
    flags = any(t.get(k) for t in added for k in ("single_word", "lstrip", "rstrip"))
    return not flags and all(names) and not any(a != b and a in b for a in names for b in names) and len(set(names)) == len(names)


class FileTokenizer:
    """Ids by a tokenizers file as the library gives them without adding special tokens; those that stand in a text keep their ids.

    For byte-level BPE whose merges come in the order of their results' ids, as in files made from rank tables, the rank engine
    of tiktoken gives the same ids at several times the speed; the file's own pattern and added tokens go with it. A file with
    anything else (a normalizer, another split, tokens that strip or contain each other) is left to the library itself.
    """

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as file:
            whole = json.load(file)
        model, added, pattern = whole["model"], whole.get("added_tokens") or [], split_pattern(whole.get("pre_tokenizer"))
        vocabulary, made = model["vocab"], ["".join(m if isinstance(m, list) else m.split(" ")) for m in model.get("merges", [])]
        results = [vocabulary[x] for x in made]
        names = {t["content"] for t in added}
        usual = not any(model.get(k) for k in ("dropout", "unk_token", "continuing_subword_prefix", "end_of_word_suffix", "byte_fallback", "ignore_merges"))
        self.ranked = usual and whole.get("normalizer") is None and pattern is not None and apart(added) and results == sorted(set(results)) and len(results) + 256 >= len(vocabulary.keys() - names)
        if self.ranked:
            to_byte, usual = byte_level_bytes(), {*made}
            ranks = {bytes(map(to_byte.__getitem__, t)): i for t, i in vocabulary.items() if t not in names and (t in usual or len(t) == 1)}
            self.engine = tiktoken.Encoding(path, pat_str=pattern, mergeable_ranks=ranks, special_tokens={t["content"]: t["id"] for t in added})
        else:
            self.engine = Tokenizer.from_file(path)

    def encode(self, text: str) -> bytes:
        """Little-endian unsigned 32-bit ids."""
        if not text:
            return b""
        if self.ranked:
            return self.engine.encode_to_numpy(text, allowed_special="all").astype("<u4", copy=False).tobytes()
        return np.array(self.engine.encode(text, add_special_tokens=False).ids, "<u4").tobytes()


_tokenizers: dict[str, FileTokenizer] = {}


def file_encoder(path: str) -> Callable[[str], bytes]:
    """An encoder to hand to pack(); the file is read once for each worker, and must exist on every executor."""

    def encode(text: str) -> bytes:
        if path not in _tokenizers:
            _tokenizers[path] = FileTokenizer(path)
        return _tokenizers[path].encode(text)

    return encode


def encoded(docs: DataFrame, encode: Callable[[str], bytes], end_id: int, id_col: str, text_col: str, source_col: str) -> DataFrame:
    """(doc_id, source, part, before, n, ids): before counts the tokens of the source in this task ahead of the row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, ahead = TaskContext.get().partitionId(), {}
        end = np.array([end_id], "<u4").tobytes()
        for batch in slices(batches):
            before, lengths, all_ids = [], [], []
            for source, text in zip(batch.column(1).to_pylist(), batch.column(2)):
                ids = encode(text.as_py() or "") + end
                before.append(ahead.get(source, 0))
                lengths.append(len(ids) // 4)
                ahead[source] = before[-1] + lengths[-1]
                all_ids.append(ids)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([part] * batch.num_rows, pa.int64()), pa.array(before, pa.int64()), pa.array(lengths, pa.int64()), pa.array(all_ids, pa.binary())], names=["doc_id", "source", "part", "before", "n", "ids"])

    picked = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(source_col).cast("string").alias("source"), F.col(text_col).cast("string").alias("text"))
    return picked.mapInArrow(run, "doc_id long, source string, part long, before long, n long, ids binary")


def pack(docs: DataFrame, encode: Callable[[str], bytes], end_id: int, targets: dict[str, float] | None = None, window: int = WINDOW, max_queues: int = 256, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", with_ids: bool = False) -> DataFrame:
    """One row for each piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset (and ids if asked for).

    targets maps sources to weights (others weigh 0 until those run dry); by default each source weighs its own tokens,
    so that every window has the mixture of the whole table.
    """
    tokens = stored(encoded(docs, encode, end_id, id_col, text_col, source_col), "packing-ids")
    by_part = stored(tokens.groupBy("source", "part").agg(F.sum("n").alias("tokens")), "packing-counts")
    by_source = by_part.groupBy("source").agg(F.sum("tokens").alias("tokens")).orderBy(F.desc("tokens"), F.asc_nulls_first("source"))
    top = by_source.limit(max_queues - 1).collect()
    all_tokens = by_part.agg(F.sum("tokens")).first()[0] or 0
    named = {row["source"]: i for i, row in enumerate(top)}
    totals = np.array([*(row["tokens"] for row in top), 0], np.int64)
    totals[-1] = all_tokens - int(totals.sum())  # the sources beyond, which share the last queue
    shares = totals.astype(float)
    if targets is not None:
        shares = np.array([*(targets.get(row["source"], 0.0) for row in top), 0.0]) + 1e-9 * (totals > 0)
    placer = Placer(*schedule(totals, shares, window), window)

    # where a task's tokens begin in their queue; queues are ordered by task, then source
    spark = docs.sparkSession
    queue = spark.createDataFrame([(k, i) for k, i in named.items()], "source string, queue int")
    counts = by_part.join(F.broadcast(queue), by_part["source"].eqNullSafe(queue["source"]), "left").select(by_part["source"], "part", "tokens", F.coalesce("queue", F.lit(len(named))).alias("queue"))
    from pyspark.sql import Window

    order = Window.partitionBy("queue").orderBy("part", "source").rowsBetween(Window.unboundedPreceding, -1)
    bases = stored(counts.select(F.col("source").alias("source_"), F.col("part").alias("part_"), "queue", F.coalesce(F.sum("tokens").over(order), F.lit(0)).alias("base")), "packing-bases")
    joined = tokens.join(maybe_broadcast(bases, 64), (tokens["part"] == bases["part_"]) & tokens["source"].eqNullSafe(bases["source_"])).select("doc_id", "n", "ids", "queue", (F.col("base") + F.col("before")).alias("at"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            out: list[list] = [[] for _ in range(8)]
            for doc, n, ids, q, at in zip(*(c.to_pylist() for c in batch.columns)):
                view = memoryview(ids)
                for start, length, sequence, offset in placer.pieces(q, at, n):
                    piece = view[4 * start : 4 * (start + length)]
                    row = (doc, start, length, zlib.crc32(piece), n, sequence, offset, bytes(piece) if with_ids else None)
                    for column, value in zip(out, row):
                        column.append(value)
            yield pa.RecordBatch.from_arrays([*(pa.array(c, pa.int64()) for c in out[:7]), *([pa.array(out[7], pa.binary())] if with_ids else [])], names=_PIECE[: 7 + with_ids])

    return joined.mapInArrow(run, ", ".join(f"{name} {kind}" for name, kind in zip(_PIECE[: 7 + with_ids], ["long"] * 7 + ["binary"])))


_PIECE = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "ids"]
