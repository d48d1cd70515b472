"""Quality rules: word, symbol and repetition counts, and compression bands.

A text is judged by zstandard ratios (compressed over raw bytes): over the whole document, and over
fixed chunks. Limits depend on the length, since short texts compress less. A ratio under its band
means repetition, one over it means noise.

Defined results: a null or empty text has no words and fails the base rule; texts under the first band are not
judged by compression; repeated rows give repeated results; other columns are neither read nor returned by
``quality_report`` and pass unchanged through ``keep_good``, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, utf8

_SYMBOLS = [b"#", b"*", b"$", b"%", b"&", b"|", b"<", b">"]


@dataclass(frozen=True)
class Band:
    """Limits of the ratio for texts of at least min_bytes."""

    min_bytes: int
    low: float
    high: float


#: From short to long; the last one whose min_bytes the text reaches holds.
BANDS = (Band(256, 0.30, 0.90), Band(1024, 0.25, 0.80), Band(4096, 0.20, 0.72), Band(16384, 0.15, 0.68))


@dataclass(frozen=True)
class CompressionRule:
    bands: tuple[Band, ...] = BANDS
    chunk_bytes: int = 4096
    chunk_low: float = 0.15
    chunk_high: float = 0.80
    #: A document goes if more than this share of its full chunks lies outside the chunk limits.
    bad_chunk_share: float = 0.5
    level: int = 3


class TextJudge:
    """Counts and verdict for one text at a time; holds a reusable compressor, so one per task."""

    def __init__(self, rule: CompressionRule):
        self.rule = rule
        self.compressor = zstandard.ZstdCompressor(level=rule.level)

    def ratio(self, data: bytes) -> float:
        return len(self.compressor.compress(data)) / len(data)

    def compression(self, data: bytes) -> tuple[float | None, int, int, bool]:
        """Whole-text ratio (null under the first band), full chunks, those outside the limits, verdict."""
        rule = self.rule
        band = next((b for b in reversed(rule.bands) if len(data) >= b.min_bytes), None)
        if band is None:
            return None, 0, 0, True
        whole = self.ratio(data)
        chunks = len(data) // rule.chunk_bytes
        bad = 0
        if chunks > 1:
            view = memoryview(data)
            for i in range(chunks):
                bad += not rule.chunk_low <= self.ratio(view[i * rule.chunk_bytes : (i + 1) * rule.chunk_bytes]) <= rule.chunk_high
        return whole, chunks, bad, band.low <= whole <= band.high and bad <= rule.bad_chunk_share * chunks

    def counts(self, data: bytes) -> tuple[int, int, int, int, int]:
        """Words, code points in words, symbols, repeated lines, words in repeated three-word windows."""
        words = data.split()  # bytes.split() parts at exactly the six ASCII white-space bytes
        joined = b"".join(words)
        chars = len(joined) if joined.isascii() else len(joined.decode("utf-8", "replace"))
        lines = [x for x in data.split(b"\n") if x and not x.isspace()]
        return len(words), chars, sum(map(data.count, _SYMBOLS)), len(lines) - len(set(lines)), repeated_words(words)

    def judge(self, data: bytes) -> dict:
        n, chars, symbols, dup, repeats = self.counts(data)
        failed = n < 50 or 100 * repeats > 50 * n
        whole, chunks, bad, fine = self.compression(data)
        return {"n_words": n, "word_chars": chars, "n_symbols": symbols, "n_dup_lines": dup, "n_repeat_words": repeats, "base_failed": failed, "kept": fine and not failed, "whole_ratio": whole, "n_chunks": chunks, "bad_chunks": bad}


def repeated_words(words: list[bytes]) -> int:
    windows = list(zip(words, words[1:], words[2:]))
    if len(set(windows)) == len(windows):
        return 0
    first: dict = {}
    covered = bytearray(len(words))
    for i, window in enumerate(windows):
        j = first.setdefault(window, i)
        if j != i:
            covered[i : i + 3] = b"\1\1\1"
            covered[j : j + 3] = b"\1\1\1"
    return sum(covered)


def quality_report(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rule: CompressionRule = CompressionRule()) -> DataFrame:
    """One row for each row of docs: id, counts, base_failed, kept, and the compression measures."""

    def rows(batch: pa.RecordBatch) -> dict[str, list]:
        judge = TextJudge(rule)
        found = [judge.judge(data) for data in utf8(batch.column(1))]
        return {"doc_id": batch.column(0).to_pylist()} | {k: [x[k] for x in found] for k in found[0]}

    schema = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, whole_ratio double, n_chunks long, bad_chunks long"
    return arrow_map(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")), rows, schema)


def keep_good(docs: DataFrame, text_col: str = "text", rule: CompressionRule = CompressionRule()) -> DataFrame:
    """The rows of docs, all columns, whose text passes the base rule and the compression bands."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        judge = TextJudge(rule)
        for batch in batches:
            yield batch.filter(pa.array([judge.judge(x)["kept"] for x in utf8(batch.column(batch.schema.get_field_index(text_col)))], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
