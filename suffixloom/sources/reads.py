"""Read collections (read_id long, seq string) from tables and files."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.refs import RefLayout
from ..operators.positions import with_positions
from ..scratch import stored

#: Bytes of texts that are cut at once.
_TEXTS = 1 << 22
LETTERS = "abcdefghijklmnopqrstuvwxyz"
DNA_OF_LETTERS = ("ACGT" * 7)[:26]
#: The same with the rarest letters as bases that could not be told.
DNA_N_OF_LETTERS = "".join("N" if c in "jqxz" else b for c, b in zip(LETTERS, DNA_OF_LETTERS))


def reads_from(df: DataFrame, id_col: str, text_col: str, validate: bool = False) -> DataFrame:
    """Two columns of df as reads. validate=True refuses nulls and repeated numbers, at the cost of a shuffle."""
    reads = df.select(F.col(id_col).cast("long").alias("read_id"), F.col(text_col).cast("string").alias("seq"))
    if validate:
        if reads.where("read_id IS NULL OR seq IS NULL").limit(1).count():
            raise ValueError("reads hold nulls")
        if reads.groupBy("read_id").count().where("count > 1").limit(1).count():
            raise ValueError("read numbers repeat")
    return reads


def chunk_reads(df: DataFrame, id_col: str, text: Column | str, width: int = 200, stride: int = 1000, overlap: int = 0) -> DataFrame:
    """Whole texts cut into reads of width symbols; read_id = id * stride + number of the piece. Null and empty texts give none,
    and a text of stride pieces or more fails at run time, as its numbers would be another text's: see fit_stride.

    With overlap, pieces begin width - overlap apart, so that what crosses a cut is whole in one of them.
    """
    return _pieces(df, id_col, F.col(text) if isinstance(text, str) else text, width, stride, width - overlap)


def _pieces(df: DataFrame, id_col: str, text: Column, width: int, stride: int, step: int, letters: dict[str, str] | None = None) -> DataFrame:
    """chunk_reads() over Arrow batches, as a cut in a long text counts its symbols from the start each time; with letters, of what they map a text's symbols onto, all else dropped."""
    table = np.zeros(256, np.uint8)
    for symbol, other in (letters or {}).items():
        table[ord(symbol)] = ord(other)

    def cut(ids: np.ndarray, known: np.ndarray, raw: np.ndarray, edges: np.ndarray) -> pa.RecordBatch:
        edges = edges - edges[0]
        if letters is not None:
            raw = table[raw]
            kept = raw > 0
            edges, raw = np.append(0, np.cumsum(kept))[edges], raw[kept]
        wide = letters is None and bool((raw & 0x80).any())
        # where symbols begin, and how many are before each text
        symbols = np.append(np.flatnonzero((raw & 0xC0) != 0x80), len(raw)) if wide else None
        before = np.searchsorted(symbols, edges) if wide else edges
        n = np.diff(before)
        pieces = np.where(n > 0, (n - 1) // step + 1, 0)
        if (pieces > stride).any():
            raise ValueError(f"a text has more than {stride} pieces: fit the stride")
        of = np.repeat(np.arange(len(n)), pieces)
        k = np.arange(len(of)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
        first = before[of] + k * step
        last = np.minimum(first + width, before[of] + n[of])
        first, last = (symbols[first], symbols[last]) if wide else (first, last)
        sizes = last - first
        to = np.append(0, np.cumsum(sizes))
        data = raw[np.arange(to[-1]) + np.repeat(first - to[:-1], sizes)]
        seq = pa.StringArray.from_buffers(len(of), pa.py_buffer(to.astype(np.int32)), pa.py_buffer(np.ascontiguousarray(data)))
        return pa.RecordBatch.from_arrays([pa.array(ids[of] * stride + k, pa.int64(), mask=~known[of]), seq], names=["read_id", "seq"])

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            known = batch.column(0).is_valid().to_numpy(zero_copy_only=False)
            ids, text = batch.column(0).fill_null(0).to_numpy(), batch.column(1).cast(pa.large_binary())
            _, edges, data = text.buffers()
            edges, data = np.frombuffer(edges, np.int64)[text.offset : text.offset + len(ids) + 1], np.frombuffer(data, np.uint8)
            first = 0
            while first < len(ids):
                last = max(first + 1, int(np.searchsorted(edges, edges[first] + _TEXTS, side="right")) - 1)
                yield cut(ids[first:last], known[first:last], data[edges[first] : edges[last]], edges[first : last + 1])
                first = last

    return df.select(F.col(id_col).cast("long").alias("id"), text.cast("string").alias("text")).where(F.octet_length("text") > 0).mapInArrow(run, "read_id long, seq string")


def fit_stride(df: DataFrame, text: Column | str, width: int = 200) -> int:
    """The next power of ten above the most pieces that a text of df has."""
    longest = df.agg(F.max(F.length(F.col(text) if isinstance(text, str) else text))).first()[0] or 0
    return RefLayout.fit(-(-longest // width)).stride


def to_dna(text: Column, bases: str = DNA_OF_LETTERS) -> Column:
    """ASCII letters mapped onto the four bases, all else dropped: repeats like a genome's, on any text."""
    return F.translate(F.lower(F.regexp_replace(text, "[^A-Za-z]", "")), LETTERS, bases)


def letters_to(bases: str) -> dict[str, str]:
    """What to_dna() makes of each ASCII letter."""
    return dict(zip(LETTERS + LETTERS.upper(), bases * 2))


def dna_reads(df: DataFrame, id_col: str, text_col: str, width: int = 200, bases: str = DNA_OF_LETTERS) -> DataFrame:
    """chunk_reads() of what to_dna() makes of texts."""
    return _pieces(df, id_col, F.col(text_col), width, 1000, width, letters_to(bases))


def random_dna_reads(df: DataFrame, key_col: str) -> DataFrame:
    """32 near-uniform symbols from a key's MD5."""
    digest = F.md5(F.concat(F.col(key_col).cast("string"), F.lit("-0")))
    return df.select(F.col(key_col).cast("long").alias("read_id"), F.translate(digest, "0123456789abcdef", "ACGT" * 4).alias("seq"))


def reverse_reads(reads: DataFrame, complement: bool = False) -> DataFrame:
    seq = F.reverse("seq")
    return reads.select("read_id", (F.translate(seq, "ACGT", "TGCA") if complement else seq).alias("seq"))


def pair_reads(forward: DataFrame, reverse: DataFrame) -> DataFrame:
    """Both files of a paired-end run as one collection: even numbers forward, odd ones reverse."""
    return forward.select((F.col("read_id") * 2).alias("read_id"), "seq").unionByName(reverse.select((F.col("read_id") * 2 + 1).alias("read_id"), "seq"))


def load_reads(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """Reads from files: parquet, json, csv (read_id, seq), text (number, tab, string), fasta and fastq (numbered as they stand)."""
    if fmt in ("parquet", "json"):
        return reads_from(getattr(spark.read, fmt)(path), "read_id", "seq")
    if fmt == "csv":
        return spark.read.schema("read_id long, seq string").csv(path)
    if fmt == "text":
        parts = F.split("value", "\t", 2)
        return spark.read.text(path).select(parts[0].cast("long").alias("read_id"), parts[1].alias("seq"))
    if fmt == "fasta":
        # a record is what stands between markers at line starts, so files are split by Spark's own line reader
        lines = F.split("value", "\r?\n")
        records = spark.read.option("lineSep", "\n>").text(path).where(F.length(F.trim("value")) > 0)
        return with_positions(records.select(F.array_join(F.slice(lines, F.lit(2), F.size(lines)), "").alias("seq")), "fasta").select(F.col("pos").alias("read_id"), "seq")
    if fmt == "fastq":
        return _second_of_four(spark, path)
    raise ValueError(f"unknown format {fmt}")


def _second_of_four(spark: SparkSession, path: str) -> DataFrame:
    """The sequence lines of four-line records. Lines are counted rather than recognised, as any may begin with a marker; of each split
    of a file a row with its number of lines comes together."""
    from pyspark.sql import Window

    lines = spark.read.text(path).select("value", F.col("_metadata.file_path").alias("file"), F.col("_metadata.file_block_start").alias("block"), F.monotonically_increasing_id().alias("at"))
    lines = stored(lines, "lines")
    blocks = lines.groupBy("file", "block").agg(F.count("*").alias("n"), F.min("at").alias("first"))
    before = Window.partitionBy("file").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    starts = blocks.select("file", "block", "first", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("start"))
    files = blocks.groupBy("file").agg(F.ceil(F.sum("n") / 4).alias("records"))
    ahead = files.select("file", F.coalesce(F.sum("records").over(Window.orderBy("file").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("ahead"))
    placed = lines.join(F.broadcast(starts.join(ahead, "file")), ["file", "block"]).withColumn("line", F.col("start") + F.col("at") - F.col("first"))
    return placed.where("line % 4 = 1").select((F.col("ahead") + (F.col("line") / 4).cast("long")).alias("read_id"), F.trim("value").alias("seq"))


def write_suffix_array(sa: DataFrame, path: str) -> None:
    """Rows range-partitioned and sorted by position, so that files carry tight minima and maxima for skipping."""
    sa.repartitionByRange("pos").sortWithinPartitions("pos").write.mode("overwrite").parquet(path)
