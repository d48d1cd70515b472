"""WARC archives through a chunked record table.

Writing: captures become record segments of bounded size (a WARC continuation record for each further chunk), and
segments are appended to archives of bounded size, one archive a file, written by Spark's own sink so that any store will do.
Reading: archives are inflated and parsed as streams into rows of record id, chunk number and the digest of the
payload so far. Chunks that follow each other in an archive share one incremental SHA-256 and only the
digest leaves the task; a record that runs on in another archive sends its chunks as rows, and one streaming
pass in chunk order goes on with the digest. No step holds a whole record.

Defined results: a null payload is empty; a null id is written as such and read back as null; rows with equal id and
payload are one capture written twice and get the same type; null ids are never referred to while any other id
has the payload, and if none has, they are responses; other columns are not read.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import maybe_broadcast, scratch_path, stored

CRLF = b"\r\n"
_END = CRLF * 2
_EPOCH = b"1970-01-01T00:00:00Z"


@dataclass(frozen=True)
class ArchiveSizes:
    """Bytes of payload in a record segment, and bytes after which an archive is closed."""

    chunk: int = 1 << 20
    archive: int = 16 << 20


def with_types(pages: DataFrame, id_col: str, payload_col: str, min_bytes: int) -> DataFrame:
    """(id, payload, bytes, digest, refers_to): refers_to is null for responses.

    Only digests that occur more than once are joined back; a hot one is split by AQE's skew join.
    """
    payload = F.coalesce(F.col(payload_col).cast("string").cast("binary"), F.lit(b""))
    base = pages.select(F.col(id_col).cast("long").alias("id"), payload.alias("payload")).withColumns({"bytes": F.octet_length("payload").cast("long"), "digest": F.sha2("payload", 256)})
    firsts = base.where(F.col("bytes") >= min_bytes).groupBy("digest").agg(F.min("id").alias("first"), F.count("*").alias("n")).where("n > 1 and first is not null").select("digest", "first")
    firsts = maybe_broadcast(stored(firsts, "warc-firsts"), 120)
    refers = F.when(F.col("id").eqNullSafe(F.col("first")), None).otherwise(F.col("first"))
    return base.join(firsts, "digest", "left").select("id", "payload", "bytes", "digest", refers.alias("refers_to"))


def _name(page: int | None) -> bytes:
    return b"<urn:page:%s>" % (b"null" if page is None else str(page).encode())


def segments(record: str, page: int | None, payload: bytes, digest: str, refers: int | None, chunk: int) -> Iterator[bytes]:
    """The WARC records of one capture, each ready but for its closing blank lines."""
    own = b"<urn:record:%s>" % record.encode()
    common = [b"X-Page: " + _name(page), b"WARC-Date: " + _EPOCH, b"WARC-Payload-Digest: sha256:" + digest.encode(), b"X-Payload-Length: %d" % len(payload)]
    if refers is not None:
        yield CRLF.join([b"WARC/1.1", b"WARC-Type: revisit", b"WARC-Record-ID: " + own, *common, b"WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", b"WARC-Refers-To: " + _name(refers), b"Content-Length: 0", b"", b""])
        return
    view, number = memoryview(payload), 0
    while number == 0 or number * chunk < len(payload):
        piece = view[number * chunk : (number + 1) * chunk]
        if number:
            more = [b"WARC-Record-ID: <urn:record:%s-%d>" % (record.encode(), number), b"WARC-Segment-Origin-ID: " + own]
        else:
            more = [b"WARC-Record-ID: " + own]
        if len(payload) > chunk:
            more.append(b"WARC-Segment-Number: %d" % (number + 1))
        yield CRLF.join([b"WARC/1.1", b"WARC-Type: " + (b"continuation" if number else b"response"), *common, *more, b"Content-Length: %d" % len(piece), b"", bytes(piece)])
        number += 1


def write_archives(typed: DataFrame, path: str, sizes: ArchiveSizes = ArchiveSizes()) -> None:
    """Write the rows of with_types() as gzipped WARC files under path, one file for each archive."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size, n, part = [], 0, 0, TaskContext.get().partitionId()
        emit = lambda: pa.RecordBatch.from_arrays([pa.array([_END.join(held)], pa.binary())], names=["value"])
        for batch in batches:
            for row in range(batch.num_rows):
                page, payload, _, digest, refers = (column[row].as_py() for column in batch.columns)
                n += 1
                for segment in segments(f"{part}-{n}", page, payload, digest, refers, sizes.chunk):
                    held.append(segment)
                    size += len(segment)
                    if size >= sizes.archive:
                        yield emit()
                        held, size = [], 0
        if held:
            yield emit()

    archives = typed.mapInArrow(pack, "value binary").select(F.col("value").cast("string").alias("value"))
    # the sink ends each value by the separator, so it supplies the last record's closing blank lines
    archives.write.options(lineSep=_END.decode(), compression="gzip", maxRecordsPerFile="1").text(path)


def _inflated(data: bytes, step: int = 1 << 18) -> Iterator[bytes]:
    """The content of a file of one or more gzip members, in pieces."""
    inflate, view = zlib.decompressobj(31), memoryview(data)
    for i in range(0, len(data), step):
        part = view[i : i + step]
        while part:
            yield inflate.decompress(part)
            part = inflate.unused_data
            if inflate.eof:
                inflate = zlib.decompressobj(31)
    yield inflate.flush()


class _Stream:
    """Reads heads and bodies from pieces, holding little more than one piece."""

    def __init__(self, pieces: Iterator[bytes]):
        self.pieces, self.held = pieces, bytearray()

    def more(self) -> bool:
        piece = next(self.pieces, None)
        self.held += piece or b""
        return piece is not None

    def head(self) -> dict[bytes, bytes] | None:
        while (end := self.held.find(_END)) < 0:
            if not self.more():
                if self.held.strip():
                    raise ValueError("an archive ends inside a record's head")
                return None
        lines = bytes(self.held[:end]).split(CRLF)
        del self.held[: end + 4]
        if not lines[0].startswith(b"WARC/"):
            raise ValueError(f"not a WARC record: {lines[0][:40]!r}")
        return {k.lower(): v.strip() for k, v in (line.split(b":", 1) for line in lines[1:])}

    def body(self, length: int, step: int = 1 << 18) -> Iterator[bytes]:
        """length bytes in pieces, then the closing blank lines are passed."""
        while length:
            if not self.held and not self.more():
                raise ValueError("an archive ends inside a record")
            piece = bytes(self.held[: min(length, step)])
            del self.held[: len(piece)]
            length -= len(piece)
            if piece:
                yield piece
        while len(self.held) < 4 and self.more():
            pass
        if self.held[:4] != _END:
            raise ValueError("a record isn't closed")
        del self.held[:4]


def _id(name: bytes | None) -> int | None:
    value = name and name.removeprefix(b"<urn:page:").removesuffix(b">")
    return None if value in (None, b"null") else int(value)


_FIELDS = ["record", "chunk_no", "page_id", "record_type", "refers_to", "stated_bytes", "stated_digest", "payload_bytes", "payload_digest", "chunk"]
_KINDS = [pa.string(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.binary()]
_CHUNKS = "record string, chunk_no long, page_id long, record_type string, refers_to long, stated_bytes long, stated_digest string, payload_bytes long, payload_digest string, chunk binary"


def _table(rows: list) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), _KINDS)], names=_FIELDS)


def parsed(data: bytes) -> Iterator[list]:
    """Rows of the chunk table from the bytes of one archive file.

    A record that begins and ends here is a single row without bytes: its chunks went through one incremental
    digest. Of one that began before or goes on after, each chunk is a row.
    """
    stream, open_, pending = _Stream(_inflated(data)), None, []
    while (head := stream.head()) is not None:
        get = lambda name, default=b"": head.get(name, default).decode().removeprefix("<urn:record:").removesuffix(">")  # noqa: E731, B023
        kind, stated, length = get(b"warc-type"), int(get(b"x-payload-length")), int(get(b"content-length"))
        record = get(b"warc-segment-origin-id") or get(b"warc-record-id")
        row = [record, int(get(b"warc-segment-number", b"1")) - 1, _id(head[b"x-page"]), kind.replace("continuation", "response"), _id(head.get(b"warc-refers-to")), stated, get(b"warc-payload-digest").removeprefix("sha256:")]
        if kind == "revisit":
            yield [*row, stated, row[-1], None]  # its payload is that of the record it refers to
            list(stream.body(length))
            continue
        if kind == "response":
            yield from pending
            open_, pending = (row, hashlib.sha256()), []
        elif open_ and open_[0][0] != record:
            yield from pending
            open_, pending = None, []
        kept, size = [], 0
        for piece in stream.body(length):
            if open_:
                open_[1].update(piece)
            if length < stated:
                kept.append(piece)
            size += len(piece)
        if open_ and size + sum(x[-3] for x in pending) == stated:
            yield [*open_[0], stated, open_[1].hexdigest(), None]
            open_, pending = None, []
        elif open_:
            pending.append([*row, size, None, b"".join(kept)])
        else:
            yield [*row, size, None, b"".join(kept)]
    yield from pending


def chunk_table(spark: SparkSession, path: str) -> DataFrame:
    """The archives under path as rows of record, chunk number, length and either digest or bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for data in batch.column(0):
                held, weight = [], 0
                for row in parsed(data.as_py()):
                    held.append(row)
                    weight += 200 + len(row[-1] or b"")
                    if weight > 4 << 20:
                        yield _table(held)
                        held, weight = [], 0
                if held:
                    yield _table(held)

    return spark.read.format("binaryFile").load(path).select("content").mapInArrow(run, _CHUNKS)


def digested(chunks: DataFrame) -> DataFrame:
    """One row for each record, with the length and digest of the payload that was read.

    Rows without bytes pass. Chunks of a record that spans archives come together in chunk order, and are
    digested one at a time.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, state, size = None, None, 0
        for batch in batches:
            out = []
            for i in range(batch.num_rows):
                row = [c[i].as_py() for c in batch.columns]
                if row[-1] is None:
                    out.append(row)
                    continue
                if row[1] == 0:
                    key, state, size = row[0], hashlib.sha256(), 0
                if key != row[0]:
                    raise ValueError(f"record {row[0]}: its first chunk is missing")
                state.update(row[-1])
                size += len(row[-1])
                if size == row[5]:
                    out.append([row[0], 0, *row[2:7], size, state.hexdigest(), None])
            if out:
                yield _table(out)

    return chunks.repartition("record").sortWithinPartitions("record", "chunk_no").mapInArrow(run, _CHUNKS).drop("chunk", "chunk_no")


def read_records(spark: SparkSession, path: str) -> DataFrame:
    return digested(chunk_table(spark, path))


def archive_round_trip(pages: DataFrame, id_col: str = "page_id", payload_col: str = "html", min_bytes: int = 100, sizes: ArchiveSizes = ArchiveSizes()) -> DataFrame:
    """Write all rows as archives in the shared folder, read them back, and describe what was read."""
    spark = pages.sparkSession
    path = scratch_path(spark, "warc")
    write_archives(with_types(pages, id_col, payload_col, min_bytes), path, sizes)
    return read_records(spark, path)
