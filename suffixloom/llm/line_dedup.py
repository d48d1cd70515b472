"""Corpus-wide line removal: lines whose normalised form stands in many documents go everywhere.

Lines are exploded to 128-bit hashes of their keys (one for each distinct key of a row), pre-aggregated
before the shuffle, and counted over distinct documents. What returns to the texts is, for each document, the
small set of its own doomed keys; each text is then cut and put together again by position in one narrow pass.

A key is the line without ASCII white space at both ends, with A-Z lower-cased. Defined results: a null or empty text is
one empty line and its key is never counted; rows with the same id are one document; rows with a null
id are together one document; identical rows get identical results; other columns pass unchanged, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import maybe_broadcast, stored, utf8

_BLANK = b" \t\n\x0b\x0c\r"


def line_key(line: bytes) -> bytes:
    return line.strip(_BLANK).lower()  # bytes.lower() changes A-Z only


def code_points(data: bytes) -> int:
    return len(data) if data.isascii() else len(data.decode("utf-8", "replace"))


def fresh(name: str, taken: list[str]) -> str:
    """name, with underscores added until no taken name equals it in any case."""
    lowered = {x.lower() for x in taken}
    while name.lower() in lowered:
        name += "_"
    return name


def line_hashes(docs: DataFrame, id_col: str, text_col: str, min_chars: int) -> DataFrame:
    """(doc_id, key): the distinct keys of each row that can be counted."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        digest = xxhash.xxh3_128_digest
        for batch in batches:
            owners, keys = [], []
            for row, data in enumerate(utf8(batch.column(1))):
                found = {digest(k) for k in map(line_key, data.split(b"\n")) if k and (min_chars < 2 or code_points(k) >= min_chars)}
                keys.extend(found)
                owners.extend([row] * len(found))
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(owners, pa.int32())), pa.array(keys, pa.binary())], names=["doc_id", "key"])

    picked = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return picked.mapInArrow(run, T.StructType([T.StructField("doc_id", picked.schema["doc_id"].dataType), T.StructField("key", T.BinaryType())]))


def doomed_keys(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_docs: int = 10, min_chars: int = 1) -> DataFrame:
    """(doc_id, keys): for each document that has any, its keys found in at least min_docs documents."""
    hashes = line_hashes(docs, id_col, text_col, min_chars)
    # rows of a key are at least as many as its documents, so this throws out nearly all keys with a plain count
    often = stored(hashes.groupBy("key").count().where(F.col("count") >= min_docs).select("key"), "lines-often")
    pairs = stored(hashes.join(maybe_broadcast(often, 48), "key").distinct(), "lines-pairs")
    doomed = stored(pairs.groupBy("key").count().where(F.col("count") >= min_docs).select("key"), "lines-doomed")
    return pairs.join(maybe_broadcast(doomed, 48), "key").groupBy("doc_id").agg(F.collect_list("key").alias("keys"))


def drop_common_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_docs: int = 10, min_chars: int = 1, spare_share: float | None = None) -> DataFrame:
    """docs with the doomed lines cut out of text_col, and two more columns: n_lines (before) and n_dropped.

    With spare_share, a text that would lose more than that share of its bytes stays whole: it is a copy of
    a document, which near-duplicate removal should reduce to one, and not boilerplate around something else.
    If docs has columns of these names, the new ones get underscores at their end.
    """
    doomed = stored(doomed_keys(docs, id_col, text_col, min_docs, min_chars), "lines-by-document")
    owner, keys = fresh("owner", docs.columns), fresh("keys", docs.columns)
    doomed = doomed.select(F.col("doc_id").alias(owner), F.col("keys").alias(keys))
    # texts go through one shuffle at every size
    joined = docs.hint("merge").join(doomed, docs[id_col].eqNullSafe(doomed[owner]), "left").drop(owner)
    n_lines, n_dropped = fresh("n_lines", docs.columns), fresh("n_dropped", docs.columns)
    schema = T.StructType([*(T.StructField(f.name, T.StringType() if f.name == text_col else f.dataType) for f in docs.schema), T.StructField(n_lines, T.LongType()), T.StructField(n_dropped, T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        digest = xxhash.xxh3_128_digest
        for batch in batches:
            at, last = batch.schema.get_field_index(text_col), batch.num_columns - 1
            texts, before, dropped = [], [], []
            for data, own in zip(batch.column(at).cast(pa.binary()).to_pylist(), batch.column(last).to_pylist()):
                lines = (data or b"").split(b"\n")
                before.append(len(lines))
                if own:
                    bad = set(own)
                    kept = [x for x in lines if not (k := line_key(x)) or digest(k) not in bad]
                    if spare_share is not None and sum(map(len, kept)) < (1 - spare_share) * sum(map(len, lines)):
                        kept = lines
                    dropped.append(len(lines) - len(kept))
                    data = b"\n".join(kept) if len(kept) < len(lines) else data
                else:
                    dropped.append(0)
                texts.append(data)
            columns = batch.columns[:last]
            columns[at] = pa.array(texts, pa.binary()).cast(pa.string())
            yield pa.RecordBatch.from_arrays([*columns, pa.array(before, pa.int64()), pa.array(dropped, pa.int64())], names=[*batch.schema.names[:last], n_lines, n_dropped])

    return joined.mapInArrow(run, schema)
