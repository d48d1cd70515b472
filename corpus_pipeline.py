"""A corpus pipeline over documents: quality rules, line dedup, near-dedup, secrets, packing.

STAGES are (name, function); a function takes (spark, docs, sf_dir) and returns a DataFrame, which is written as Parquet
and read again as the next one's docs. All but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from suffixloom.llm import line_dedup, packing, quality_rules, secrets, simhash
from suffixloom.llm.common import stored
from suffixloom.llm.queries import tokenizer_files


def _measured(docs: DataFrame, columns: list[str]) -> DataFrame:
    """columns of docs, with n_chars made to fit the text again where there is such a column."""
    length = {"n_chars": F.length("text").cast(docs.schema["n_chars"].dataType)} if "n_chars" in columns else {}
    return docs.withColumns(length).select(*(F.col(f"`{c}`") for c in columns))


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rule or the compression bands reject go."""
    return quality_rules.keep_good(docs)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines found in ten documents or more go, but from texts that are mostly such lines: those are copies."""
    return _measured(line_dedup.drop_common_lines(docs, min_docs=10, spare_share=0.5), docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates stays."""
    return simhash.keep_one(docs, width=5, similarity=0.8)


def secret_strings(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets are replaced by a mark."""
    return _measured(secrets.redact(docs), docs.columns)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of token sequences."""
    files = tokenizer_files()
    return packing.pack(docs, packing.file_encoder(files.path("byte_bpe_50k.json")), end_id=1)


STAGES = [("quality", quality), ("lines", lines), ("near_duplicates", near_duplicates), ("secrets", secret_strings), ("packing", packed)]

#: zstandard, SimHash and the tokenizer are beyond SQL; tests compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
