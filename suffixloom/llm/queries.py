"""The queries of the training-data operators: each applies one to its whole table and returns its whole result."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, licenses, line_dedup, neighbours, packing, quality_rules, secrets, simhash, urls, warc


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokenizer_files():
    """The module that knows the vocabulary files of the public tokenizers."""
    import public_tokenizers

    return public_tokenizers


def op1_warc_archives(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.archive_round_trip(table(spark, sf_dir, "pages")).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op2_secret_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.secret_spans(table(spark, sf_dir, "documents"))


def op3_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    files = tokenizer_files()
    return bpe.round_trip(table(spark, sf_dir, "documents"), files.path("byte_bpe_50k.tiktoken"), files.PATTERN)


#: The path rules of the query.
RULES = [urls.PathRule("org/", "allow"), urls.PathRule("example.org/es/", "block"), urls.PathRule("example.org/en/1", "block"), urls.PathRule("com/fr/", "allow"), urls.PathRule("com/de/", "block")]


def op4_url_verdicts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Labelled URLs are those whose path ends in the number of a document with a quality label."""
    pages, labels = table(spark, sf_dir, "pages"), table(spark, sf_dir, "labels")
    number = F.regexp_extract("url", r"/(\d{1,18})(?:[/.?#]|$)", 1)
    labelled = pages.select("url", F.when(number != "", number.cast("long")).alias("doc_id")).join(labels.select("doc_id", "quality"), "doc_id").select("url", F.col("quality").alias("label"))
    return urls.judge_urls(pages, labelled, RULES)


def op5_mixture_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    files = tokenizer_files()
    encode = packing.file_encoder(files.path("byte_bpe_50k.json"))
    return packing.pack(table(spark, sf_dir, "documents"), encode, end_id=1)


def op6_learned_partitions(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings")
    return neighbours.nearest(vectors, vectors.where(F.col("vec_id") % 100 == 0), k=10)


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.quality_report(table(spark, sf_dir, "documents"))


def op8_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    done = line_dedup.drop_common_lines(table(spark, sf_dir, "documents").select("doc_id", "text"), min_docs=10)
    text = F.coalesce("text", F.lit(""))
    return done.select("doc_id", "n_lines", "n_dropped", F.sha2(text.cast("binary"), 256).alias("kept_sha256"))


def op9_simhash_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_components(table(spark, sf_dir, "documents"), width=3, radius=2)
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def op10_license_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.license_labels(table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_warc_archives, op2_secret_spans, op3_bpe_round_trip, op4_url_verdicts, op5_mixture_packing, op6_learned_partitions, op7_quality_rules, op8_line_dedup, op9_simhash_components, op10_license_labels)}
