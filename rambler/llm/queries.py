"""One query for each training-data operator, over whole tables and with production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import documents, pick
from .decontam import contamination
from .jaccard import jaccard_classes
from .langid import identify
from .licenses import license_labels
from .linededup import dedup_lines
from .lm import score_documents
from .packing import pack_documents
from .sharding import shard_by_bytes
from .tokencount import count_tokens
from .winnow import edited_fingerprints


def op1_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pieces of all documents in windows of 2048 tokens. Null text: the end id alone; repeated rows and null ids are packed each; no rows: none."""
    return pack_documents(documents(spark, sf_dir)).select("doc_id", "start", "length", F.crc32("token_ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")


def op2_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """License phrases and verified template spans of each row. Null or empty text: no word, no label, score 0; repeated rows give a row each."""
    return license_labels(documents(spark, sf_dir))


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What stays of each row without the lines that ten rows or more hold. Null or empty text: one empty line, which stays; repeated rows count as documents."""
    return dedup_lines(pick(documents(spark, sf_dir), "doc_id", "text"), min_docs=10).select("doc_id", "n_lines", "n_dropped", F.sha2(F.coalesce("text", F.lit("")).cast("binary"), 256).alias("kept_sha256"))


def op4_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Eight contiguous shards of near-equal bytes, in the order of doc_id. Null text: size 1; ties and repeated rows are placed one after another."""
    placed = shard_by_bytes(documents(spark, sf_dir), shards=8)
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op5_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Size of each row's shingle set and its class. Null, empty and blank texts: size 0 and a class of their own; repeated rows are of one class."""
    return jaccard_classes(documents(spark, sf_dir), k=5, percent=75)


def op6_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Words of each row that windows of ten benchmark words cover. Null or empty text: no word, no hit; repeated rows are hit alike."""
    found = contamination(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"), n=10)
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("items_sha256"), "contaminated")


def op7_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes and tokens of each row. Null or empty text: 0 and 0; repeated rows give a row each."""
    return count_tokens(documents(spark, sf_dir), limit=512)


def op8_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Base score and context-tree score of each row. Null or empty text: the end token alone; a null id trains; repeated rows train as often as they occur."""
    return score_documents(documents(spark, sf_dir))


def op9_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprints of each row and of its edited text. Null text counts as empty; rows of one id follow each other in the order of their texts' hashes."""
    return edited_fingerprints(documents(spark, sf_dir)).select("doc_id", "n_chars", F.sha2(F.col("edited_text").cast("binary"), 256).alias("edited_sha256"), "fingerprint", "edited_fingerprint", "near_edited", "near_next")


def op10_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Language of each row, from a model of the training rows. Null text, or one without a letter: und, score 0; repeated rows give a row each."""
    docs = documents(spark, sf_dir)
    held_out = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2, F.lit(False))
    return identify(pick(docs, "doc_id", "text"), docs.where(~held_out)).select("doc_id", held_out.alias("held_out"), "lang_pred", "score")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (op1_packing, op2_license_scan, op3_line_dedup, op4_sharding, op5_jaccard_join, op6_decontamination, op7_token_counts, op8_lm_scoring, op9_fingerprints, op10_language_id)}
