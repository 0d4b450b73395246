"""Corpus preparation: stages over `documents`, each over the whole of what its predecessor kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rambler.llm.common import documents, pick, written
from rambler.llm.decontam import contamination, small
from rambler.llm.jaccard import jaccard_classes
from rambler.llm.langid import UNKNOWN, identify
from rambler.llm.linededup import dedup_lines
from rambler.llm.packing import pack_documents

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which a language is found go on; those without any letter, or without text, are rejected. Labels aren't changed."""
    own = pick(docs, *COLUMNS)
    return identify(own, own).where(F.col("lang_pred") != UNKNOWN).select(*COLUMNS)


def without_common_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that ten or more documents hold are taken out; every document stays, n_chars follows its text."""
    return dedup_lines(pick(docs, *COLUMNS), min_docs=10).withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents that links join, the one with the least id stays (of rows that repeat an id and a text, one). Documents without words stay."""
    own = pick(docs, *COLUMNS)
    classes = written(jaccard_classes(own))
    n, ids = classes.agg(F.count("*"), F.countDistinct("doc_id")).first()
    kept = written(classes.where("doc_id <=> component_id").select(F.col("doc_id").alias("kept")).distinct())
    left = own.join(small(kept, 32), F.expr("doc_id <=> kept"), "left_semi")
    return left if n == ids else left.dropDuplicates(["doc_id", "text"])


def without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold ten consecutive words of a benchmark item are dropped."""
    own = pick(docs, *COLUMNS)
    hit = written(contamination(own, spark.read.parquet(f"{sf_dir}/benchmark.parquet")).where("contaminated").select(F.col("doc_id").alias("hit")).distinct())
    return own.join(small(hit, 32), F.expr("doc_id <=> hit"), "left_anti")


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token windows of what is left."""
    return pack_documents(docs)


STAGES = [
    ("language identification", known_language),
    ("line dedup", without_common_lines),
    ("n-gram jaccard join", one_of_each_group),
    ("benchmark decontamination", without_benchmark),
    ("packing", packed),
]
#: Packing's token ids and the fitted language model are beyond SQL; the stages are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for _, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
