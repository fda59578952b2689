"""The corpus pipeline: five stages, each one of the training-data operators.

quality classifier -> line dedup -> shingle Jaccard join -> benchmark
decontamination -> BPE.  Every stage works on all that its predecessor kept and
returns the columns of documents; the last returns each document's ids.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evolrank.llm import bpe, decontaminate, line_dedup, ngram_join, quality
from evolrank.llm.common import materialise, release, table

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def _with_text(text) -> list:
    return ["row.doc_id", text.alias("text"), "row.lang", "row.source", F.length(text).cast("long").alias("n_chars")]


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rule ensemble rejects go."""
    model = quality.fit_quality(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    scored = quality.score_quality(docs.select(*COLUMNS), model)
    return scored.where("predicted = 1").select("row.*")


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that an earlier document holds go; a document whose every line went is kept with an empty text."""
    return line_dedup.dedup_lines(docs.select(*COLUMNS)).select(*_with_text(F.col("kept_text")))


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays: the one with the smallest id."""
    groups = ngram_join.similar_components(docs.select("doc_id", "text"))
    extra = groups.where(F.col("component_id") != F.col("doc_id")).select(F.col("doc_id").alias("extra_id")).distinct()
    return docs.select(*COLUMNS).join(extra, docs["doc_id"] == extra["extra_id"], "left_anti")


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark passage go."""
    return decontaminate.decontaminate(docs.select(*COLUMNS), table(spark, sf_dir, "benchmark"))


def bpe_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) of every document that is left."""
    return bpe.encoded_digests(docs.select("doc_id", "text"))


STAGES = [
    ("quality classifier", quality_stage),
    ("line dedup", line_stage),
    ("n-gram Jaccard join", near_duplicate_stage),
    ("benchmark decontamination", decontamination_stage),
    ("BPE", bpe_stage),
]
ORACLE_SQL = None  # tokens and the fitted rules are beyond SQL; the operators of the stages are tested one by one


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, last = table(spark, sf_dir, "documents"), None
    for _, stage in STAGES:
        docs = materialise(stage(spark, docs, sf_dir))
        if last is not None:
            release(last)
        last = docs
    return docs
