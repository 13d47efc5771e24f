"""Corpus pipeline: quality filter, line dedup, near-duplicate removal, benchmark decontamination, tokenising.

Each stage takes (spark, docs, sf_dir) and works on all that the one before it kept. All but the last return the columns of docs.

Edge cases: null and empty texts go through each stage as its operator defines; rows with a null id are never dropped as copies; extra columns are
carried along; an empty table passes through.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from idagg.llm import bpe, decontaminate, line_dedup, quality, simhash
from idagg.llm._common import fresh, materialize, scratch, table


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier scores 0.5 or more."""
    net = quality.fit(docs, table(spark, sf_dir, "labels"), may_learn=F.crc32(F.col("id").cast("string")) % 3 != 1)
    good = fresh(docs, "__quality")
    return quality.score(docs, net, out=good).where(F.col(good) >= 0.5).drop(good)


def cut_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without runs of two or more lines that an earlier document, or place, has too; n_chars follows the text."""
    got = line_dedup.dedup(docs, runs=True, counts=False)
    return got.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else got


def keep_one_of_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates: the smallest id."""
    return simhash.keep_one(docs)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item."""
    return decontaminate.drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def tokenise(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256."""
    return bpe.encode_digests(docs)


STAGES = [
    ("quality_classifier", keep_good),
    ("line_dedup", cut_repeated_lines),
    ("simhash_near_dedup", keep_one_of_copies),
    ("benchmark_decontamination", drop_leaks),
    ("bpe_encoding", tokenise),
]

#: Stages 1, 3 and 5 learn, search by Hamming distance and tokenise: not expressible in SQL; tests hold each against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        if k == len(STAGES) - 1:
            return stage(spark, docs, sf_dir)
        with scratch(spark):  # what a stage wrote on its way goes when its result is written
            docs = materialize(stage(spark, docs, sf_dir), name, keep=True)
    return docs
