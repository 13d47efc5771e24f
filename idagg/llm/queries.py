"""The registered queries of this subpackage: each applies one operator to its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, decontaminate, embeddings, licenses, line_dedup, quality, repeats, simhash, toxicity, warc
from ._common import table


def _fold(id_col: str, k: int):
    return F.crc32(F.col(id_col).cast("string")) % k


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = toxicity.fit(docs, table(spark, sf_dir, "labels"), may_learn=_fold("id", 5) != 0)
    got = toxicity.score(docs, model)
    return got.select(
        "doc_id", F.coalesce(_fold("doc_id", 5) == 0, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op2_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.search(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = line_dedup.dedup(table(spark, sf_dir, "documents").select("doc_id", "text"), runs=True)
    return got.select(
        "doc_id", F.col("__n_lines").alias("n_lines"), F.col("__cut_lines").alias("n_removed_lines"), F.col("__cut_chunks").alias("n_removed_chunks"),
        F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


def op4_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = simhash.clusters(table(spark, sf_dir, "documents"))
    return got.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op5_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embeddings.clusters(table(spark, sf_dir, "embeddings"))


def op6_suffix_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = repeats.dedup(table(spark, sf_dir, "documents"), words=repeats.PASSAGE)
    return got.select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"), "n_passage_words")


def op7_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    net = quality.fit(docs, table(spark, sf_dir, "labels"), may_learn=_fold("id", 3) != 1)
    got = quality.score(docs, net)
    return got.select(
        "doc_id", F.coalesce(_fold("doc_id", 3) == 1, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op8_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    archives = warc.write(table(spark, sf_dir, "pages"))
    return warc.read(archives).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op9_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_digests(table(spark, sf_dir, "documents"))


def op10_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(table(spark, sf_dir, "documents"))


def queries() -> dict:
    return {"op1_toxicity": op1_toxicity, "op2_decontaminate": op2_decontaminate, "op3_line_dedup": op3_line_dedup, "op4_simhash": op4_simhash, "op5_embeddings": op5_embeddings, "op6_suffix_array": op6_suffix_array, "op7_quality": op7_quality, "op8_warc": op8_warc, "op9_bpe": op9_bpe, "op10_licenses": op10_licenses}


def oracle_sql() -> dict[str, str]:
    return {"op2_decontaminate": decontaminate.oracle(), "op3_line_dedup": line_dedup.oracle(), "op8_warc": warc.oracle(), "op10_licenses": licenses.oracle()}
