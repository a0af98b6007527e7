"""Queries over the given tables, one per operator, with production parameters on whole tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from poolcurator.llm import decontamination, exact_dedup, licenses, mixing, near_dedup, quality, secret_scan, sharding, toxicity, url_filter


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every secret candidate of every document with the forest's verdict."""
    model = secret_scan.train_forest(secret_scan.made_up_findings(spark))
    return secret_scan.scan_secrets(table(spark, sf_dir, "documents"), model)


def op2_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with the one that stays of its texts."""
    return exact_dedup.exact_duplicates(table(spark, sf_dir, "documents")).drop("bucket")


def op3_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with the licences that it names or quotes."""
    return licenses.license_digest(*licenses.scan_licenses(table(spark, sf_dir, "documents")))


def op4_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with its class of near duplicates."""
    return near_dedup.near_duplicates(table(spark, sf_dir, "documents"))


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with its toxicity score, learnt from the rows that are not held out."""
    docs = table(spark, sf_dir, "documents")
    model = toxicity.train_on_labels(docs, table(spark, sf_dir, "labels"))
    held_out = F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(4)) == 2
    return toxicity.score(docs, model).select("doc_id", held_out.alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


def op6_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every page with its rule and verdict."""
    return url_filter.filter_urls(table(spark, sf_dir, "pages"))


def op7_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with its shard of 24, by law `bytes`."""
    return sharding.shard(table(spark, sf_dir, "documents"), 24).withColumns({"law": F.lit("bytes"), "grown_shard": F.lit(None).cast("int")})


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with the words that the mix takes of it."""
    return mixing.mix(table(spark, sf_dir, "documents")).drop("repeats")


def op9_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with its perplexity and whether it stays."""
    docs = table(spark, sf_dir, "documents")
    return quality.quality_filter(docs, table(spark, sf_dir, "labels").where("quality = 1"))


def op10_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every pair of a document and a benchmark item that it contains to 0.8 or more."""
    return decontamination.find_items(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def queries() -> dict:
    return {name: f for name, f in globals().items() if name.startswith("op")}
