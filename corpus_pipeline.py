"""A training corpus from raw documents: toxicity, near duplicates, decontamination, mixing, sharding."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from poolcurator.llm import decontamination, mixing, near_dedup, sharding, toxicity
from poolcurator.llm.store import drop_path, new_path, small_side, write_table

#: A document at or above this score is rejected.
TOXIC = 0.3


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """docs without those that the toxicity classifier rejects."""
    model = toxicity.train_on_labels(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    scored = toxicity.score(docs, model, keep=tuple(c for c in docs.columns if c != "doc_id"))
    return scored.where(F.col("score") < TOXIC).select(*docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near duplicates; documents without an id stay."""
    dropped, _ = write_table(near_dedup.near_duplicates(docs).where("not kept").select(F.col("doc_id").alias("_gone")), "dropped")
    return docs.join(small_side(dropped, dropped.count()), docs.doc_id == F.col("_gone"), "left_anti")


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """docs without those that contain a benchmark item."""
    return decontamination.decontaminate(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them."""
    mixed = mixing.mix(docs, keep=tuple(c for c in docs.columns if c not in ("doc_id",)))
    return mixed.where("repeats > 0").withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("repeats")))).select(*docs.columns)


def shard_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every row of the mix with its shard and slot."""
    return sharding.shard(docs, 24)


STAGES = [
    ("toxicity", drop_toxic),
    ("near_dedup", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("mixing", mix_sources),
    ("sharding", shard_documents),
]

#: No stage but decontamination can be put in SQL; the tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages in order on documents; each is written to the shared folder and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    last = None
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i == len(STAGES) - 1:
            return docs
        path = new_path(spark, f"pipeline-{name}")
        schema = docs.schema
        docs.write.parquet(path)
        docs = spark.read.schema(schema).parquet(path)
        if last:
            drop_path(spark, last)
        last = path
    return docs
