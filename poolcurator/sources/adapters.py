"""Samples (instruction, input, output) from documents, chats and web pages."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from poolcurator import schema
from poolcurator.functions import text as X


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    reader = spark.read
    if name in schema.TABLES:
        reader = reader.schema(schema.TABLES[name])
    return reader.parquet(f"{sf_dir}/{name}.parquet")


def read_spread(spark: SparkSession, sf_dir: str, name: str, key: str) -> DataFrame:
    """The table, dealt by key to all cores if it comes in too few splits to keep half of them busy.

    A small table is often one file of one row group, which one task would work through; large ones are left as
    they are. Aggregates by the key need no further shuffle then.
    """
    df, cores = read_table(spark, sf_dir, name), spark.sparkContext.defaultParallelism
    return df if 2 * df.rdd.getNumPartitions() > cores else df.repartition(cores, key)


def as_samples(df: DataFrame, pool: str) -> DataFrame:
    """df in the sample layout; columns that it lacks are null."""
    have = set(df.columns)
    out = []
    for f in schema.struct(schema.SAMPLE):
        value = F.lit(pool) if f.name == "pool" else F.col(f.name) if f.name in have else F.lit(None)
        out.append(value.cast(f.dataType).alias(f.name))
    return df.select(out)


def from_documents(docs: DataFrame, pool: str = "documents") -> DataFrame:
    """First line as instruction, the rest as output."""
    return as_samples(
        docs.select(F.col("doc_id").alias("sample_id"), X.lead_line("text").alias("instruction"), F.lit("").alias("input"), X.rest_lines("text").alias("output"), "text", "lang", "source", "n_chars"), pool
    )


def chat_turns(chats: DataFrame) -> DataFrame:
    """Turns with the next turn's role and text, and the conversation's system text."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    return chats.select(
        "conv_id",
        "turn",
        "role",
        "text",
        F.lead("role").over(w).alias("next_role"),
        F.lead("text").over(w).alias("next_text"),
        F.coalesce(F.max(F.when(F.col("role") == "system", F.col("text"))).over(Window.partitionBy("conv_id")), F.lit("")).alias("system"),
    )


def chat_pairs(chats: DataFrame, first_only: bool = False, pool: str = "chat") -> DataFrame:
    """User turns answered by the next turn."""
    pairs = chat_turns(chats).where("role = 'user' AND next_role = 'assistant'")
    if first_only:
        pairs = pairs.withColumn("rn", F.row_number().over(Window.partitionBy("conv_id").orderBy("turn"))).where("rn = 1")
    return as_samples(
        pairs.select(
            (F.col("conv_id") * 1000 + F.col("turn")).alias("sample_id"),
            F.col("text").alias("instruction"),
            F.col("system").alias("input"),
            F.col("next_text").alias("output"),
            F.concat_ws("\n", "text", "next_text").alias("text"),
        ),
        pool,
    )


def chat_history(chats: DataFrame, pool: str = "history") -> DataFrame:
    """Assistant turns with all earlier turns as instruction."""
    w = Window.partitionBy("conv_id").orderBy("turn").rowsBetween(Window.unboundedPreceding, -1)
    said = chats.withColumn("line", F.concat(F.col("role"), F.lit(": "), F.col("text")))
    rows = said.withColumn("history", F.array_join(F.collect_list("line").over(w), "\n")).where("role = 'assistant'")
    return as_samples(
        rows.select(
            (F.col("conv_id") * 1000 + F.col("turn")).alias("sample_id"), F.col("history").alias("instruction"), F.lit("").alias("input"), F.col("text").alias("output"), F.concat_ws("\n", "history", "text").alias("text")
        ),
        pool,
    )


def page_text(html) -> F.Column:
    """Visible text: scripts, styles and tags go, common entities are decoded, white space is collapsed."""
    t = F.regexp_replace(html, r"(?is)<(script|style)\b[^>]*>.*?</(script|style)>", " ")
    t = F.regexp_replace(t, r"(?s)<[^>]*>", " ")
    for name, sign in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&amp;", "&")):
        t = F.replace(t, F.lit(name), F.lit(sign))
    return F.trim(F.regexp_replace(t, r"[ \t\r\n]+", " "))


def from_pages(pages: DataFrame, pool: str = "pages") -> DataFrame:
    title = F.regexp_extract("html", r"(?is)<title>(.*?)</title>", 1)
    body = page_text(F.regexp_replace("html", r"(?is)^.*?</head>", " "))
    return as_samples(pages.select(F.col("page_id").alias("sample_id"), title.alias("instruction"), F.col("url").alias("input"), body.alias("output"), F.concat_ws("\n", title, body).alias("text")), pool)


def pool_of(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The pools of the experiments by name."""
    docs = from_documents(read_spread(spark, sf_dir, "documents", "doc_id"))
    if name == "SD-1":
        return docs.where("lang = 'en'")
    if name == "SD-2":
        return docs.where("lang = 'en' AND cast(substr(source, 4) AS int) % 2 = 1")
    if name == "SD-3":
        return docs.where("lang = 'fr'")
    if name == "SD-4":
        return docs.where("lang IN ('fr', 'es')")
    if name == "MD-1":
        return docs
    chats = read_table(spark, sf_dir, "conversations")
    if name == "SD-5":
        return chat_pairs(chats)
    if name == "SD-6":
        return chat_pairs(chats, first_only=True)
    if name == "MD-2":
        # Chat ids are turned negative, so that they never meet a document's.
        return docs.unionByName(chat_pairs(chats).withColumn("sample_id", -F.col("sample_id") - 1))
    raise KeyError(name)
