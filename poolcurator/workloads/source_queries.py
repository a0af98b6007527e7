"""Queries of sources, adapters, and the batch twins of the streaming operators."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from poolcurator.config import Policy
from poolcurator.registry import query
from poolcurator.sources import adapters as A
from poolcurator.sources import files
from poolcurator.streaming import events as S
from poolcurator.workloads.cascade_sql import policy_sql
from poolcurator.workloads.common import FDOC, read_table, uniform_sql


@query("scan_parquet", "SELECT doc_id, n_chars FROM documents WHERE n_chars BETWEEN 100 AND 500")
def scan_parquet(spark, d):
    return read_table(spark, d, "documents").where("n_chars BETWEEN 100 AND 500").select("doc_id", "n_chars")


def round_trip(name: str, table: str, fmt: str, order: list[str]):
    @query(f"scan_{name}", f"SELECT {', '.join(order)} FROM {table}")
    def run(spark, d):
        return files.round_trip(read_table(spark, d, table).select(*order), fmt)


round_trip("jsonl", "conversations", "json", ["conv_id", "turn", "role", "text"])
round_trip("csv", "nation", "csv", ["n_nationkey", "n_name", "n_regionkey"])
round_trip("orc", "customer", "orc", ["c_custkey", "c_name", "c_nationkey", "c_acctbal"])


@query("scan_corrupt", "SELECT conv_id % 5 = 4 AS bad, count(*) AS n FROM conversations GROUP BY ALL")
def scan_corrupt(spark, d):
    """Every fifth conversation's lines are cut; they are caught, not lost."""
    rows = read_table(spark, d, "conversations")
    line = F.to_json(F.struct("conv_id", "turn", "role", "text"))
    lines = rows.select(F.when(F.col("conv_id") % 5 == 4, F.substring(line, 1, 12)).otherwise(line).alias("value"))
    return files.parse_jsonl(lines, "conv_id long, turn long, role string, text string").groupBy(F.col("_corrupt").isNotNull().alias("bad")).agg(F.count(F.lit(1)).alias("n"))


@query("scan_metadata")
def scan_metadata(spark, d):
    return read_table(spark, d, "documents").select("doc_id", F.col("_metadata.file_name").alias("file"), F.col("_metadata.file_block_length").alias("bytes"))


@query("sink_partitioned", "SELECT lang, count(*) AS n FROM documents WHERE lang IN ('de', 'fr') GROUP BY lang")
def sink_partitioned(spark, d):
    """Written by language; the filter prunes partitions on the way back."""
    path = files.scratch(spark, "by-lang")
    read_table(spark, d, "documents").select("doc_id", "lang").write.partitionBy("lang").parquet(path)
    return spark.read.schema("doc_id long, lang string").parquet(path).where("lang IN ('de', 'fr')").groupBy("lang").agg(F.count(F.lit(1)).alias("n"))


def bucketed_join(spark, d):
    """Documents and labels in the same buckets by id, joined without a shuffle."""
    name = f"pc_{uuid.uuid4().hex[:12]}"
    a = files.write_bucketed(read_table(spark, d, "documents").select("doc_id", "lang"), f"{name}_documents", "doc_id", 8)
    b = files.write_bucketed(read_table(spark, d, "labels").select("doc_id", "quality"), f"{name}_labels", "doc_id", 8)
    return a.hint("merge").join(b, "doc_id")


@query("sink_bucketed", "SELECT lang, count(*) AS n, sum(quality) AS good FROM documents JOIN labels USING (doc_id) GROUP BY lang")
def sink_bucketed(spark, d):
    return bucketed_join(spark, d).groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.sum("quality").alias("good"))


ENT = "replace(replace(replace(replace(replace({}, '&nbsp;', ' '), '&lt;', '<'), '&gt;', '>'), '&quot;', '\"'), '&amp;', '&')"
BODY = "trim(regexp_replace(" + ENT.format("regexp_replace(regexp_replace(regexp_replace(html, '(?is)^.*?</head>', ' '), '(?is)<(script|style)\\b[^>]*>.*?</(script|style)>', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g')") + ", '[ \\t\\r\\n]+', ' ', 'g'))"


@query("ingest_pages", f"SELECT page_id, regexp_extract(html, '(?is)<title>(.*?)</title>', 1) AS title, {BODY} AS body FROM pages")
def ingest_pages(spark, d):
    return A.from_pages(read_table(spark, d, "pages")).select(F.col("sample_id").alias("page_id"), F.col("instruction").alias("title"), F.col("output").alias("body"))


TURNS = "tn AS (SELECT *, lead(role) OVER w AS nr, lead(text) OVER w AS nt FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn))"


@query("adapt_chat_pairs", f"WITH {TURNS} SELECT conv_id * 1000 + turn AS sample_id, text AS instruction, nt AS output FROM tn WHERE role = 'user' AND nr = 'assistant'")
def adapt_chat_pairs(spark, d):
    return A.chat_pairs(read_table(spark, d, "conversations")).select("sample_id", "instruction", "output")


@query("adapt_chat_first", f"WITH {TURNS} SELECT conv_id * 1000 + turn AS sample_id FROM tn WHERE role = 'user' AND nr = 'assistant' QUALIFY row_number() OVER (PARTITION BY conv_id ORDER BY turn) = 1")
def adapt_chat_first(spark, d):
    return A.chat_pairs(read_table(spark, d, "conversations"), first_only=True).select("sample_id")


@query("adapt_chat_history", "SELECT conv_id * 1000 + turn AS sample_id, h AS instruction FROM (SELECT conv_id, turn, role, coalesce(string_agg(role || ': ' || text, chr(10) ORDER BY turn) OVER (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), '') AS h FROM conversations) WHERE role = 'assistant'")
def adapt_chat_history(spark, d):
    return A.chat_history(read_table(spark, d, "conversations")).select("sample_id", "instruction")


@query("adapt_documents", f"WITH {FDOC} SELECT sample_id, instruction, output FROM fdoc")
def adapt_documents(spark, d):
    return A.from_documents(read_table(spark, d, "documents")).select("sample_id", "instruction", "output")


# ---- batch twins of the streaming operators ------------------------------------------------------


@query("events_tumbling", "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def events_tumbling(spark, d):
    return S.tumbling(read_table(spark, d, "events"), "1 hour").select(F.col("window.start").alias("start"), "event_type", "n", F.round("total", 4).alias("total"))


@query("events_sliding", "SELECT start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 30 MINUTE, ts), time_bucket(INTERVAL 30 MINUTE, ts) - INTERVAL 30 MINUTE]) AS start FROM events) GROUP BY start")
def events_sliding(spark, d):
    return S.sliding(read_table(spark, d, "events"), "1 hour", "30 minutes").select(F.col("window.start").alias("start"), "n")


@query(
    "events_session",
    "WITH g AS (SELECT *, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS sid FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, sid",
)
def events_session(spark, d):
    return S.sessions(read_table(spark, d, "events"), "30 minutes").select("user_id", F.col("session.start").alias("start"), "n")


@query("events_watermark_dedup", "SELECT user_id, event_type, date_trunc('day', ts)::timestamp AS day, count(*) AS n FROM (SELECT DISTINCT user_id, event_type, ts FROM events) GROUP BY ALL")
def events_watermark_dedup(spark, d):
    e = read_table(spark, d, "events").select("user_id", "event_type", "ts").dropDuplicates()
    return e.groupBy("user_id", "event_type", F.date_trunc("day", "ts").cast("timestamp_ntz").alias("day")).agg(F.count(F.lit(1)).alias("n"))


@query("events_stream_join", "SELECT c_mktsegment, event_type, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY ALL")
def events_stream_join(spark, d):
    return S.with_static(read_table(spark, d, "events"), read_table(spark, d, "customer")).groupBy("c_mktsegment", "event_type").agg(F.count(F.lit(1)).alias("n"))


REPLAYED = " + ".join(f"{w} * " + (f"(1 - {uniform_sql('sample_id', m)})" if m == "mean_diff" else uniform_sql("sample_id", m)) for m, w in S.WEIGHTS.to_dict().items())


@query("stream_replay_scored", f"WITH {FDOC}, s AS (SELECT sample_id, {REPLAYED} AS score FROM fdoc WHERE {policy_sql(Policy())}) SELECT sample_id, round(score, 6) AS score FROM s WHERE score >= {S.FLOOR}")
def stream_replay_scored(spark, d):
    """Documents replayed by a file stream through the frozen policy and score, all available rows in one run."""
    return S.replay_documents(spark, d)
