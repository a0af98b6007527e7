"""Streaming operators; each takes a batch or a streaming DataFrame, so batch results are the oracle."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from poolcurator.config import METRICS, Policy, Weights
from poolcurator.sources.adapters import from_documents
from poolcurator.sources.files import drop_folder, scratch
from poolcurator.stages import characteristic
from poolcurator.stages.informativeness import composite, minmax, orient


def tumbling(events: DataFrame, length: str, late: str | None = None) -> DataFrame:
    e = events.withWatermark("ts", late) if late else events
    return e.groupBy(F.window("ts", length), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))


def sliding(events: DataFrame, length: str, step: str, late: str | None = None) -> DataFrame:
    e = events.withWatermark("ts", late) if late else events
    return e.groupBy(F.window("ts", length, step)).agg(F.count(F.lit(1)).alias("n"))


def sessions(events: DataFrame, gap: str, late: str | None = None) -> DataFrame:
    e = events.withWatermark("ts", late) if late else events
    return e.groupBy(F.session_window("ts", gap).alias("session"), "user_id").agg(F.count(F.lit(1)).alias("n"))


def deduplicated(events: DataFrame, late: str = "10 minutes", keys: tuple[str, ...] = ("event_id",)) -> DataFrame:
    """Rows whose key was not seen within the watermark; state is dropped behind it."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(list(keys))


def with_static(events: DataFrame, customers: DataFrame, most: int = 1_000_000) -> DataFrame:
    """Events with their customer's segment; the static side is broadcast if its count allows."""
    c = customers.select("c_custkey", "c_mktsegment")
    return events.join(F.broadcast(c) if c.count() <= most else c, F.col("user_id") == F.col("c_custkey"))


def paired(events_a: DataFrame, events_b: DataFrame, first: str = "view", then: str = "purchase", within: str = "10 minutes", late: str = "10 minutes") -> DataFrame:
    """Stream-stream join: `then` events at most `within` after a `first` event of the same user."""
    a = events_a.where(F.col("event_type") == first).select(F.col("event_id").alias("view_id"), F.col("user_id").alias("u1"), F.col("ts").alias("t1")).withWatermark("t1", late)
    b = events_b.where(F.col("event_type") == then).select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("u2"), F.col("ts").alias("t2")).withWatermark("t2", late)
    return a.join(b, F.expr(f"u1 = u2 AND t2 >= t1 AND t2 <= t1 + INTERVAL {within}")).select("view_id", "purchase_id")


def scored(samples: DataFrame, policy: Policy, weights: Weights, bounds: dict, metrics, floor: float) -> DataFrame:
    """Arriving samples through a frozen configuration: policy, metrics scaled by stored bounds, weighted score, threshold."""
    s = metrics(characteristic.match(samples, policy))
    return composite(orient(minmax(s, METRICS, bounds)), weights).where(F.col("score") >= floor)


def running_top_k(stream: DataFrame, path: str, k: int, score: str = "score", key: str = "sample_id"):
    """A writer that keeps the best k rows so far in a table of k rows, replaced at every micro-batch."""

    def merge(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        last = f"{path}/{number - 1}"
        rows = batch
        if number:
            rows = batch.unionByName(spark.read.schema(batch.schema).parquet(last))
        rows.orderBy(F.desc(score), key).limit(k).write.mode("overwrite").parquet(f"{path}/{number}")
        if number > 1:  # a batch that runs again needs the one before it, and no older one
            drop_folder(spark, f"{path}/{number - 2}")

    return stream.writeStream.foreachBatch(merge)


def pass_rate_alarm(samples: DataFrame, policy: Policy, frozen: float, tolerance: float = 0.05, length: str | None = None, late: str | None = None) -> DataFrame:
    """Share of passing rows per source, and per window of ts where a length is given, and whether it left the frozen rate."""
    ok = F.avg(F.coalesce(characteristic.compile_policy(policy), F.lit(False)).cast("double"))
    rows = samples.withWatermark("ts", late) if late else samples
    by = [F.window("ts", length), F.col("source")] if length else [F.col("source")]
    return rows.groupBy(*by).agg(F.round(ok, 6).alias("rate"), F.count(F.lit(1)).alias("n")).withColumn("alarm", F.abs(F.col("rate") - frozen) > tolerance)


def late_rows(query: StreamingQuery) -> int:
    """Rows that the query's stateful operators dropped because they came after the watermark had passed."""
    return sum(s.numRowsDroppedByWatermark for p in query.recentProgress for s in p.stateOperators)


#: A frozen configuration for replays.
WEIGHTS = Weights(0.20, 0.15, 0.25, 0.40)
BOUNDS = {m: (0.0, 1.0) for m in METRICS}
FLOOR = 0.5


def seeded_metrics(df: DataFrame) -> DataFrame:
    from poolcurator.functions.text import seeded_uniform

    return df.select("sample_id", *[seeded_uniform("sample_id", m).alias(m) for m in METRICS])


def replay_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(sample_id, score): documents replayed by a file stream through the frozen configuration."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    source, out, mark = scratch(spark, "replay-in"), scratch(spark, "replay-out"), scratch(spark, "replay-mark")
    docs.write.parquet(source)
    stream = from_documents(spark.readStream.schema(docs.schema).parquet(source))
    rows = scored(stream, Policy(), WEIGHTS, BOUNDS, seeded_metrics, FLOOR).select("sample_id", F.round("score", 6).alias("score"))
    q = rows.writeStream.format("parquet").option("path", out).option("checkpointLocation", mark).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(rows.schema).parquet(out)
