"""Relational operators that Spark lacks or that need care at scale: range, interval and as-of joins, salting, running totals."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

BROADCAST_ROWS = 1_000_000


def join_checked(left: DataFrame, right: DataFrame, on: list[str], how: str = "inner", most: int = BROADCAST_ROWS) -> DataFrame:
    """left joined with right, which is broadcast only if its counted rows are within the limit."""
    return left.join(F.broadcast(right) if right.count() <= most else right, on, how)


def running_total(df: DataFrame, value: str, order: str, parts: int | None = None) -> DataFrame:
    """df with `total`, the running sum in the given order, ties together.

    Rows are range-partitioned; each range starts from the sum of the ranges before it, one row per
    range on the driver.
    """
    n = parts or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = df.repartitionByRange(n, order).withColumn("_p", F.spark_partition_id()).persist()
    before, total = [], 0
    for r in dealt.groupBy("_p").agg(F.sum(value).alias("s")).orderBy("_p").collect():
        before.append((r["_p"], total))
        total += r["s"] or 0
    kind = "double" if dict(df.dtypes)[value] in ("double", "float") else "long"
    offsets = df.sparkSession.createDataFrame([(p, float(t) if kind == "double" else t) for p, t in before or [(0, 0)]], f"_p int, _off {kind}")
    inside = F.sum(value).over(Window.partitionBy("_p").orderBy(order))
    return dealt.join(F.broadcast(offsets), "_p").withColumn("total", inside + F.col("_off")).drop("_p", "_off")


def range_join(points: DataFrame, cells: DataFrame, x: str, lo: str, hi: str, width: int) -> DataFrame:
    """Points with the cells lo <= x < hi: both are cut into bins of the given width, an equi-join key."""
    bins = cells.withColumn("_bin", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    return points.withColumn("_bin", F.floor(F.col(x) / width)).join(bins, "_bin").where((F.col(x) >= F.col(lo)) & (F.col(x) < F.col(hi))).drop("_bin")


def interval_pairs(events: DataFrame, first: str, then: str, seconds: int) -> DataFrame:
    """(view_id, purchase_id): events of two types of one user at most so many seconds apart, in order.

    Time is cut into bins as long as the interval, so a pair meets in the first event's bin or the next.
    """
    t = F.unix_micros(F.col("ts").cast("timestamp"))
    width = seconds * 1_000_000
    a = events.where(F.col("event_type") == first).select(F.col("event_id").alias("view_id"), "user_id", t.alias("t1"))
    a = a.withColumn("bin", F.explode(F.array(F.floor(F.col("t1") / width), F.floor(F.col("t1") / width) + 1)))
    b = events.where(F.col("event_type") == then).select(F.col("event_id").alias("purchase_id"), "user_id", t.alias("t2"), F.floor(t / width).alias("bin"))
    return a.join(b, ["user_id", "bin"]).where((F.col("t2") >= F.col("t1")) & (F.col("t2") <= F.col("t1") + width)).select("view_id", "purchase_id")


def asof(left: DataFrame, right: DataFrame, by: str, order: str, value: str) -> DataFrame:
    """left with the latest value of right at or before its time: one shuffle by key, one sorted pass. Of equal times the largest value counts."""
    have = set(left.columns)
    rows = left.withColumns({value: F.lit(None).cast(dict(right.dtypes)[value]), "_left": F.lit(1)}).unionByName(right.withColumn("_left", F.lit(0)), allowMissingColumns=True)
    w = Window.partitionBy(by).orderBy(order, "_left", F.asc_nulls_first(value)).rowsBetween(Window.unboundedPreceding, 0)
    return rows.withColumn(value, F.last(value, ignorenulls=True).over(w)).where("_left = 1").select(*[c for c in left.columns if c in have], value)


def salted_sum(df: DataFrame, key: str, value: str, spread: str, salts: int = 16) -> DataFrame:
    """(key, n, total) in two steps, so no task holds all rows of a hot key even where partial aggregation fails."""
    part = df.groupBy(key, F.pmod(F.xxhash64(spread), F.lit(salts)).alias("_salt")).agg(F.count(F.lit(1)).alias("n"), F.sum(value).alias("total"))
    return part.groupBy(key).agg(F.sum("n").alias("n"), F.sum("total").alias("total"))


def salted_join(rows: DataFrame, groups: DataFrame, key: str, spread: str, salts: int = 16) -> DataFrame:
    """rows joined with one row per key, the hot keys' rows dealt over `salts` tasks and the small side repeated as often."""
    a = rows.withColumn("_salt", F.pmod(F.xxhash64(spread), F.lit(salts)).cast("int"))
    b = groups.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [key, "_salt"]).drop("_salt")


def first_of_each(df: DataFrame, column: str, key: str) -> DataFrame:
    """(key, copies): the least id of every different value; only digests are shuffled."""
    return df.groupBy(F.sha2(column, 256).alias("_d")).agg(F.min(key).alias(key), F.count(F.lit(1)).alias("copies")).drop("_d")


def repeated_lines(df: DataFrame, more_than: int, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(line, docs): lines that occur in more than so many rows; a row's own repeats are dropped before the shuffle."""
    lines = df.select(key, F.explode(F.array_distinct(F.split(text, "\n"))).alias("line")).where(F.length("line") > 0)
    return lines.groupBy("line").agg(F.count(F.lit(1)).alias("docs")).where(F.col("docs") > more_than)
