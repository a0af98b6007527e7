"""The best k rows by a score, ties by id."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from poolcurator.functions.text import seeded_key
from poolcurator.sources.files import durable

#: Up to this many rows a bounded heap per task is used; beyond it a threshold.
HEAP_ROWS = 100_000


def top_k(df: DataFrame, score: str, k: int, key: str = "sample_id", ties: tuple[str, ...] = (), ascending: bool = False) -> DataFrame:
    """The k rows with the best score; nulls come last, ties by the further scores, then the least id."""
    order = [F.asc_nulls_last(score) if ascending else F.desc_nulls_last(score), *[F.desc_nulls_last(t) for t in ties], F.asc(key)]
    if k <= HEAP_ROWS:
        return df.orderBy(*order).limit(k)
    return threshold_top_k(df, score, k, key, ascending, ties=ties)


def threshold_top_k(df: DataFrame, score: str, k: int, key: str = "sample_id", ascending: bool = False, accuracy: int = 100_000, ties: tuple[str, ...] = ()) -> DataFrame:
    """The same rows without sorting all: a quantile sketch bounds the k-th score, and only the band around it is sorted.

    Three scans of a narrow table; rows surely above the band are kept unsorted.
    """
    value = F.col(score).cast("double")
    value = -value if ascending else value
    rows = df.withColumn("_v", F.coalesce(value, F.lit(float("-inf"))))
    n = rows.count()
    if n <= k:
        return rows.drop("_v")
    order = [F.desc("_v"), *[F.desc_nulls_last(t) for t in ties], F.asc(key)]
    p, slack = 1 - k / n, 2.0 / accuracy
    lo, hi = rows.agg(F.percentile_approx("_v", F.array(F.lit(max(0.0, p - slack)), F.lit(min(1.0, p + slack))), F.lit(accuracy))).first()[0]
    above, within = rows.agg(F.count_if(F.col("_v") > hi), F.count_if(F.col("_v") >= lo)).first()
    if above > k or within < k:  # the sketch was off: fall back to an exact sort
        return rows.orderBy(*order).limit(k).drop("_v")
    band = rows.where((F.col("_v") <= hi) & (F.col("_v") >= lo)).orderBy(*order).limit(k - above)
    return rows.where(F.col("_v") > hi).unionByName(band).drop("_v")


def with_rank(df: DataFrame, score: str, k: int, key: str = "sample_id", out: str = "rank", heap_rows: int = HEAP_ROWS) -> DataFrame:
    """df with its place by falling score, nulls last, ties by id; k bounds its rows.

    Up to heap_rows one task numbers them. Beyond it, ranges of the order are written, counted (one row per range
    on the driver) and numbered each by itself.
    """
    order = [F.desc_nulls_last(score), F.asc(key)]
    if k <= heap_rows:
        return df.withColumn(out, F.row_number().over(Window.orderBy(*order)))
    parts = max(1, -(-k // heap_rows))
    dealt = durable(df.repartitionByRange(parts, *order).withColumn("_p", F.spark_partition_id()), "ranges")
    before, total = [], 0
    for r in dealt.groupBy("_p").agg(F.count(F.lit(1)).alias("n")).orderBy("_p").collect():
        before.append((r["_p"], total))
        total += r["n"]
    offsets = F.broadcast(df.sparkSession.createDataFrame(before or [(0, 0)], "_p int, _off int"))
    inside = F.row_number().over(Window.partitionBy("_p").orderBy(*order))
    return dealt.withColumn(out, inside).join(offsets, "_p").withColumn(out, F.col(out) + F.col("_off")).drop("_p", "_off")


def rehydrate(pool: DataFrame, ids: DataFrame, key: str = "sample_id", small: int = 1_000_000) -> DataFrame:
    """Rows of the pool whose id is selected; the ids are broadcast only if their counted number allows it."""
    ids = ids.select(key)
    return pool.join(F.broadcast(ids) if ids.count() <= small else ids, key, "left_semi")


def random_k(df: DataFrame, k: int, seed: int = 42, key: str = "sample_id") -> DataFrame:
    """k rows drawn uniformly without replacement, the same on every partitioning."""
    return df.withColumn("_key", seeded_key(key, seed)).orderBy("_key", key).limit(k).drop("_key")


def per_group(df: DataFrame, group: str, n: int, seed: int = 42, key: str = "sample_id") -> DataFrame:
    """n seeded rows of every group; each task keeps n candidates a group before the shuffle."""
    w = Window.partitionBy(group).orderBy(seeded_key(key, seed), key)
    return df.withColumn("_rn", F.row_number().over(w)).where(F.col("_rn") <= n).drop("_rn")


def gumbel(key: str, salt: str = "gumbel") -> F.Column:
    """A seeded Gumbel draw per id."""
    from poolcurator.functions.text import seeded_uniform

    u = F.greatest(F.lit(1e-9), F.least(F.lit(1 - 1e-9), seeded_uniform(key, salt)))
    return -F.log(-F.log(u))
