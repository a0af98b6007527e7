"""Stage 3: model-relative metrics, min-max, orientation, weighted score, top k*."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from poolcurator.backbone.core import Backbone, CostLedger, ask
from poolcurator.config import METRICS, SelectionRequest, Weights
from poolcurator.functions import text as X
from poolcurator.operators.embed import bigram_buckets, bigrams, bucket_of
from poolcurator.operators.topk import top_k
from poolcurator.target.probe import mean_diff


def bucket_vectors(samples: DataFrame, text: str, key: str = "sample_id") -> DataFrame:
    """(key, norm, buckets): sparse bigram counts."""
    return bigram_buckets(samples.select(key, F.col(text)), key, text)


def drift(samples: DataFrame, said: str = "generated", wanted: str = "output", key: str = "sample_id") -> DataFrame:
    """(key, drift): 1 - cosine of the two texts' encodings; 1 if either is empty.

    Both texts' bigrams come from one scan: Spark 4.1 plans an aggregate above a union of sides that are dealt by the
    key without a shuffle, and fails when their partitions add up.
    """
    of = lambda c, side: F.transform(F.coalesce(bigrams(c), F.array().cast("array<string>")), lambda g: F.struct(g.alias("g"), F.lit(side).alias("side")))
    grams = X.explode_rows(samples, [key], F.concat(of(said, 0), of(wanted, 1)), "t").select(key, "t.g", "t.side")
    counts = grams.groupBy(key, "g").agg(F.count_if(F.col("side") == 0).alias("a"), F.count_if(F.col("side") == 1).alias("b"))
    per = counts.groupBy(key, bucket_of("g").alias("bucket")).agg(F.sum("a").cast("double").alias("a"), F.sum("b").cast("double").alias("b"))
    sums = per.groupBy(key).agg(F.sum(F.col("a") * F.col("b")).alias("ab"), F.sum(F.col("a") * F.col("a")).alias("aa"), F.sum(F.col("b") * F.col("b")).alias("bb"))
    cos = F.when((F.col("aa") > 0) & (F.col("bb") > 0), F.col("ab") / F.sqrt(F.col("aa") * F.col("bb"))).otherwise(0.0)
    return samples.select(key).join(sums, key, "left").select(key, (1 - F.coalesce(cos, F.lit(0.0))).alias("drift"))


def measure(samples: DataFrame, target, generate: bool = True, optimizer: str = "adamw", lr: float = 1e-5, key: str = "sample_id", moved: DataFrame | None = None) -> DataFrame:
    """(key, loss, entropy, drift, mean_diff) of every sample.

    The parameter shift is the model's own where it brings one (`shift`), that of its count table with
    optimizer "table", else that of the probe, which knows no model: `moved` is its result where it is at hand. A model
    that cannot generate is judged by the prompt.
    """
    out = samples.select(key).join(target.metrics(samples, key), key, "left")
    if generate and hasattr(target, "generate"):
        said = samples.select(key, "output").join(target.generate(samples, key=key), key)
    else:
        said = samples.select(key, "output", F.col("instruction").alias("generated"))
    if hasattr(target, "shift"):
        moved = target.shift(samples, lr, key)
    elif optimizer == "table":
        moved = target.table_shift(samples, lr, key)
    elif moved is None:
        moved = mean_diff(samples, optimizer, lr, key=key)
    return out.join(drift(said, key=key), key).join(moved, key, "left")


def minmax(df: DataFrame, columns: tuple[str, ...] = METRICS, bounds: dict | None = None) -> DataFrame:
    """Columns scaled to 0..1 by one fused aggregate; constant columns become 0. bounds: frozen minima and maxima instead."""
    if bounds is None:
        row = df.agg(*[f(c).alias(f"{n}_{c}") for c in columns for n, f in (("lo", F.min), ("hi", F.max))]).first()
        bounds = {c: (row[f"lo_{c}"], row[f"hi_{c}"]) for c in columns}
    scaled = {}
    for c in columns:
        lo, hi = bounds[c]
        scaled[c] = F.lit(0.0) if lo is None or hi is None or hi <= lo else (F.col(c) - lo) / (hi - lo)
    return df.withColumns({c: F.when(F.col(c).isNull(), F.lit(None)).otherwise(v) for c, v in scaled.items()})


def clip(df: DataFrame, columns: tuple[str, ...] = METRICS, low: float = 0.01, high: float = 0.99) -> DataFrame:
    """Columns held within two quantiles, before min-max (an extension: one extreme row squeezes all others)."""
    q = df.agg(*[F.percentile_approx(c, F.array(F.lit(low), F.lit(high))).alias(c) for c in columns]).first()
    return df.withColumns({c: F.greatest(F.lit(q[c][0]), F.least(F.lit(q[c][1]), F.col(c))) for c in columns if q[c]})


def orient(df: DataFrame) -> DataFrame:
    """A small parameter shift is good, so mean_diff is turned round after scaling."""
    return df.withColumn("mean_diff", 1 - F.col("mean_diff"))


def composite(df: DataFrame, weights: Weights, out: str = "score") -> DataFrame:
    total = F.lit(0.0)
    for m, w in weights.to_dict().items():
        total = total + w * F.coalesce(m, F.lit(0.0))
    return df.withColumn(out, total)


def informative(metrics: DataFrame, weights: Weights, k_star: int, key: str = "sample_id", bounds: dict | None = None) -> DataFrame:
    """The best k* samples by the weighted, oriented, scaled metrics."""
    return top_k(composite(orient(minmax(metrics, bounds=bounds)), weights).withColumn("score", F.round("score", 6)), "score", k_star, key)


def propose_weights(request: SelectionRequest, observations: dict, backbone: Backbone, max_retries: int = 3, ledger: CostLedger | None = None) -> Weights:
    return ask(backbone, "weights", {"request": request.text, "observations": observations}, Weights.parse, max_retries, ledger)


def given_metrics(samples: DataFrame, key: str = "sample_id") -> DataFrame:
    """Seeded stand-in metrics for parity of scaling, score and top-k without a model."""
    return samples.select(key, *[X.seeded_uniform(key, m).alias(m) for m in METRICS])
