"""Parameter shift of a linear probe after one optimiser step on one sample.

The probe maps the prompt's vector e_x to the answer's: loss 1/2 |W e_x - e_y|^2, so its gradient is
the outer product of the residual r = W e_x - e_y with e_x. The model is never changed, so a
sample's score cannot depend on the order of samples.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from poolcurator.functions import text as X

BUCKETS = 16


def token_vectors(samples: DataFrame, columns: tuple[str, ...], buckets: int = BUCKETS, key: str = "sample_id") -> DataFrame:
    """(key, one array per column): shares of a text's tokens by md5 bucket; all zero without tokens.

    Tokens are counted by bucket in the tasks before the one shuffle.
    """
    sides = F.array(*[F.struct(F.lit(c).alias("side"), X.tokens(c).alias("t")) for c in columns])
    words = X.explode_rows(X.explode_rows(samples, [key], sides, "s"), [key, F.col("s.side").alias("side")], F.col("s.t"), "w")
    bucket = F.pmod(F.conv(F.substring(F.md5("w"), 1, 4), 16, 10).cast("int"), F.lit(buckets))
    counts = words.groupBy(key, "side", bucket.alias("b")).agg(F.count(F.lit(1)).alias("n"))
    maps = counts.groupBy(key).agg(*[F.map_from_entries(F.collect_list(F.when(F.col("side") == c, F.struct("b", "n")))).alias(f"_{c}") for c in columns])
    line = F.sequence(F.lit(0), F.lit(buckets - 1))

    def shares(c: str) -> Column:
        total = F.aggregate(F.map_values(f"_{c}"), F.lit(0).cast("long"), lambda a, x: a + x)
        return F.transform(line, lambda i: F.when(total > 0, F.coalesce(F.try_element_at(f"_{c}", i), F.lit(0)) / total).otherwise(F.lit(0.0)))

    return samples.select(key).join(maps, key, "left").select(key, *[shares(c).alias(c) for c in columns])


def mean_abs(a: Column | str) -> Column:
    c = X.col(a)
    return F.aggregate(c, F.lit(0.0), lambda s, x: s + F.abs(x)) / F.size(c)


def residual(e_x: str, e_y: str, scale: float = 0.5) -> Column:
    """W e_x - e_y for W = scale * identity."""
    return F.zip_with(X.col(e_x), X.col(e_y), lambda a, b: a * scale - b)


def shift_sgd(r: str, e: str, lr: float = 1e-5) -> Column:
    return lr * mean_abs(r) * mean_abs(e)


def shift_adamw(r: str, e: str, lr: float = 1e-5, eps: float = 1e-8, decay: float = 0.0, scale: float = 0.5) -> Column:
    """Mean absolute change after a first AdamW step from fresh state: lr g/(|g|+eps) plus decay of the weight."""
    rs, es = X.col(r), X.col(e)

    def row(x, i):
        def cell(y, j):
            g = x * y
            w = F.when(i == j, F.lit(scale)).otherwise(F.lit(0.0))
            return F.abs(lr * g / (F.abs(g) + eps) + lr * decay * w)

        return F.aggregate(F.transform(es, cell), F.lit(0.0), lambda s, v: s + v)

    return F.aggregate(F.transform(rs, row), F.lit(0.0), lambda s, v: s + v) / (F.size(rs) * F.size(es))


def mean_diff(samples: DataFrame, optimizer: str = "adamw", lr: float = 1e-5, layers: int = 1, key: str = "sample_id") -> DataFrame:
    """(key, mean_diff); with several layers the shifts of probes over different hashes are averaged."""
    rows = None
    for n in range(layers):
        v = token_vectors(samples, ("instruction", "output"), BUCKETS + n, key).withColumnsRenamed({"instruction": f"x{n}", "output": f"y{n}"})
        rows = v if rows is None else rows.join(v, key)
    rows = rows.withColumns({f"r{n}": residual(f"x{n}", f"y{n}") for n in range(layers)})
    step = shift_adamw if optimizer == "adamw" else shift_sgd
    total = sum((step(f"r{n}", f"x{n}", lr) for n in range(layers)), F.lit(0.0)) / layers
    return rows.select(key, total.alias("mean_diff"))
