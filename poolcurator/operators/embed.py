"""Embeddings of texts: hashed character bigrams, tables of given vectors, or a hook for a model."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from poolcurator.functions import text as X

DIMENSIONS = 256


def bigrams(text: str) -> F.Column:
    """Lower-case character bigrams of a column."""
    low = F.lower(F.col(text))
    # Pairs from the first character on and from the second on: every bigram once, in linear time.
    pair = F.lit("(?s)..")
    return F.concat(F.regexp_extract_all(low, pair, F.lit(0)), F.regexp_extract_all(F.substring(low, 2, 2_000_000_000), pair, F.lit(0)))


def bucket_of(gram: str) -> F.Column:
    return F.pmod(F.conv(F.substring(F.md5(gram), 1, 4), 16, 10).cast("int"), F.lit(DIMENSIONS))


def bigram_buckets(df: DataFrame, key: str = "sample_id", text: str = "text") -> DataFrame:
    """(key, bucket, n): counts of lower-case character bigrams by the first two bytes of their md5, modulo 256.

    Different bigrams are few, so they are counted per text before hashing.
    """
    low, grams = F.lower(F.col(text)), bigrams(text)
    rows = X.explode_rows(df.where(F.length(low) >= 2), [key], grams, "g").groupBy(key, "g").agg(F.count(F.lit(1)).alias("c"))
    return rows.groupBy(key, bucket_of("g").alias("bucket")).agg(F.sum("c").alias("n"))


def hashed_vectors(texts: pd.Series, dims: int = DIMENSIONS) -> list[np.ndarray]:
    """Unit vectors of bigram counts, the same buckets as bigram_buckets."""
    return [unit(v) for v in hashed_counts(texts, dims)]


def unit(v: np.ndarray) -> np.ndarray:
    return v / max(float(np.linalg.norm(v)), 1e-12)


def hashed_counts(texts: pd.Series, dims: int = DIMENSIONS) -> list[np.ndarray]:
    """Bigram counts by bucket."""
    import hashlib

    known: dict[str, int] = {}
    out = []
    for text in texts:
        v = np.zeros(dims, dtype=np.float32)
        low = (text or "").lower()
        if len(low) >= 2:
            codes = np.frombuffer(low.encode("utf-32-le"), dtype=np.uint32).astype(np.uint64)
            pair, n = np.unique(codes[:-1] << np.uint64(32) | codes[1:], return_counts=True)
            for p, c in zip(pair.tolist(), n.tolist(), strict=True):
                b = known.get(p)
                if b is None:
                    b = known[p] = int(hashlib.md5((chr(p >> 32) + chr(p & 0xFFFFFFFF)).encode()).hexdigest()[:4], 16) % dims
                v[b] += c
        out.append(v)
    return out


def embed(df: DataFrame, text: str = "text", encoder: Callable[[pd.Series], list] | None = None, out: str = "embedding") -> DataFrame:
    """df with a vector column; the encoder runs once per Arrow batch."""
    encode = encoder or hashed_vectors

    @F.pandas_udf("array<float>")
    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for s in batches:
            yield pd.Series(encode(s))

    return df.withColumn(out, run(F.col(text)))


def embed_counted(df: DataFrame, text: str = "text") -> DataFrame:
    """df with `embedding`, as embed() makes it, and the whole counts behind it as `counts`."""

    @F.pandas_udf("embedding array<float>, counts array<int>")
    def run(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        for s in batches:
            counts = hashed_counts(s)
            yield pd.DataFrame({"embedding": [unit(v) for v in counts], "counts": [v.astype(np.int32) for v in counts]})

    return df.withColumn("_v", run(F.col(text))).select("*", "_v.embedding", "_v.counts").drop("_v")


def with_vectors(df: DataFrame, vectors: DataFrame, key: str = "sample_id", vector_key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """df joined with a table of given vectors."""
    return df.join(vectors.select(F.col(vector_key).alias(key), F.col(vector).alias("embedding")), key)
