"""Stand-ins for training and benchmarking: what can be measured of a subset without training a model on it."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from poolcurator.functions import text as X
from poolcurator.sources.files import durable
from poolcurator.target.ngram import BOS


def label_precision(selected: DataFrame, labels: DataFrame, key: str = "sample_id") -> DataFrame:
    """Labelled rows among the selected, and their mean quality and toxic labels."""
    rows = selected.select(key).join(labels.select(F.col("doc_id").alias(key), "quality", "toxic"), key)
    return rows.agg(F.count(F.lit(1)).alias("labelled"), F.round(F.avg("quality"), 6).alias("quality"), F.round(F.avg("toxic"), 6).alias("toxic"))


def domain_pr(selected: DataFrame, pool: DataFrame, lang: str) -> DataFrame:
    """Precision and recall of a selection against the language column."""
    hit = selected.agg(F.count_if(F.col("lang") == lang).alias("tp"), F.count(F.lit(1)).alias("n"))
    total = pool.agg(F.count_if(F.col("lang") == lang).alias("all"))
    return hit.crossJoin(total).select(F.round(F.col("tp") / F.nullif("n", F.lit(0)), 6).alias("precision"), F.round(F.col("tp") / F.nullif("all", F.lit(0)), 6).alias("recall"))  # one row each


def proxy_downstream(model, reference: DataFrame) -> DataFrame:
    """Perplexity of reference texts under a count model fitted on the subset."""
    y = X.tokens("text")
    rows = reference.select(y.alias("y")).where(F.size("y") > 0)
    rows = rows.select(F.explode(F.arrays_zip(F.concat(F.array(F.lit(BOS)), F.slice("y", F.lit(1), F.size("y") - 1)).alias("h"), F.col("y").alias("w"))).alias("t")).select("t.h", "t.w")
    return model.scored(rows).agg(F.round(F.exp(F.avg(-F.log("p"))), 4).alias("perplexity"))


def surplus_copies(df: DataFrame) -> DataFrame:
    counts = df.groupBy(F.md5("text").alias("digest")).agg(F.count(F.lit(1)).alias("c"))
    return counts.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("n"), F.coalesce(F.sum(F.col("c") - 1), F.lit(0)).alias("surplus"))


def word_shingles(df: DataFrame, key: str, n: int = 8, text: str = "text") -> DataFrame:
    """(key, s): every run of n tokens, hashed."""
    runs = X.once(X.tokens(text), lambda t: F.when(F.size(t) >= n, F.transform(F.sequence(F.lit(1), F.size(t) - n + 1), lambda i: F.xxhash64(F.slice(t, i, F.lit(n))))))
    return X.explode_rows(df, [key], runs, "s")


def contaminated(docs: DataFrame, items: DataFrame, n: int = 8, most: int = 5_000_000) -> DataFrame:
    """(doc_id): documents that share a run of n tokens with an item; the items' runs are broadcast if their number allows."""
    wanted = word_shingles(items, "item_id", n).select("s").distinct()
    side = F.broadcast(wanted) if wanted.count() <= most else wanted
    return word_shingles(docs, "doc_id", n).join(side, "s", "left_semi").select("doc_id").distinct()


def hashed_runs(tokens: F.Column, n: int) -> F.Column:
    """Every run of n tokens, hashed; null for fewer tokens."""
    return X.once(tokens, lambda t: F.when(F.size(t) >= n, F.transform(F.sequence(F.lit(1), F.size(t) - n + 1), lambda i: F.xxhash64(F.slice(t, i, F.lit(n))))))


def quoting(docs: DataFrame, items: DataFrame, n: int = 8, most: int = 5_000_000) -> DataFrame:
    """(doc_id): documents that hold an item's text, character by character.

    Whatever holds a text has its inner tokens whole and in a row, as both ends of these are inside the text: runs of
    them lead to pairs, which are then compared. A text's first inner tokens count, n or the next smaller power of two
    that it has; texts without inner tokens are looked for in every document.
    """
    # Tokens keep their case: lower case may depend on what stands around them.
    words = lambda c: F.regexp_extract_all(c, F.lit(X.TOKEN), F.lit(0))
    texts = items.select(F.col("text").alias("item")).where("item IS NOT NULL").distinct()
    inner = texts.withColumn("y", words("item")).select("item", F.when(F.size("y") > 2, F.slice("y", F.lit(2), F.size("y") - 2)).otherwise(F.array().cast("array<string>")).alias("y"))
    runs = [r for i in range(n.bit_length()) if (r := 1 << i) <= n]
    size = F.greatest(F.lit(0), *[F.when(F.size("y") >= r, F.lit(r)) for r in runs])
    wanted = durable(inner.withColumn("r", size).select("item", "r", F.when(F.col("r") > 0, F.xxhash64(F.slice("y", F.lit(1), F.col("r")))).alias("s")), "wanted")
    counted = {r["r"]: r["n"] for r in wanted.groupBy("r").agg(F.count(F.lit(1)).alias("n")).collect()}
    found = []
    for r in runs:
        if counted.get(r):
            one = wanted.where(F.col("r") == r).select("item", "s")
            met = hashed_runs(words("text"), r)
            small = counted[r] <= most
            # Ids and hashes meet first; texts are read again for the pairs found.
            at = X.explode_rows(docs, ["doc_id"], met, "s").join(F.broadcast(one) if small else one, "s").select("doc_id", "item")
            pairs = durable(at.distinct(), "pairs")
            held = docs.select("doc_id", "text").join(F.broadcast(pairs) if pairs.count() <= most // 50 else pairs, "doc_id")
            found.append(held.where(F.contains("text", "item")).select("doc_id"))
    if counted.get(0):
        found.append(docs.join(F.broadcast(wanted.where("r = 0").select("item")), F.contains("text", "item"), "left_semi").select("doc_id"))
    return reduce(DataFrame.unionByName, found).distinct() if found else docs.select("doc_id").limit(0)


def subset_overlap(a: DataFrame, b: DataFrame, key: str = "sample_id") -> DataFrame:
    both = a.select(key, F.lit(1).alias("a"), F.lit(0).alias("b")).unionByName(b.select(key, F.lit(0).alias("a"), F.lit(1).alias("b")))
    per = both.groupBy(key).agg(F.max("a").alias("a"), F.max("b").alias("b"))
    shared = F.sum(F.col("a") * F.col("b"))
    return per.agg(shared.alias("shared"), F.round(shared / F.count(F.lit(1)), 6).alias("jaccard"))


def mean_cosine(vectors: DataFrame, vector: str = "embedding") -> DataFrame:
    """Mean cosine of all pairs from the sum of unit vectors: no pairs are made."""
    n = X.norm(vector)
    unit = vectors.select(F.posexplode(F.transform(vector, lambda x: x.cast("double") / n)).alias("i", "x"))
    s = unit.groupBy("i").agg(F.sum("x").alias("s"), F.count(F.lit(1)).alias("n"))
    return s.agg(F.round((F.sum(F.col("s") * F.col("s")) - F.max("n")) / (F.max("n") * (F.max("n") - 1)), 6).alias("mean_cosine"))
