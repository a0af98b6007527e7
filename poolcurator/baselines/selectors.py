"""Comparators that pick k samples without the cascade."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from poolcurator.backbone.core import Backbone, CostLedger, ask
from poolcurator.config import ConfigRejected, SelectionRequest
from poolcurator.functions import text as X
from poolcurator.operators.embed import DIMENSIONS, bigram_buckets
from poolcurator.operators.relational import running_total
from poolcurator.operators.topk import gumbel, rehydrate, top_k
from poolcurator.sources.files import durable

#: Reference vectors that every task may hold.
REFERENCES = 100_000


def held_by_all(rows: DataFrame, what: str, most: int = REFERENCES) -> DataFrame:
    """rows marked for broadcast; an error beyond `most` of them, as the method is meant for a bounded set of examples."""
    n = rows.count()
    if n > most:
        raise ValueError(f"{n} {what}; at most {most} can be sent to every task")
    return F.broadcast(rows)


def full_pool(df: DataFrame) -> DataFrame:
    """Everything: the control."""
    return df


def ifd_top_k(samples: DataFrame, proxy, k: int, cap: float | None = None, key: str = "sample_id") -> DataFrame:
    """(key, ifd): the samples whose answer the prompt helps least, by a small proxy model; cap excludes ratios above it."""
    scored = proxy.ifd(samples, key).withColumn("ifd", F.round("ifd", 6))
    if cap is not None:
        scored = scored.where(F.col("ifd") <= cap)
    return top_k(scored.select(key, "ifd"), "ifd", k, key)


def tag_then_ifd(samples: DataFrame, proxy, tags: list[str], k: int, column: str = "lang", key: str = "sample_id") -> DataFrame:
    """IFD among samples whose source tag is wanted; on a pool partitioned by the tag this prunes partitions."""
    return ifd_top_k(samples.where(F.col(column).isin(tags)), proxy, k, key=key)


def centroid_similarity(vectors: DataFrame, reference: DataFrame, key: str = "sample_id", vector: str = "embedding") -> DataFrame:
    """(key, similarity): cosine to the mean of the reference vectors."""
    mean = reference.select(F.posexplode(vector).alias("i", "x")).groupBy("i").agg(F.avg(F.col("x").cast("double")).alias("m")).groupBy().agg(F.transform(F.sort_array(F.collect_list(F.struct("i", "m"))), lambda s: s["m"]).alias("centre"))
    return vectors.crossJoin(F.broadcast(mean)).select(key, X.cosine(vector, "centre").alias("similarity"))  # one row


def reference_similarity(vectors: DataFrame, reference: DataFrame, how: str = "max", key: str = "sample_id", vector: str = "embedding") -> DataFrame:
    """(key, similarity): highest or mean cosine to the reference vectors, a bounded target set that every task holds."""
    refs = held_by_all(reference.select(F.col(vector).alias("_ref")), "reference vectors")
    best = F.max if how == "max" else F.avg
    return vectors.crossJoin(refs).groupBy(key).agg(best(X.cosine(vector, "_ref")).alias("similarity"))


def text_similarity(samples: DataFrame, reference: DataFrame, key: str = "sample_id", reference_key: str = "item_id", text: str = "text", counts: DataFrame | None = None) -> DataFrame:
    """(key, similarity): cosine of a text's character-bigram vector to the mean of the reference texts' unit vectors; 0 for texts without bigrams.

    The reference is one row per bucket, 256 at most, so only it is broadcast; a text's buckets are added up once.
    `counts` are the samples' (key, counts) by bucket where they are at hand.
    """
    ref = bigram_buckets(reference, reference_key, text)
    size = ref.groupBy(reference_key).agg(F.sqrt(F.sum(F.col("n") * F.col("n")).cast("double")).alias("norm"))
    mean = ref.join(size, reference_key).groupBy("bucket").agg(F.sum(F.col("n") / F.col("norm")).alias("m"))
    length = mean.agg(F.sqrt(F.sum(F.col("m") * F.col("m"))).alias("length"))  # one row
    centre = mean.crossJoin(F.broadcast(length)).select("bucket", (F.col("m") / F.col("length")).alias("m"))
    if counts is not None:
        held = {r["bucket"]: r["m"] for r in centre.collect()}  # one row per bucket
        m = F.array(*[F.lit(held.get(b, 0.0)) for b in range(DIMENSIONS)])
        own = F.sqrt(F.aggregate("counts", F.lit(0.0), lambda a, n: a + n.cast("double") * n))
        value = F.when(own > 0, F.aggregate(F.zip_with("counts", m, lambda n, x: n * x), F.lit(0.0), lambda a, x: a + x) / own).otherwise(F.lit(0.0))
        return counts.select(key, value.alias("similarity"))
    mine = bigram_buckets(samples, key, text).join(F.broadcast(centre), "bucket", "left")
    near = mine.groupBy(key).agg((F.sum(F.col("n") * F.coalesce("m", F.lit(0.0))) / F.sqrt(F.sum(F.col("n") * F.col("n")).cast("double"))).alias("similarity"))
    return samples.select(key).join(near, key, "left").select(key, F.coalesce("similarity", F.lit(0.0)).alias("similarity"))


def sim_then_ifd(samples: DataFrame, similarity: DataFrame, proxy, candidates: int, k: int, key: str = "sample_id") -> DataFrame:
    """IFD among the samples most similar to the target examples."""
    near = top_k(similarity.withColumn("similarity", F.round("similarity", 6)), "similarity", candidates, key)
    return ifd_top_k(rehydrate(samples, near, key), proxy, k, key=key)


# ---- rating-probability scores -------------------------------------------------------------------


def selectit_token(probs: str = "probs") -> F.Column:
    """Most likely rating times the mean gap between its probability and the others', after renormalising."""
    p = F.transform(probs, lambda x: x / F.aggregate(probs, F.lit(0.0), lambda a, b: a + b))
    top = F.array_max(p)
    rating = F.array_position(p, top).cast("double")
    gaps = F.aggregate(F.transform(p, lambda x: F.abs(top - x)), F.lit(0.0), lambda a, b: a + b)
    return rating * gaps / (F.size(probs) - 1)


def selectit_sentence(df: DataFrame, alpha: float = 0.2, by: tuple[str, ...] = ("sample_id", "model")) -> DataFrame:
    """Mean token score over rating prompts, less where the prompts disagree."""
    return df.groupBy(*by).agg((F.avg("token") / (1 + alpha * F.stddev_pop("token"))).alias("sentence"))


def selectit_model(df: DataFrame, sizes: dict[str, float], key: str = "sample_id") -> DataFrame:
    """Mean over models, weighted by their parameter counts."""
    table = df.sparkSession.createDataFrame([(m, float(n)) for m, n in sizes.items()], "model string, size double")
    return df.join(F.broadcast(table), "model").groupBy(key).agg((F.sum(F.col("sentence") * F.col("size")) / F.sum("size")).alias("score"))


def rating_probabilities(samples: DataFrame, prompts: int = 5, models: tuple[str, ...] = ("7B", "13B"), ratings: int = 5, key: str = "sample_id") -> DataFrame:
    """Seeded stand-in probabilities per (sample, prompt, model), where no model is at hand."""
    rows = samples.select(key, F.explode(F.sequence(F.lit(1), F.lit(prompts))).alias("prompt_id")).select("*", F.explode(F.array(*map(F.lit, models))).alias("model"))
    u = [X.seeded_uniform(F.concat_ws("|", F.col(key).cast("string"), F.col("prompt_id").cast("string"), "model"), f"rating{r}") for r in range(1, ratings + 1)]
    total = sum(u[1:], u[0])
    return rows.withColumn("probs", F.array(*[x / total for x in u]))


# ---- information gain on a tag graph -------------------------------------------------------------


def tag_edges(tags: DataFrame, least: float = 0.05, key: str = "sample_id") -> DataFrame:
    """(a, b, weight): Jaccard overlap of tags' supports where it is high enough; every tag with itself 1."""
    support = tags.groupBy("tag").agg(F.count_distinct(key).alias("n"))
    pairs = tags.select(key, F.col("tag").alias("a")).join(tags.select(key, F.col("tag").alias("b")), key).groupBy("a", "b").agg(F.count_distinct(key).alias("c"))
    out = pairs.join(support.select(F.col("tag").alias("a"), F.col("n").alias("na")), "a").join(support.select(F.col("tag").alias("b"), F.col("n").alias("nb")), "b")
    return out.select("a", "b", (F.col("c") / (F.col("na") + F.col("nb") - F.col("c"))).alias("weight")).where(F.col("weight") >= least)


def mig_first_gains(tags: DataFrame, edges: DataFrame, power: float = 0.8, key: str = "sample_id") -> DataFrame:
    """(key, gain): what each sample adds to the empty set: sum over tags of (propagated mass)**power."""
    mass = tags.join(edges, F.col("tag") == F.col("a")).groupBy(key, "b").agg(F.sum(F.col("quality") * F.col("weight")).alias("m"))
    return mass.groupBy(key).agg(F.sum(F.pow("m", F.lit(power))).alias("gain"))


def mig_information(tags: DataFrame, edges: DataFrame, selected: DataFrame, power: float = 0.8, key: str = "sample_id") -> float:
    """Information of a selected set."""
    mass = tags.join(selected.select(key), key, "left_semi").join(edges, F.col("tag") == F.col("a")).groupBy("b").agg(F.sum(F.col("quality") * F.col("weight")).alias("m"))
    return mass.agg(F.coalesce(F.sum(F.pow("m", F.lit(power))), F.lit(0.0))).first()[0]


def tag_chains(tags: DataFrame, key: str = "sample_id") -> DataFrame:
    """(key, chain, scale): samples of a chain have the same tags, with qualities in the same proportion, `scale` times the chain's.

    Samples whose tags are all of one quality share the chain of their tags; any others only meet their equals.
    """
    rows = tags.groupBy(key).agg(F.sort_array(F.collect_list(F.struct("tag", F.col("quality").cast("double").alias("quality")))).alias("t"))
    even = F.array_min("t.quality") == F.array_max("t.quality")
    parts = F.transform("t", lambda x: F.struct(x["tag"].alias("tag"), F.when(even, F.lit(1.0)).otherwise(x["quality"]).alias("quality")))
    return rows.select(key, F.to_json(parts).alias("chain"), F.when(even, F.array_max("t.quality")).otherwise(F.lit(1.0)).alias("scale"))


def mig_walk(rows: pa.Table, links: dict[str, list[tuple[str, float]]], k: int, power: float = 0.8, key: str = "sample_id") -> list[tuple[int, float]]:
    """[(id, gain)] of the k best marginal gains, from the rows of tag_chains.

    A gain grows with the scale, so only the first sample left of every chain can be the next one, and as gains only
    shrink, those are looked at lazily.
    """
    import heapq
    import json

    names = rows.column("chain").combine_chunks().dictionary_encode()
    rows = pa.table({"code": names.indices, "scale": rows.column("scale"), "id": rows.column(key)}).sort_by([("code", "ascending"), ("scale", "descending"), ("id", "ascending")])
    codes, scales, ids = rows.column("code").to_numpy(), rows.column("scale").to_numpy(), rows.column("id")
    parts = [[(t["quality"], links.get(t["tag"], [])) for t in json.loads(c)] for c in names.dictionary.to_pylist()]
    state: dict[str, float] = {}

    def mass(at: int) -> dict[str, float]:
        m: dict[str, float] = {}
        for quality, near in parts[codes[at]]:
            for b, w in near:
                m[b] = m.get(b, 0.0) + float(scales[at]) * quality * w
        return m

    def gain(m: dict[str, float]) -> float:
        return sum((state.get(b, 0.0) + x) ** power - state.get(b, 0.0) ** power for b, x in m.items())

    out: list[tuple[int, float]] = []
    heap: list[tuple] = []  # (-gain, id, number of samples that the gain knows, row, mass)

    def push(at: int) -> None:
        m = mass(at)
        heapq.heappush(heap, (-gain(m), ids[at].as_py(), len(out), at, m))

    for at in np.flatnonzero(np.diff(codes, prepend=-1)).tolist():
        push(at)
    while heap and len(out) < k:
        g, i, known, at, m = heapq.heappop(heap)
        if known < len(out):
            heapq.heappush(heap, (-gain(m), i, len(out), at, m))
            continue
        for b, x in m.items():
            state[b] = state.get(b, 0.0) + x
        out.append((i, -g))
        if at + 1 < len(codes) and codes[at + 1] == codes[at]:
            push(at + 1)
    return out


def mig_greedy(tags: DataFrame, edges: DataFrame, k: int, power: float = 0.8, key: str = "sample_id", pool: int | None = None) -> list[tuple[int, float]]:
    """[(id, gain)]: best marginal information gain, one after the other.

    The state is one number per tag. Gains only shrink, so the candidates with the largest first gains
    are walked lazily on the driver; `pool` of them (20 k by default) are looked at, which is exact when the
    k-th accepted gain is no less than the best first gain outside, and is checked; else the pool is doubled.
    The driver holds a candidate's id and scale, and the mass of one sample a chain.
    """
    links: dict[str, list[tuple[str, float]]] = {}
    for r in edges.collect():  # tags squared at most; the caller bounds the tags
        links.setdefault(r["a"], []).append((r["b"], r["weight"]))
    known = tags.join(edges.select(F.col("a").alias("tag")).distinct(), "tag", "left_semi")
    n = known.select(key).distinct().count()
    size, first = min(n, pool or 20 * k), None
    while True:
        held, outside = known, 0.0
        if size < n:
            if first is None:
                first = mig_first_gains(tags, edges, power, key).withColumn("gain", F.round("gain", 9)).persist()
            order = F.desc("gain"), F.asc(key)
            outside = first.orderBy(*order).offset(size).limit(1).first()["gain"]
            held = known.join(first.orderBy(*order).limit(size).select(key), key, "left_semi")
        out = mig_walk(tag_chains(held, key).toArrow(), links, k, power, key)
        if size >= n or not out or out[-1][1] >= outside:
            if first is not None:
                first.unpersist()
            return out
        size = min(n, size * 2)


def tfidf_tags(samples: DataFrame, per_sample: int = 3, key: str = "sample_id") -> DataFrame:
    """(key, tag, weight): each sample's tokens with the highest tf-idf."""
    n = samples.count()
    tf = X.explode_rows(samples, [key], X.tokens("text"), "tag").groupBy(key, "tag").agg(F.count(F.lit(1)).alias("tf"))
    df = tf.groupBy("tag").agg(F.count(F.lit(1)).alias("df"))
    w = tf.join(df, "tag").select(key, "tag", F.round(F.col("tf") * F.log(F.lit(float(n)) / F.col("df")), 6).alias("weight"))
    rank = F.row_number().over(Window.partitionBy(key).orderBy(F.desc("weight"), "tag"))
    return w.withColumn("rn", rank).where(F.col("rn") <= per_sample).drop("rn")


# ---- difficulty and trace length -----------------------------------------------------------------


def solve_rate(rollouts: DataFrame, key: str = "sample_id") -> DataFrame:
    return rollouts.groupBy(key).agg(F.avg(F.col("correct").cast("double")).alias("rate"))


def effective_length(c: str = "output") -> F.Column:
    """Length after dropping steps (lines) that repeat exactly, first ones kept."""
    return F.length(F.array_join(F.array_distinct(F.split(c, "\n")), "\n"))


def fit_difficulty(rows: DataFrame, features: tuple[str, ...], label: str = "difficulty"):
    """A ridge regression that spreads rollout difficulty to samples without rollouts."""
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.regression import LinearRegression

    vec = VectorAssembler(inputCols=list(features), outputCol="features")
    model = LinearRegression(labelCol=label, regParam=0.01).fit(vec.transform(rows.where(F.col(label).isNotNull())))
    return lambda df: model.transform(vec.transform(df)).drop("features")


def exact_ranks(df: DataFrame, value: str, out: str, key: str = "sample_id", parts: int | None = None) -> DataFrame:
    """df with rank() by falling value (1 is the largest), ties shared, without a single-task window.

    Values are counted, the counts are range-partitioned, and each range starts where the ranges before
    it end: one row per range goes to the driver.
    """
    counts = df.groupBy(value).agg(F.count(F.lit(1)).alias("_n"))
    n = parts or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = counts.repartitionByRange(n, F.desc(value)).withColumn("_p", F.spark_partition_id()).persist()
    before, total = {}, 0
    for r in dealt.groupBy("_p").agg(F.sum("_n").alias("n")).orderBy("_p").collect():
        before[r["_p"]] = total
        total += r["n"]
    offset = dealt.sparkSession.createDataFrame(list(before.items()) or [(0, 0)], "_p int, _off long")
    running = F.sum("_n").over(Window.partitionBy("_p").orderBy(F.desc(value))) - F.col("_n")
    ranks = dealt.join(F.broadcast(offset), "_p").withColumn(out, running + F.col("_off") + 1).select(value, out)
    return df.join(ranks, value)


def joint_rank(df: DataFrame, k: int, w: float = 0.25, key: str = "sample_id") -> DataFrame:
    """(key, score): w times the difficulty's rank and 1 - w times the trace length's; the smallest stay."""
    ranked = exact_ranks(exact_ranks(df, "difficulty", "r_d", key), "length", "r_l", key)
    return top_k(ranked.select(key, F.round(w * F.col("r_d") + (1 - w) * F.col("r_l"), 6).alias("score")), "score", k, key, ascending=True)


# ---- complexity x quality + knowledge, with a diversity walk -------------------------------------


def deft_score(df: DataFrame, key: str = "sample_id") -> DataFrame:
    """(key, score) from columns complexity, quality, knowledge: each scaled to 0..1, then c q + q k."""
    from poolcurator.stages.informativeness import minmax

    s = minmax(df, ("complexity", "quality", "knowledge"))
    return s.select(key, (F.col("complexity") * F.col("quality") + F.col("quality") * F.col("knowledge")).alias("score"))


def deft(samples: DataFrame, model, rankers: DataFrame, k: int, mode: str = "single", tau: float = 0.9, key: str = "sample_id", vectors: DataFrame | None = None) -> list[int]:
    """Ids by complexity x quality + quality x knowledge with a diversity walk over the texts' own vectors.

    rankers: (key, complexity, quality). The score knows no target, so a pool of several fields is refused. `vectors`
    are the texts' (key, embedding) where they are at hand.
    """
    from poolcurator.operators.embed import embed

    if mode != "single":
        raise ConfigRejected("this score is for pools of one field")
    score = deft_score(rankers.join(model.min_k(samples, key=key), key), key).withColumn("score", F.round("score", 6))
    vectors = embed(samples.select(key, "text")).select(key, "embedding") if vectors is None else vectors
    return greedy_diverse(durable(vectors.join(score, key), "scored-vectors"), k, tau, key=key)


def fit_ranker(rows: DataFrame, features: tuple[str, ...], label: str = "label"):
    """A logistic ranker from labelled rows; adds column p."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.functions import vector_to_array

    vec = VectorAssembler(inputCols=list(features), outputCol="features")
    model = LogisticRegression(labelCol=label, regParam=0.01).fit(vec.transform(rows))
    return lambda df: model.transform(vec.transform(df)).withColumn("p", F.get(vector_to_array("probability"), F.lit(1))).drop("features", "rawPrediction", "probability", "prediction")


#: Vectors that the driver looks at in one round of the walk.
WALK_ROWS = 8_192


def unit_rows(column) -> np.ndarray:
    """The Arrow lists as rows of length 1."""
    flat = column.combine_chunks() if hasattr(column, "combine_chunks") else column
    v = flat.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(flat), -1)
    return v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-12)


def far_from(df: DataFrame, kept: np.ndarray, tau: float, vector: str = "embedding", columns: int = 512) -> DataFrame:
    """Rows of df whose cosine to each of the kept unit vectors is below tau; a task holds `columns` cosines a row at once."""
    shared = df.sparkSession.sparkContext.broadcast(kept)

    def run(batches):
        for b in batches:
            v = unit_rows(b.column(vector)) if len(b) else np.zeros((0, 1))
            left = np.arange(len(b))
            for i in range(0, len(shared.value), columns):
                if len(left):
                    left = left[(v[left] @ shared.value[i : i + columns].T).max(axis=1) < tau]
            yield b.take(pa.array(left))

    return df.mapInArrow(run, df.schema)


def greedy_diverse(df: DataFrame, k: int, tau: float = 0.9, block: int = 512, key: str = "sample_id", vector: str = "embedding") -> list[int]:
    """Ids in falling score order, each kept if its highest cosine to those kept is below tau, until k.

    Exact: the driver walks the best rows, and whatever is too near to one of those just kept leaves the table before
    the next round, as it can never be kept. So a round's rows only meet each other, and the driver holds one
    round of vectors.
    """
    kept_ids: list[int] = []
    rest = df.select(key, "score", vector)
    while True:
        rows = rest.orderBy(F.desc("score"), key).limit(block).toArrow()
        if not rows.num_rows:
            return kept_ids
        v, ids = unit_rows(rows.column(vector)), rows.column(key).to_pylist()
        fresh, far = [], np.ones(len(v), dtype=bool)
        for i in range(len(v)):
            if far[i]:
                fresh.append(i)
                kept_ids.append(ids[i])
                if len(kept_ids) == k:
                    return kept_ids
                far[i + 1 :] &= v[i + 1 :] @ v[i] < tau
        if rows.num_rows < block:
            return kept_ids
        score, last = rows.column("score")[-1].as_py(), ids[-1]
        tie = F.col("score").eqNullSafe(F.lit(score).cast(dict(rest.dtypes)["score"])) & (F.col(key) > last)
        after = tie if score is None else (F.col("score") < score) | F.col("score").isNull() | tie
        rest = durable(far_from(rest.where(after), v[fresh], tau, vector), "walk")
        block = min(2 * block, max(block, WALK_ROWS))


# ---- importance resampling -----------------------------------------------------------------------


def word_grams(text: str = "text") -> F.Column:
    """Unigrams and bigrams of a column."""
    return X.once(X.tokens(text), lambda t: F.concat(t, F.filter(F.transform(t, lambda w, i: F.concat(w, F.lit(" "), F.get(t, i + 1))), lambda g: g.isNotNull())))


def md5_bucket(gram, buckets: int) -> F.Column:
    return F.pmod(F.conv(F.substring(F.md5(gram), 1, 8), 16, 10).cast("long"), F.lit(buckets)).cast("int")


def ngram_buckets(df: DataFrame, key: str, text: str = "text", buckets: int = 10_000) -> DataFrame:
    """(key, bucket, n): unigrams and bigrams by md5 bucket."""
    # Equal grams of a text are added up before they are hashed.
    grams = X.explode_rows(df, [key], word_grams(text), "g").groupBy(key, "g").agg(F.count(F.lit(1)).alias("c"))
    return grams.groupBy(key, md5_bucket("g", buckets).alias("bucket")).agg(F.sum("c").alias("n"))


def hashed_grams(lists, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """The Arrow lists' tokens and pairs of neighbours as md5_bucket has them: where each list's buckets begin and end, and the buckets.

    Equal tokens and equal pairs are hashed once.
    """
    from hashlib import md5

    def hashed(grams) -> np.ndarray:
        return (np.frombuffer(b"".join(md5(g).digest()[:4] for g in grams), dtype=">u4") % buckets).astype(np.int32)

    size = lists.value_lengths().to_numpy()
    names = lists.flatten().dictionary_encode()
    code, words = names.indices.to_numpy().astype(np.int64), [w.encode() for w in names.dictionary.to_pylist()]
    ends = np.cumsum(size)
    first = np.ones(len(code), dtype=bool)  # of each pair
    first[ends - 1] = False  # no list is empty
    at = np.flatnonzero(first)
    pairs, which = np.unique(code[at] * len(words) + code[at + 1], return_inverse=True)
    left, right = (pairs // max(1, len(words))).tolist(), (pairs % max(1, len(words))).tolist()
    # A token's bucket, then that of its pair.
    out = np.empty(len(code) + len(at), dtype=np.int32)
    spot = np.arange(len(code)) + np.concatenate([[0], np.cumsum(first)[:-1]]) if len(code) else np.zeros(0, dtype=np.int64)
    out[spot] = hashed(words)[code]
    out[spot[at] + 1] = hashed(words[a] + b" " + words[b] for a, b in zip(left, right, strict=True))[which]
    return np.concatenate([[0], np.cumsum(2 * size - 1)]).astype(np.int32), out


@dataclass
class Bags:
    """A pool's n-grams by bucket, for resamplings towards several targets: written once, a row a sample, and never shuffled."""

    rows: DataFrame  # key, bag: the bucket of every n-gram
    raw: DataFrame  # bucket, q: the whole pool's counts

    @classmethod
    def of(cls, pool: DataFrame, key: str = "sample_id", buckets: int = 10_000) -> Bags:
        def run(batches):
            for b in batches:
                for i in range(0, len(b), 1000):
                    part = b.slice(i, 1000)
                    ids, bag = hashed_grams(part.column("t"), buckets)
                    yield pa.RecordBatch.from_arrays([part.column(key), pa.ListArray.from_arrays(pa.array(ids), pa.array(bag))], [key, "bag"])

        tokens = pool.select(key, X.tokens("text").alias("t")).where("size(t) > 0")
        rows = durable(tokens.mapInArrow(run, f"{key} {dict(pool.dtypes)[key]}, bag array<int>"), "bags")
        return cls(rows, durable(rows.select(F.explode("bag").alias("bucket")).groupBy("bucket").agg(F.count(F.lit(1)).alias("q")), "raw-bag"))

    def summed(self, table: DataFrame, buckets: int, key: str) -> DataFrame:
        """(key, value): the sum over a sample's n-grams of their bucket's r in a table (bucket, r)."""
        ratio = np.zeros(buckets)
        for r in table.collect():  # `buckets` rows at most
            ratio[r["bucket"]] = r["r"]
        shared = table.sparkSession.sparkContext.broadcast(ratio)

        def run(batches):
            for b in batches:
                bag = b.column("bag")
                ends = np.cumsum(np.concatenate([[0], bag.value_lengths().to_numpy()]))
                if len(b):  # no bag is empty
                    yield pa.RecordBatch.from_arrays([b.column(key), pa.array(np.add.reduceat(shared.value[bag.flatten().to_numpy()], ends[:-1]))], [key, "value"])

        return self.rows.mapInArrow(run, f"{key} {dict(self.rows.dtypes)[key]}, value double")


def dsir_logratio(raw: DataFrame, target: DataFrame, key: str = "sample_id", target_key: str = "item_id", buckets: int = 10_000, smooth: float = 1.0, bags: Bags | None = None) -> DataFrame:
    """(key, value): log ratio of a sample's n-grams under the target's and the raw pool's bag models; `bags` are raw's where they are at hand."""
    mine = ngram_buckets(raw, key, buckets=buckets) if bags is None else None
    q = mine.groupBy("bucket").agg(F.sum("n").alias("q")) if bags is None else bags.raw
    p = ngram_buckets(target, target_key, buckets=buckets).groupBy("bucket").agg(F.sum("n").alias("p"))
    counts = q.join(p, "bucket", "full").select("bucket", F.coalesce("p", F.lit(0)).alias("p"), F.coalesce("q", F.lit(0)).alias("q"))
    totals = counts.agg(F.sum("p").alias("tp"), F.sum("q").alias("tq"))
    ratio = F.log((F.col("p") + smooth) / (F.col("tp") + smooth * buckets)) - F.log((F.col("q") + smooth) / (F.col("tq") + smooth * buckets))
    table = counts.crossJoin(F.broadcast(totals)).select("bucket", ratio.alias("r"))  # `buckets` rows at most
    if bags is not None:
        return bags.summed(table, buckets, key)
    return mine.join(F.broadcast(table), "bucket").groupBy(key).agg(F.sum(F.col("n") * F.col("r")).alias("value"))


def dsir(raw: DataFrame, target: DataFrame, k: int, key: str = "sample_id", target_key: str = "item_id", buckets: int = 10_000, bags: Bags | None = None) -> DataFrame:
    """(key, score): k samples drawn without replacement in proportion to the ratio, by Gumbel top-k."""
    v = dsir_logratio(raw, target, key, target_key, buckets, bags=bags)
    return top_k(v.select(key, F.round(F.col("value") + gumbel(key), 6).alias("score")), "score", k, key)


# ---- optimal transport by neighbourhoods ---------------------------------------------------------


def knn(queries: DataFrame, candidates: DataFrame, neighbours: int = 10) -> DataFrame:
    """(query, vec_id, similarity): the nearest candidates of every query by cosine.

    The bounded target set is held by every task, which meets it with an Arrow batch of candidates in matrix products and
    keeps `neighbours` rows a query of each batch, and again before the shuffle.
    """
    n = queries.count()
    if n > REFERENCES:
        raise ValueError(f"{n} target vectors; at most {REFERENCES} can be sent to every task")
    kind, qkind = dict(candidates.dtypes)["vec_id"], dict(queries.dtypes)["vec_id"]
    held = queries.select("vec_id", "embedding").toArrow()
    if not n or candidates.isEmpty():
        return candidates.select(F.lit(0).cast(qkind).alias("query"), "vec_id", F.lit(0.0).alias("similarity")).limit(0)
    shared = candidates.sparkSession.sparkContext.broadcast((held.column("vec_id").to_pylist(), unit_rows(held.column("embedding"))))

    def run(batches):
        names, q = shared.value
        for b in batches:
            if not len(b):
                continue
            v, ids = unit_rows(b.column("embedding")), np.array(b.column("vec_id").to_pylist())
            out = []
            for i in range(0, len(q), 512):
                near = np.round(q[i : i + 512] @ v.T, 6)
                for j, row in enumerate(near):
                    best = np.lexsort((ids, -row))[:neighbours]
                    out.append((names[i + j], best, row[best]))
            at = np.concatenate([best for _, best, _ in out])
            query = [name for name, best, _ in out for _ in best]
            yield pa.RecordBatch.from_arrays([pa.array(query), pa.array(ids[at]), pa.array(np.concatenate([x for _, _, x in out]))], ["query", "vec_id", "similarity"])

    rows = candidates.select("vec_id", "embedding").mapInArrow(run, f"query {qkind}, vec_id {kind}, similarity double")
    rank = F.row_number().over(Window.partitionBy("query").orderBy(F.desc("similarity"), "vec_id"))
    return rows.withColumn("rn", rank).where(F.col("rn") <= neighbours).drop("rn")


def aligned(near: DataFrame, alpha: float = 0.5, scale: float = 1.0) -> DataFrame:
    """near, cut where a wider neighbourhood would cost more alignment than it brings diversity.

    alpha weighs the transport cost (cosine distance over `scale`) against the regulariser that spreads a query's
    mass. The j-th neighbour stays while the j - 1 nearer ones together are at most (1 - alpha) / alpha * scale closer
    than it: alpha near 1 keeps the nearest only, alpha near 0 all that were found.
    """
    w = Window.partitionBy("query").orderBy(F.desc("similarity"), "vec_id")
    d = 1 - F.col("similarity")
    closer = F.row_number().over(w) * d - F.sum(d).over(w.rowsBetween(Window.unboundedPreceding, 0))
    return near.withColumn("_closer", F.round(closer, 9)).where(F.col("_closer") <= (1 - alpha) / alpha * scale).drop("_closer")


def kde_mass(near: DataFrame, candidates: DataFrame, bandwidth: float = 0.5, kde: bool = True) -> DataFrame:
    """(query, vec_id, mass): each query's unit mass over its neighbours, less where candidates crowd (or even)."""
    if not kde:
        return near.select("query", "vec_id", (1 / F.count(F.lit(1)).over(Window.partitionBy("query"))).alias("mass"))
    v = near.join(candidates.select("vec_id", "embedding"), "vec_id")
    pairs = v.alias("a").join(v.alias("b"), F.expr("a.query = b.query")).select(
        F.col("a.query").alias("query"), F.col("a.vec_id").alias("vec_id"), F.exp(-X.squared_distance("a.embedding", "b.embedding") / (2 * bandwidth * bandwidth)).alias("kernel")
    )  # neighbours squared per query
    density = pairs.groupBy("query", "vec_id").agg(F.sum("kernel").alias("density"))
    inverse = 1 / F.col("density")
    return density.select("query", "vec_id", (inverse / F.sum(inverse).over(Window.partitionBy("query"))).alias("mass"))


def categorical_draw(mass: DataFrame, k: int, seed: int = 42) -> DataFrame:
    """(draw, vec_id): k draws with replacement, each to the row whose running mass covers its seeded uniform."""
    total = mass.groupBy("vec_id").agg(F.sum("mass").alias("m"))
    cells = durable(running_total(total, "m", "vec_id"), "cells")
    whole, n = cells.agg(F.max("total"), F.count(F.lit(1))).first()
    draws = mass.sparkSession.range(k).select(F.col("id").alias("draw")).withColumn("u", X.fine_uniform("draw", f"draw{seed}") * F.lit(float(whole or 1.0)))
    # Cells and draws meet in as many bins as there are cells, an equi-join key for the range condition: a bin has a
    # cell or two, and a large cell as many bins as its share.
    width = (whole or 1.0) / max(1, n)
    lo = F.col("total") - F.col("m")
    bins = cells.select("vec_id", lo.alias("lo"), F.col("total").alias("hi"), F.explode(F.sequence(F.greatest(F.floor(lo / width) - 1, F.lit(0)), F.floor(F.col("total") / width) + 1)).alias("bin"))
    return draws.withColumn("bin", F.floor(F.col("u") / width)).join(bins, "bin").where("u >= lo AND u < hi").select("draw", "vec_id")


# ---- single pass ---------------------------------------------------------------------------------


def single_pass_plan(request: SelectionRequest, backbone: Backbone, ledger: CostLedger | None = None) -> dict[str, float]:
    """What one call makes of the request: a noise limit, a least answer length, and weights of variety, cleanness and length."""

    def parse(reply) -> dict[str, float]:
        plan = {n: float(reply[n]) for n in ("max_noise", "min_output", "variety", "clean", "length")}
        if set(reply) != set(plan) or not 0 <= plan["max_noise"] <= 1 or min(plan.values()) < 0:
            raise ConfigRejected(f"not a plan: {reply}")
        return plan

    return ask(backbone, "plan", {"request": request.text}, parse, ledger=ledger)


def single_pass(samples: DataFrame, k: int, request: SelectionRequest, backbone: Backbone, key: str = "sample_id", ledger: CostLedger | None = None) -> DataFrame:
    """(key, score): the same request and budget, one call, one scan with one filter and one order expression."""
    plan = single_pass_plan(request, backbone, ledger)
    f = samples.select(key, F.round(X.share_of("text", X.noise_class()), 6).alias("noise"), F.round(X.unique_share("text"), 6).alias("variety"), F.length("output").alias("n"))
    ok = f.where((F.col("noise") <= plan["max_noise"]) & (F.col("n") >= plan["min_output"]))
    score = plan["variety"] * F.col("variety") + plan["clean"] * (1 - F.col("noise")) + plan["length"] * F.least(F.col("n") / 2000, F.lit(1.0))
    return top_k(ok.select(key, F.round(score, 6).alias("score")), "score", k, key)
