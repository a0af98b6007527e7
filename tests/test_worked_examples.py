"""Worked examples of every metric and score, computed by hand or by a plain loop."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from poolcurator.baselines import selectors as B
from poolcurator.config import Weights
from poolcurator.functions import text as X
from poolcurator.stages import informativeness as N
from poolcurator.stages import quality as Q
from poolcurator.target import probe
from poolcurator.target.ngram import BOS, BigramTarget, PromptCacheTarget

S = "sample_id long, instruction string, output string"


@pytest.fixture(scope="module")
def theta(spark):
    return BigramTarget.fit(spark.createDataFrame([(1, "", "a b a b c"), (2, "", "a b b")], S))


def test_loss_entropy_and_difficulty(spark, theta):
    assert theta.v == 4  # three tokens and the unknown one
    theta = BigramTarget(theta.pairs, theta.contexts, 3)
    # V = 3 as in the example: entropies are recomputed for it below
    row = theta.ifd(spark.createDataFrame([(7, "x b", "a b c")], S)).first()
    assert row.alone == pytest.approx(0.417368, abs=1e-6) and row.given == pytest.approx(0.753248, abs=1e-6)
    assert row.ifd == pytest.approx(1.804758, abs=1e-6)


def explicit(theta, h, cache=None, beta=0.2):
    pairs = {(r.h, r.w): r.n for r in theta.pairs.collect()}
    vocab = sorted({w for _, w in pairs} | set(cache or {}))
    total = sum(n for (a, _), n in pairs.items() if a == h)
    p = {w: (pairs.get((h, w), 0) + theta.smoothing) / (total + theta.smoothing * theta.v) for w in vocab}
    unknown = theta.v - len({w for _, w in pairs})
    p0 = theta.smoothing / (total + theta.smoothing * theta.v)
    if cache is None:
        return -sum(x * math.log(x) for x in p.values()) - unknown * p0 * math.log(p0)
    mixed = {w: (1 - beta) * x + beta * cache.get(w, 0) for w, x in p.items()}
    return -sum(x * math.log(x) for x in mixed.values()) - unknown * (1 - beta) * p0 * math.log((1 - beta) * p0)


def test_entropy_closed_form(spark, theta):
    got = theta.metrics(spark.createDataFrame([(1, "x b", "a b c")], S)).first()
    assert got.entropy == pytest.approx(np.mean([explicit(theta, h) for h in ("b", "a", "b")]))


def test_prompt_cache_entropy(spark, theta):
    got = PromptCacheTarget(theta).metrics(spark.createDataFrame([(1, "a b b", "a c"), (2, "", "b")], S)).orderBy("sample_id").collect()
    want = np.mean([explicit(theta, h, {"a": 1 / 3, "b": 2 / 3}) for h in ("b", "a")])
    assert got[0].entropy == pytest.approx(want) and got[1].entropy == pytest.approx(explicit(theta, BOS))


def test_generation_is_greedy(spark, theta):
    # a is always followed by b; b by a, b and c once each, of which the last counts; nothing follows c.
    got = theta.generate(spark.createDataFrame([(1, "start a", ""), (2, "unknown", ""), (3, "c", "")], S), 3).collect()
    assert {r.sample_id: r.generated for r in got} == {1: "b c", 2: "a b c", 3: "a b c"}


def test_drift_is_one_minus_cosine(spark):
    v = spark.createDataFrame([([1.0, 2.0, 0.0], [2.0, 1.0, 0.0])], "a array<double>, b array<double>")
    assert v.select(1 - X.cosine("a", "b")).first()[0] == pytest.approx(0.2)


def test_parameter_shift(spark):
    v = spark.createDataFrame([([1.0, 2.0], [1.0, 0.0])], "x array<double>, y array<double>").withColumn("r", probe.residual("x", "y"))
    sgd, adamw = v.select(probe.shift_sgd("r", "x"), probe.shift_adamw("r", "x")).first()
    assert sgd == pytest.approx(1.125e-5) and adamw == pytest.approx(9.9999998875e-6, rel=1e-9)
    # against a numeric first step
    w, e, y, lr, eps = 0.5 * np.eye(2), np.array([1.0, 2.0]), np.array([1.0, 0.0]), 1e-5, 1e-8
    g = np.outer(w @ e - y, e)
    m, s = 0.1 * g / (1 - 0.9), 0.001 * g * g / (1 - 0.999)
    assert adamw == pytest.approx(np.abs(lr * m / (np.sqrt(s) + eps)).mean(), rel=1e-6)


def test_scaled_oriented_weighted(spark):
    m = spark.createDataFrame([(1, 2.0, 1.0, 0.2, 4e-6), (2, 4.0, 2.0, 0.6, 1e-5), (3, 3.0, 3.0, 0.4, 2e-6)], "sample_id long, loss double, entropy double, drift double, mean_diff double")
    o = N.composite(N.orient(N.minmax(m)), Weights(0.2, 0.15, 0.25, 0.4)).orderBy("sample_id").collect()
    assert [tuple(round(r[c], 9) for c in ("loss", "entropy", "drift", "mean_diff")) for r in o] == [(0, 0, 0, 0.75), (1, 0.5, 1, 0), (0.5, 1, 0.5, 1)]
    assert [round(r.score, 9) for r in o] == [0.3, 0.525, 0.775]
    const = spark.createDataFrame([(1, 5.0, 1.0, 1.0, 1.0), (2, 5.0, 2.0, None, 1.0)], m.schema)
    assert [r.loss for r in N.minmax(const).collect()] == [0, 0]


def test_rubric_sum(spark):
    z = {"a": 0.35, "b": 0.30, "c": 0.20, "d": 0.15}
    rows = [(i, d, q, False) for i, qs in ((1, (5, 4, 4, 3)), (2, (3, 5, 4, 5))) for d, q in zip(z, qs)] + [(3, "a", 5, False)]
    got = {r.sample_id: round(r.q, 9) for r in Q.quality_score(spark.createDataFrame(rows, "sample_id long, dim string, q int, flagged boolean"), z).collect()}
    assert got == {1: 4.2, 2: 4.1}


def test_rating_scores(spark):
    p = spark.createDataFrame([([0.1, 0.1, 0.2, 0.5, 0.1],)], "probs array<double>")
    assert p.select(B.selectit_token()).first()[0] == pytest.approx(1.5)
    s = spark.createDataFrame([(1, "7B", x) for x in (2.0, 1.6, 1.8)], "sample_id long, model string, token double")
    assert B.selectit_sentence(s).first().sentence == pytest.approx(1.743072, abs=1e-6)
    m = spark.createDataFrame([(1, "7B", 1.7), (1, "13B", 1.9)], "sample_id long, model string, sentence double")
    assert B.selectit_model(m, {"7B": 7, "13B": 13}).first().score == pytest.approx(1.83)


def test_information(spark):
    tags = spark.createDataFrame([(1, "t1", 0.5), (1, "t3", 0.5)], "sample_id long, tag string, quality double")
    edges = [("t1", "t1", 1.0), ("t1", "t2", 0.9), ("t2", "t1", 0.9), ("t2", "t2", 1.0), ("t3", "t3", 1.0)]
    e = spark.createDataFrame(edges, "a string, b string, weight double")
    assert B.mig_information(tags, e, tags.select("sample_id").distinct()) == pytest.approx(1.676621, abs=1e-6)
    assert B.mig_first_gains(tags, e).first().gain == pytest.approx(1.676621, abs=1e-6)


def test_greedy_information_matches_plain_loop(spark):
    rng = np.random.default_rng(2)
    rows = [(i, f"t{t}", float(rng.random())) for i in range(60) for t in rng.choice(8, 3, replace=False)]
    tags = spark.createDataFrame(rows, "sample_id long, tag string, quality double")
    edges = B.tag_edges(tags, 0.15)
    links = {}
    for r in edges.collect():
        links.setdefault(r.a, []).append((r.b, r.weight))
    mass = {}
    for i, t, q in rows:
        for b, w in links[t]:
            mass.setdefault(i, {}).setdefault(b, 0)
            mass[i][b] += q * w
    state, plain = {}, []
    for _ in range(10):
        gains = {i: sum((state.get(b, 0) + x) ** 0.8 - state.get(b, 0) ** 0.8 for b, x in m.items()) for i, m in mass.items() if i not in plain}
        best = max(gains, key=lambda i: (gains[i], -i))
        plain.append(best)
        for b, x in mass[best].items():
            state[b] = state.get(b, 0) + x
    assert [i for i, _ in B.mig_greedy(tags, edges, 10, pool=12)] == plain


def test_greedy_information_of_samples_that_share_their_tags(spark):
    import tracemalloc

    rng = np.random.default_rng(3)
    rows = [(i, t, q) for i, q in enumerate(rng.random(20_000).round(4).tolist()) for t in ("en", f"s{i % 2}")]
    tags = spark.createDataFrame(rows, "sample_id long, tag string, quality double")
    edges = B.tag_edges(tags)
    links = {}
    for r in edges.collect():
        links.setdefault(r.a, []).append((r.b, r.weight))
    state, plain, at = {}, [], [0, 0]
    q = {i: x for i, _, x in rows}
    line = [sorted((i for i in q if i % 2 == s), key=lambda i: (-q[i], i)) for s in (0, 1)]
    for _ in range(2_000):
        best = []
        for s in (0, 1):
            i, mass = line[s][at[s]], {}
            for t in ("en", f"s{s}"):
                for b, w in links[t]:
                    mass[b] = mass.get(b, 0) + q[i] * w
            best.append((-sum((state.get(b, 0) + x) ** 0.8 - state.get(b, 0) ** 0.8 for b, x in mass.items()), i, s, mass))
        _, i, s, mass = min(best, key=lambda c: c[:2])
        plain.append(i)
        at[s] += 1
        for b, x in mass.items():
            state[b] = state.get(b, 0) + x
    tracemalloc.start()
    try:
        assert [i for i, _ in B.mig_greedy(tags, edges, 2_000)] == plain
        assert tracemalloc.get_traced_memory()[1] < 4e6  # the driver held rows and masses of all samples before
    finally:
        tracemalloc.stop()


def test_joint_rank_and_terms(spark):
    d = spark.createDataFrame([(1, 0.9, 100), (2, 0.5, 300), (3, 0.7, 200)], "sample_id long, difficulty double, length int")
    assert [(r.sample_id, r.score) for r in B.joint_rank(d, 3).collect()] == [(2, 1.5), (3, 2.0), (1, 2.5)]
    t = spark.createDataFrame([(1, 0.5, 0.8, 0.3), (2, 1.0, 0.2, 1.0), (3, 0.0, 0.0, 0.0), (4, 1.0, 1.0, 1.0)], "sample_id long, complexity double, quality double, knowledge double")
    got = {r.sample_id: round(r.score, 9) for r in B.deft_score(t).collect()}
    assert got[1] == 0.64 and got[2] == 0.4


def test_effective_length(spark):
    assert spark.createDataFrame([("ab\nc\nab\n",)], "output string").select(B.effective_length()).first()[0] == len("ab\nc\n")


def test_diversity_walk_matches_plain_loop(spark):
    rng = np.random.default_rng(7)
    v = rng.normal(size=(80, 4))
    rows = [(i, float(s), v[i].tolist()) for i, s in enumerate(rng.random(80).round(1))]
    df = spark.createDataFrame(rows, "sample_id long, score double, embedding array<double>")
    kept = []
    for i, _, x in sorted(rows, key=lambda r: (-r[1], r[0])):
        if all(np.dot(x, v[j]) / np.linalg.norm(x) / np.linalg.norm(v[j]) < 0.6 for j in kept) and len(kept) < 12:
            kept.append(i)
    assert B.greedy_diverse(df, 12, 0.6, block=16) == kept


def test_gumbel_and_density(spark):
    assert -math.log(-math.log(0.25)) == pytest.approx(-0.326634, abs=1e-6)
    near = spark.createDataFrame([(1, i) for i in (1, 2)], "query long, vec_id long")
    v = spark.createDataFrame([(1, [0.0]), (2, [0.0])], "vec_id long, embedding array<double>")
    assert [r.mass for r in B.kde_mass(near, v).collect()] == [0.5, 0.5]


def test_batches_are_functions_of_ids(spark):
    ids = spark.range(95).withColumnRenamed("id", "sample_id")
    for ranges in (None, 3):
        a = {r.sample_id: r.batch_id for r in Q.assign_batches(ids, 10, ranges=ranges).collect()}
        b = {r.sample_id: r.batch_id for r in Q.assign_batches(ids.repartition(7), 10, ranges=ranges).collect()}
        assert a == b and max(list(a.values()).count(x) for x in a.values()) <= 10


def test_threshold_top_k(spark):
    from poolcurator.operators.topk import threshold_top_k

    df = spark.range(5000).select(F.col("id").alias("sample_id"), (F.col("id") % 37).cast("double").alias("s"))
    want = [r.sample_id for r in df.orderBy(F.desc("s"), "sample_id").limit(700).collect()]
    assert sorted(r.sample_id for r in threshold_top_k(df, "s", 700, accuracy=100).collect()) == sorted(want)
