"""What is made once for several requests says the same as what each request made for itself."""

import hashlib

import numpy as np
import pyarrow as pa
import pytest

from poolcurator.baselines import selectors as B
from poolcurator.evaluate import runner
from poolcurator.operators import cluster
from poolcurator.operators.embed import embed, embed_counted
from poolcurator.sources.adapters import pool_of
from poolcurator.sources.files import durable
from poolcurator.target.ngram import BigramTarget, Measured


def close(a, b, key="sample_id"):
    a, b = ({r[key]: r.asDict() for r in df.collect()} for df in (a, b))
    return a.keys() == b.keys() and all(a[i][c] == pytest.approx(b[i][c], rel=1e-9, abs=1e-12) for i in a for c in a[i])


def test_one_pass_measures_the_pool_for_both_models(spark, small):
    pool = durable(pool_of(spark, small, "MD-2"), "pool")  # chats have pairs that the fit never saw
    base, proxy = BigramTarget.fit_all(pool_of(spark, small, "MD-1"), (0.1, 1.0))
    table = base.measure(pool, (0.1, 1.0))
    part = pool.where("lang = 'de' OR sample_id < 0")
    want = [(m.metrics(p), m.ifd(p)) for m in (base, proxy) for p in (pool, part)]
    want = [(durable(x, "want"), durable(y, "want")) for x, y in want]
    base.measured = proxy.measured = Measured(pool, table)
    got = [(m.metrics(p), m.ifd(p)) for m in (base, proxy) for p in (pool, part)]
    for (m, i), (wm, wi) in zip(got, want, strict=True):
        assert close(m, wm) and close(i, wi)
        assert not any("bigram-" in f for f in [*m.inputFiles(), *i.inputFiles()])


def test_counts_and_bags_at_hand_change_no_score(spark, small):
    pool = durable(pool_of(spark, small, "MD-1"), "pool").unionByName(spark.createDataFrame([(-1, "", "a"), (-2, "é É", "b"), (-3, None, None)], "sample_id long, text string, lang string"), allowMissingColumns=True)
    examples = pool.where("lang = 'es'").limit(20)
    counted = durable(embed_counted(pool.select("sample_id", "text")), "vectors")
    assert close(B.text_similarity(pool, examples, reference_key="sample_id", counts=counted), B.text_similarity(pool, examples, reference_key="sample_id"))
    assert {r[0]: r[1] for r in counted.select("sample_id", "embedding").collect()} == {r[0]: r[1] for r in embed(pool).select("sample_id", "embedding").collect()}
    assert close(B.dsir_logratio(pool, examples, target_key="sample_id", bags=B.Bags.of(pool)), B.dsir_logratio(pool, examples, target_key="sample_id"))


def test_grams_of_a_batch():
    rows = [["a", "b", "a"], ["é"], ["x", "x", "x", "x"]]
    at, bag = B.hashed_grams(pa.array(rows), 10_000)
    for i, t in enumerate(rows):
        grams = t + [f"{a} {b}" for a, b in zip(t, t[1:])]
        assert sorted(bag[at[i] : at[i + 1]].tolist()) == sorted(int(hashlib.md5(g.encode()).hexdigest()[:8], 16) % 10_000 for g in grams)


def test_nearest_centre_is_assign_nearest(spark):
    v = np.random.default_rng(1).normal(size=(60, 4))
    df = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(v)], "sample_id long, embedding array<double>")
    centres = [(2, v[2].tolist()), (0, v[5].tolist()), (1, v[5].tolist())]  # equals go to the least id
    assert close(cluster.nearest_centre(df, centres), cluster.assign_nearest(df, centres))


def test_the_multi_grid_counts_the_tokens_once(spark, small, monkeypatch):
    from poolcurator.target import ngram

    made, keep = [], ngram.durable
    monkeypatch.setattr(ngram, "durable", lambda df, name: (made.append(name), keep(df, name))[1])
    got = runner.compare_multi(spark, small, "MD-1", ("R-mix-de",))
    assert {r.method for r in got.select("method").distinct().collect()} >= {"tag_ifd", "sim_ifd", "resampling", "transport", "single_pass"}
    assert made.count("bigram-pairs") == 1
