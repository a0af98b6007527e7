"""Queries against their SQL on made-up tables with what the given ones lack: fractions of seconds, inner runs, many rows."""

import math

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from poolcurator import cascade, registry
from poolcurator.baselines import selectors
from poolcurator.evaluate import runner
from poolcurator.plans.shapes import operators
from poolcurator.sources.adapters import from_documents, pool_of, read_table
from poolcurator.sources.files import durable
from poolcurator.stages import informativeness, quality
from poolcurator.target import ngram
from tests.parity import connect, difference


@pytest.fixture
def tables(tmp_path):
    """A folder of tables made by SQL: add(name, sql)."""

    def add(name: str, sql: str) -> str:
        duckdb.sql(f"COPY ({sql}) TO '{tmp_path}/{name}.parquet' (FORMAT parquet)")
        return str(tmp_path)

    return add


def against_sql(spark, folder: str, name: str, *needed: str) -> str:
    con = duckdb.connect()
    for t in needed:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{folder}/{t}.parquet'")
    return difference(registry.queries()[name](spark, folder), con, registry.oracle_sql()[name])


def test_window_of_seconds_rounds_as_its_sql(spark, tables):
    at = "[0.0, 0.5, 0.6, 1.5, 3600.4, 3600.5, 3600.6, 3601.5, 3602.5, 7201.49]"
    d = tables("events", f"SELECT i AS event_id, make_timestamp((1704067200 * 1000000::bigint + round(x * 1e6))::bigint) AS ts, i % 2 AS user_id, 'view' AS event_type, 1.0::double AS value, '' AS props FROM (SELECT unnest({at}) AS x, unnest(range(10)) AS i)")
    assert against_sql(spark, d, "win_range_interval", "events") == ""


def test_quotes_are_found_by_characters(spark, tables):
    """Shared runs of words do not make a quote; a quote may start within a word, be short, or have no words."""
    tables("benchmark", "SELECT i AS item_id, t AS text FROM (SELECT unnest(range(7)) AS i, unnest(['One two three four five six seven eight nine ten.', 'ab cd', '?!', 'a b c d', 'the long ΣΟΦΟΣ one', NULL, 'ab cd']) AS t)")
    texts = """['so One two three four five six seven eight nine', 'xOne two three four five six seven eight nine ten.', 'one two three four five six seven eight nine ten.', 'crab cdrom', 'what?!', 'aa b c dd', 'a b  c d',
      'the long ΣΟΦΟΣ oneX', NULL, '', 'One two three four five six seven eight nine ten. One two three four five six seven eight nine ten.']"""
    d = tables("documents", f"SELECT i AS doc_id, t AS text, 'en' AS lang, 'src1' AS source, length(t) AS n_chars FROM (SELECT unnest(range(11)) AS i, unnest({texts}) AS t)")
    assert against_sql(spark, d, "decontam_ngram", "documents", "benchmark") == ""
    from poolcurator.evaluate.standin import quoting

    pair = read_table(spark, d, "documents"), read_table(spark, d, "benchmark")
    assert sorted(quoting(*pair, most=0).collect()) == sorted(quoting(*pair).collect())


def test_batches_by_ranges_are_those_of_the_whole(spark):
    ids = spark.range(2_345).withColumnRenamed("id", "sample_id")
    for seed in (42, 7):
        whole = {r.sample_id: r.batch_id for r in quality.assign_batches(ids, 10, seed).collect()}
        assert {r.sample_id: r.batch_id for r in quality.assign_batches(ids, 10, seed, ranges=23).collect()} == whole


@pytest.mark.parametrize("name", ["cascade_depth234", "cascade_full"])
def test_cascade_with_batches_by_ranges(spark, small, name, monkeypatch):
    monkeypatch.setattr(quality, "batch_ranges", lambda n, b=10: 5)
    assert difference(registry.queries()[name](spark, small), connect(small), registry.oracle_sql()[name]) == ""


def test_drift_of_dealt_samples_joined_by_shuffles(spark, small):
    """Both texts of samples that are already dealt by their id; the sides' partitions must not add up."""
    docs = from_documents(read_table(spark, small, "documents"))
    want = {r.sample_id: r.drift for r in informativeness.drift(docs, "instruction").collect()}
    keys = {"spark.sql.autoBroadcastJoinThreshold": "-1", "spark.sql.adaptive.autoBroadcastJoinThreshold": "-1", "spark.sql.adaptive.coalescePartitions.enabled": "false"}
    for k, v in keys.items():
        spark.conf.set(k, v)
    try:
        dealt = docs.repartition(4, "sample_id")
        target = ngram.UnigramTarget.fit(docs)
        assert durable(informativeness.measure(dealt, target), "measured").count() == len(want)
        assert not operators(informativeness.drift(dealt, "instruction"))["Union"]
        assert {r.sample_id: r.drift for r in durable(informativeness.drift(dealt, "instruction"), "drift").collect()} == want
    finally:
        for k in keys:
            spark.conf.unset(k)


@pytest.mark.parametrize("k", [40, 1_000])
def test_diversity_walk_in_rounds(spark, k, monkeypatch):
    """Against a plain loop, over more rounds than one, with ties and rows without a score, which come last."""
    monkeypatch.setattr(selectors, "WALK_ROWS", 32)
    draw = np.random.default_rng(5)
    v = draw.normal(size=(400, 3)).astype(np.float32)
    rows = [(i, None if i % 7 == 0 else float(i % 50), v[i].tolist()) for i in range(400)]
    unit = v.astype(np.float64) / np.linalg.norm(v.astype(np.float64), axis=1, keepdims=True)
    want = []
    for i, s, _ in sorted(rows, key=lambda r: (r[1] is None, -(r[1] or 0), r[0])):
        if len(want) < k and (not want or (unit[want] @ unit[i]).max() < 0.97):
            want.append(i)
    df = spark.createDataFrame(rows, "sample_id long, score double, embedding array<float>")
    assert selectors.greedy_diverse(df, k, 0.97, block=16) == want


@pytest.mark.parametrize("name", ["experiment_weights", "weights_sum"])
def test_weights_read_a_given_table(spark, small, name):
    out = registry.queries()[name](spark, small)
    assert out.inputFiles() and difference(out, connect(small), registry.oracle_sql()[name]) == ""


def test_ledger_runs_share_one_fit(spark, small, monkeypatch):
    seen = []
    monkeypatch.setattr(runner, "run_cascade", lambda pool, request, target, *a, **k: seen.append(target))
    runner.costs(spark, small)
    assert len(seen) == 2 and seen[0] is seen[1]


def test_grid_shares_one_count_of_tokens(spark, small, monkeypatch):
    counted, keep = [], ngram.durable
    monkeypatch.setattr(ngram, "durable", lambda df, name: (counted.append(name), keep(df, name))[1])
    proxy, models = runner.models_for(spark, small, runner.TARGETS)
    assert sorted(counted) == ["bigram-contexts", "bigram-pairs", "unigram"]  # four fits before
    docs = runner.pool_of(spark, small, "MD-1")
    rows = lambda df: sorted((r[0], *(round(x, 6) if isinstance(x, float) else x for x in r[1:])) for r in df.collect())
    for one, two in ((proxy, runner.proxy_for(spark, small)), (models["bigram"], runner.target_for(spark, small, "bigram")), (models["cache"].base, runner.target_for(spark, small, "bigram"))):
        assert (one.v, one.smoothing) == (two.v, two.smoothing) and rows(one.contexts) == rows(two.contexts)
    alone = ngram.UnigramTarget.fit(docs)
    assert (models["unigram"].total, models["unigram"].v, rows(models["unigram"].counts)) == (alone.total, alone.v, rows(alone.counts))


def test_token_rows_of_a_pool_serve_all_models(spark, small):
    pool = durable(runner.pool_of(spark, small, "SD-3"), "pool")
    part = pool.where("sample_id % 3 = 0")
    plain, known = runner.models_for(spark, small, runner.TARGETS), runner.models_for(spark, small, runner.TARGETS, pool)
    rows = lambda df: {r[0]: pytest.approx(tuple(r[1:]), abs=1e-9) for r in df.collect()}
    for one, two in zip([plain[0], *plain[1].values()], [known[0], *known[1].values()], strict=True):
        for some in (pool, part):
            for ask in (lambda m: m.metrics(some), lambda m: m.min_k(some), lambda m: m.ifd(some)):  # noqa: B023
                got = {r[0]: tuple(r[1:]) for r in ask(two).collect()}
                assert got and got == rows(ask(one))
    met = lambda df: {f.split("/")[-2].rsplit("-", 1)[0] for f in df.inputFiles()}
    for m in (known[0], known[1]["unigram"], known[1]["bigram"]):  # each met the count tables before
        assert met(m.min_k(pool)) == {"known-tokens"} and not met(m.ifd(pool)) & {"bigram-pairs", "bigram-contexts"}


def test_cascades_share_what_comes_before_the_target(spark, small, monkeypatch):
    pool = durable(runner.pool_of(spark, small, "SD-3"), "pool")
    models = runner.models_for(spark, small, ("unigram", "bigram"), pool)[1]
    cfg, ask = runner.config(pool), runner.request("R-fr")
    alone = {n: sorted(map(tuple, cascade.run_cascade(pool, ask, m, cfg).selected.collect())) for n, m in models.items()}
    looked, look = [], cascade.inspect_pool
    monkeypatch.setattr(cascade, "inspect_pool", lambda now, stage, *a: (looked.append(stage), look(now, stage, *a))[1])
    front = {}
    runs = {n: cascade.run_cascade(pool, ask, m, cfg, front=front) for n, m in models.items()}
    assert {n: sorted(map(tuple, r.selected.collect())) for n, r in runs.items()} == alone
    assert looked == [2, 3, 4, 4] and runs["bigram"].configs.keys() == {"policy", "weights", "rubric"}  # 2, 3, 4, 2, 3, 4 before


@pytest.mark.parametrize("length", [1, 2, 3, 20])
def test_chains_of_likeliest_tokens(spark, length):
    rows = spark.createDataFrame([(1, "x a", "", "b c d"), (2, "nothing known", "", "b c e e"), (3, None, "", "q r"), (4, "e", "", ""), (5, "d", "", "b")], "sample_id long, instruction string, input string, output string")
    base = ngram.BigramTarget.fit(rows)
    best = {r.h: r.last for r in base.best().collect()}
    want = {}
    for i, last in ((1, "a"), (2, "known"), (3, None), (4, "e"), (5, "d")):
        h, said = last if last in best else ngram.BOS, []
        while h in best and len(said) < length:
            h = best[h]
            said.append(h)
        want[i] = " ".join(said)
    got = base.generate(rows, length)
    assert {r.sample_id: r.generated for r in got.collect()} == want
    assert got._jdf.queryExecution().optimizedPlan().toString().count("Join ") <= 3  # one for each token before


def test_entropy_with_a_prompt_is_that_of_the_whole_vocabulary(spark, monkeypatch):
    rows = spark.createDataFrame([(1, "a b b", "", "b c b c a"), (2, "", "", "a b"), (3, "z c", "", "b b c")], "sample_id long, instruction string, input string, output string")
    base = ngram.BigramTarget.fit(rows)
    pairs, total = {(r.h, r.w): r.n for r in base.pairs.collect()}, {r.h: r.total for r in base.contexts.collect()}
    words = {w for _, w in pairs}
    p = lambda h, w: (pairs.get((h, w), 0) + 0.1) / (total.get(h, 0) + 0.1 * base.v)
    want = {}
    for i, x, y in ((1, "a b b".split(), "b c b c a".split()), (2, [], "a b".split()), (3, "z c".split(), "b b c".split())):
        beta, spots = 0.2 if x else 0.0, [(x[-1] if x else ngram.BOS, y[0]), *zip(y, y[1:], strict=False)]
        m = lambda h, w: (1 - beta) * p(h, w) + beta * x.count(w) / max(1, len(x))  # noqa: E731, B023
        # One token of the vocabulary is unknown; in the third prompt it is z.
        line = lambda h: [m(h, w) for w in words | set(x)] + [(1 - beta) * p(h, "?")] * (base.v - len(words | set(x)))  # noqa: E731, B023
        want[i] = pytest.approx((sum(-math.log(m(*s)) for s in spots) / len(spots), sum(-sum(q * math.log(q) for q in line(h)) for h, _ in spots) / len(spots)))
    made, keep = [], ngram.durable
    monkeypatch.setattr(ngram, "durable", lambda df, name: (made.append((name, df)), keep(df, name))[1])
    target = ngram.PromptCacheTarget(base)
    assert {r[0]: (r.loss, r.entropy) for r in target.metrics(rows).collect()} == want
    # The sample's tokens before, each once; all its places were met with the prompt's words before.
    assert {n: df.count() for n, df in made}["prompt-heads"] == 6
    target.generate(rows).count()
    assert [n for n, _ in made].count("prompt-words") == 1


def test_depths_share_one_fit(spark, small, monkeypatch):
    seen = []
    monkeypatch.setattr(runner, "label_report", lambda *a: spark.range(1))
    monkeypatch.setattr(runner, "depths", lambda spark, d, pool, name, model=None: seen.append(model))
    registry.queries()["experiment_depths"](spark, small)
    assert len(seen) == len(runner.DEPTHS) and seen[0] is not None and all(m is seen[0] for m in seen)


def test_prompt_cache_entropies_meet_only_counted_pairs(spark, small, monkeypatch):
    """A sample's heads times its prompt's tokens are not looked up one by one, and the entropies are those of the plain sum."""
    pool = durable(pool_of(spark, small, "SD-4"), "pool")
    target = runner.models_for(spark, small, ("cache",), pool)[1]["cache"]
    rows = target.scored(pool, "sample_id")
    b, beta = target.base, target.beta
    heads = rows.select("sample_id", "h", "h_entropy", "has")
    met = b.scored(heads.select("sample_id", "h").distinct().join(target.cache(pool, "sample_id"), "sample_id")).withColumn("own", (1 - beta) * F.col("p"))
    fix = met.withColumn("m", F.col("own") + beta * F.col("q")).groupBy("sample_id", "h").agg(F.sum(F.expr("own * ln(own) - m * ln(m)")).alias("fix"))
    mixed = F.when(F.col("has"), (1 - beta) * F.col("h_entropy") - (1 - beta) * float(np.log(1 - beta)) + F.col("fix")).otherwise(F.col("h_entropy"))
    want = {r[0]: r[1] for r in heads.join(fix, ["sample_id", "h"], "left").groupBy("sample_id").agg(F.avg(mixed)).collect()}
    monkeypatch.setattr(ngram.BigramTarget, "scored", lambda *a, **k: pytest.fail("looked up one by one"))
    got = {r.sample_id: r.entropy for r in target.metrics(pool).collect()}
    assert len(want) > 5 and got == pytest.approx(want, abs=1e-9)
