"""Control plane, stages, clustering, streaming, plans and parity on the smallest tables."""

import json
from decimal import Decimal

import numpy as np
import pytest
from pyspark.sql import functions as F

from poolcurator import inspect as I
from poolcurator import registry, schema
from poolcurator.backbone.core import CostLedger, ReplayBackbone, ask
from poolcurator.backbone.rules import RuleBackbone, TaxonomyMatcher
from poolcurator.baselines import selectors as B
from poolcurator.cascade import explain_cascade, run_cascade
from poolcurator.config import CascadeConfig, ConfigRejected, Policy, Rubric, SelectionRequest, Weights
from poolcurator.evaluate import runner
from poolcurator.functions import text as X
from poolcurator.operators import cluster, topk
from poolcurator.operators import relational as R
from poolcurator.sources import files
from poolcurator.sources.adapters import from_documents, read_table
from poolcurator.stages import characteristic as C
from poolcurator.stages import domain, quality
from poolcurator.stages import informativeness as N
from poolcurator.streaming import events as E
from poolcurator.target import ngram
from tests.parity import connect, difference


def test_retries_then_rejects():
    good = json.dumps(Policy().to_dict())
    ledger = CostLedger()
    out = ask(ReplayBackbone({"policy": ["not json", '{"min_total_len": 1}', good]}), "policy", {"request": "x", "observations": {}, "keys": ""}, lambda r: Policy.merge(r, strict=True), ledger=ledger)
    assert out == Policy() and ledger.summary()["failures"] == 2 and ledger.summary()["retries"] == 2
    with pytest.raises(ConfigRejected):
        ask(ReplayBackbone({"weights": ['{"loss": 2}']}), "weights", {"request": "", "observations": {}}, Weights.parse, 2)


@pytest.mark.parametrize("bad", [{"min_total_len": 5000}, {"max_noise_ratio": 2}, {"noise_regex": "["}, {"noise_regex": "(?=a)"}, {"refusal_phrases": "x"}, {"other": 1}, {"min_inst_len": True}])
def test_policy_is_checked(bad):
    with pytest.raises(ConfigRejected):
        Policy.merge(bad)


def test_weights_and_rubric_are_checked():
    assert Weights.parse({"loss": 0, "entropy": 0.5, "drift": 0.25, "mean_diff": 0.25}).validate() == ["loss"]
    for bad in ({"loss": 1}, {"loss": -0.1, "entropy": 0.6, "drift": 0.25, "mean_diff": 0.25}, {"loss": "x", "entropy": 0, "drift": 0, "mean_diff": 1}):
        with pytest.raises(ConfigRejected):
            Weights.parse(bad)
    with pytest.raises(ConfigRejected):
        Rubric.parse({"a": {"description": "", "weight": 0.9}})


def test_matching_takes_any_label_and_lineage():
    m = TaxonomyMatcher({"algebra": "math"})
    clusters = {0: ["algebra"], 1: ["code", "math"], 2: ["mixed"]}
    assert m.match(["math"], clusters) == [0, 1] and m.match([], clusters) == [0, 1, 2]
    with pytest.raises(ConfigRejected):
        domain.match_clusters(SelectionRequest("", ""), [(0, ["a"])], ReplayBackbone({"match": ['{"matching_cluster_ids": [9]}']}))


def test_dominant_weights_follow_the_request():

    for name, metric in (("R-chat", "drift"), ("R-fr", "mean_diff")):
        got = json.loads(RuleBackbone().complete("weights", "", {"request": runner.REQUESTS[name]}))
        assert max(got, key=got.get) == metric and abs(sum(got.values()) - 1) < 1e-9



def test_policy_counts_and_reasons(spark, small):
    s = from_documents(read_table(spark, small, "documents"))
    assert C.match(s, Policy()).count() == 135
    reasons = {r.reason: r["count"] for r in C.reject_reasons(s, Policy()).groupBy("reason").count().collect()}
    assert reasons["kept"] == 135 and sum(reasons.values()) == 200
    nulls = spark.createDataFrame([(1, None, "", "y" * 50, None), (2, "x", "", "", "")], "sample_id long, instruction string, input string, output string, text string")
    assert C.match(nulls, Policy()).count() == 0
    with pytest.raises(ValueError):
        C.match(s.drop("output"), Policy())


def test_tighter_policy_is_a_subset(spark, small):
    s = from_documents(read_table(spark, small, "documents"))
    loose = {r[0] for r in C.match(s, Policy()).select("sample_id").collect()}
    tight = {r[0] for r in C.match(s, Policy(max_noise_ratio=0.01, max_total_len=2000)).select("sample_id").collect()}
    assert tight <= loose


def test_many_refusal_phrases_use_one_pattern(spark):
    df = spark.createDataFrame([("as told (1)",), ("no",)], "output string")
    phrases = tuple(f"phrase{i}" for i in range(10)) + ("told (1)",)
    assert [r[0] for r in df.select(C.refusal_free("output", phrases)).collect()] == [False, True]


def test_unicode_words():
    assert X.unicode_words(r"[^\w\s]\w") == r"[^\p{L}\p{M}\p{N}_\s][\p{L}\p{M}\p{N}_]"


def test_verdict_contract(spark):
    rubric = Rubric.parse({"a": {"description": "d", "weight": 1.0}})
    rows = spark.createDataFrame([(i, "x", "", "y", i // 3) for i in range(18)], "sample_id long, instruction string, input string, output string, batch_id long")

    def judge(prompt, batch):
        if batch[0]["sample_id"] == 3:
            return "garbage"
        if batch[0]["sample_id"] == 6:
            raise RuntimeError("down")
        out = [{"sample_id": b["sample_id"], "scores": {"a": 1 + 2 * b["sample_id"]}, "reasoning": "", "flagged": False} for b in batch]
        if batch[0]["sample_id"] == 9:  # one object too many
            out.append({"sample_id": 99, "scores": {"a": 3}})
        if batch[0]["sample_id"] == 12:  # one sample twice
            out[1] = dict(out[0], scores={"a": 2})
        if batch[0]["sample_id"] == 15:  # one too few
            out.pop()
        return json.dumps(out)

    raw = quality.score_batches(rows, rubric, judge)
    got = quality.parse_verdicts(raw).collect()
    assert sorted((r.sample_id, r.q) for r in got) == [(0, 1), (1, 3), (2, 5)]
    ledger = CostLedger(price_in=Decimal(3), price_out=Decimal(15))
    quality.bill(raw, ledger)
    assert ledger.summary()["calls"] == 6 and ledger.summary()["failures"] == 1 and ledger.summary()["usd"] > 0


def test_guarded_select(spark, small):
    s = from_documents(read_table(spark, small, "documents"))
    assert I.guarded_select(s, "SELECT lang, count(*) AS n FROM pool GROUP BY lang").count() == 4
    for bad in ("DROP TABLE x", "SELECT 1; SELECT 2", "SELECT * FROM other", "SELECT * FROM pool, x", "INSERT INTO pool SELECT 1", "SELECT * FROM parquet.`/x`", "WITH a AS (SELECT 1) SELECT * FROM a"):
        with pytest.raises(I.UnsafeQuery):
            I.guarded_select(s, bad)


def test_cascade_is_nested_and_exact(spark, small):
    pool = runner.pool_of(spark, small, "SD-1")
    cfg = CascadeConfig(k=20, n_c=500)
    r = run_cascade(pool, runner.request("R-en"), runner.target_for(spark, small, "bigram"), cfg)
    ids = [{x[0] for x in r.survivors[s].select("sample_id").collect()} for s in (0, 1, 2, 3, 4)]
    assert all(b <= a for a, b in zip(ids, ids[1:])) and len(ids[3]) == min(60, len(ids[2])) and len(ids[4]) == 20
    assert [x.rank for x in r.selected.orderBy("rank").collect()] == list(range(1, 21))
    assert explain_cascade(1000, cfg)["judge_calls"] == 6 and r.ledger.summary()["calls"] == 6  # three looks, three configurations
    again = run_cascade(pool.repartition(9), runner.request("R-en"), runner.target_for(spark, small, "bigram"), cfg)
    assert {x.sample_id for x in again.selected.collect()} == ids[4]


def test_ties_are_kept_by_both_ways_to_the_top(spark):
    rows = [(i, 1.0 if i < 40 else float(i % 3), float(i * 7 % 11)) for i in range(120)]
    df = spark.createDataFrame(rows, "sample_id long, q double, score double")
    for k in (5, 30, 60, 100):
        heap = topk.top_k(df, "q", k, ties=("score",))
        assert {r[0] for r in heap.collect()} == {r[0] for r in topk.threshold_top_k(df, "q", k, ties=("score",)).collect()}
        one = {(r.sample_id, r["rank"]) for r in topk.with_rank(heap, "q", k).collect()}
        assert one == {(r.sample_id, r["rank"]) for r in topk.with_rank(heap, "q", k, heap_rows=7).collect()}


def test_generation_walks_and_doubles_alike(spark, small, monkeypatch):
    pool = runner.pool_of(spark, small, "MD-1")
    target = runner.target_for(spark, small, "bigram")
    walked = {(r.sample_id, r.generated) for r in target.generate(pool).collect()}
    monkeypatch.setattr(ngram, "BROADCAST_ROWS", 0)
    assert walked == {(r.sample_id, r.generated) for r in target.generate(pool).collect()} and len(walked) == 200


def test_generation_by_the_tokens_met_from_the_second_step_on(spark, small, monkeypatch):
    pool = runner.pool_of(spark, small, "SD-5")
    target = runner.target_for(spark, small, "bigram")
    walked = {(r.sample_id, r.generated) for r in target.generate(pool).collect()}
    n, inner = target.contexts.count(), target.best().select("last").distinct().count()
    monkeypatch.setattr(ngram, "BROADCAST_ROWS", inner)
    assert inner < n and not target._chains
    target._best = None
    assert walked == {(r.sample_id, r.generated) for r in target.generate(pool).collect()} and walked
    assert not target._chains  # chains of all contexts were built before


@pytest.mark.parametrize("most", [500_000, 100, 0])
def test_cache_generation_ends_when_a_token_comes_back(spark, small, most, monkeypatch):
    docs = runner.pool_of(spark, small, "SD-3").select("sample_id", "instruction", "output").limit(30)
    rows = docs.unionByName(spark.createDataFrame([(-1, "", "a"), (-2, "unknown0 unknown1", "b"), (-3, None, "c")], docs.schema))
    base = ngram.BigramTarget.fit(runner.pool_of(spark, small, "SD-3"))
    pairs, total, best = {(r.h, r.w): r.n for r in base.pairs.collect()}, {r.h: r.total for r in base.contexts.collect()}, {r.h: r.last for r in base.best().collect()}
    p = lambda h, w: (pairs.get((h, w), 0) + 0.1) / (total.get(h, 0) + 0.1 * base.v)
    plain = {}
    for r in rows.withColumn("t", X.tokens("instruction")).collect():
        said, words = [], r.t or []
        h = words[-1] if words else ngram.BOS
        for _ in range(20):
            options = [(round(0.8 * p(h, w) + 0.2 * words.count(w) / len(words), 12), w) for w in set(words)]
            options += [(round(0.8 * p(h, best[h]), 12), best[h])] if h in best else []
            if not options:
                break
            h = max(options)[1]
            said.append(h)
        plain[r.sample_id] = " ".join(said)
    rounds = []
    keep = ngram.durable
    monkeypatch.setattr(ngram, "durable", lambda df, name: (rounds.append(name), keep(df, name))[1])
    monkeypatch.setattr(ngram, "BROADCAST_ROWS", most)
    got = {r.sample_id: r.generated for r in ngram.PromptCacheTarget(base).generate(rows).collect()}
    assert got == plain and len(got) == rows.count()
    assert rounds.count("said") < 21  # one a token before
    base.generate(rows).count()
    assert rounds.count("best") == 1  # one for each of the two targets before


def test_metrics_do_not_depend_on_the_order_of_samples(spark, small):
    pool = runner.pool_of(spark, small, "SD-3")
    target = runner.target_for(spark, small, "bigram")
    whole = {r.sample_id: (r.loss, r.mean_diff) for r in N.measure(pool, target).collect()}
    part = N.measure(pool.where("sample_id > 60").orderBy(F.desc("sample_id")).repartition(3), target).collect()
    assert part and all(whole[r.sample_id] == pytest.approx((r.loss, r.mean_diff)) for r in part if r.loss is not None)


def test_every_target_generates(spark, small):
    rows = spark.createDataFrame([(1, "a b", "", "c d c d"), (2, "q", "", "c c")], "sample_id long, instruction string, input string, output string")
    base = ngram.BigramTarget.fit(rows)
    said = {r.sample_id: r.generated for r in ngram.PromptCacheTarget(base, 0.9).generate(rows, 4).collect()}
    assert said[2] == "q q q q" and set(said[1].split()) <= {"a", "b", "c", "d"} and len(said[1].split()) == 4
    assert {r.generated for r in ngram.UnigramTarget.fit(rows).generate(rows, 3).collect()} == {"c c c"}
    table = spark.createDataFrame([(1, [-1.0], [0.5], "c d", 0.25)], "sample_id long, lps array<double>, ents array<double>, generated string, shift double")
    got = N.measure(rows.where("sample_id = 1"), ngram.PrecomputedTarget(table)).first()
    assert got.loss == 1.0 and got.mean_diff == 0.25 and 0 < got.drift < 0.5


def test_backbone_chooses_what_to_look_at(spark, small):
    s = from_documents(read_table(spark, small, "documents"))
    reply = json.dumps({"probes": ["languages"], "queries": ["SELECT count(*) AS n FROM pool", "DROP TABLE pool"]})
    canned = ReplayBackbone({"inspect": [reply]})
    canned.inspects = True
    ledger = CostLedger()
    got = I.inspect_pool(s, 3, canned, runner.request("R-en"), ledger)
    assert len(got["probes"]["languages"]) == 4 and got["queries"]["SELECT count(*) AS n FROM pool"] == [{"n": 200}]
    assert got["queries"]["DROP TABLE pool"].startswith("refused") and ledger.table()[0][1:3] == (3, "inspect")


def test_boundary_of_clusterers():
    assert cluster.choose_clusterer(50_000) == "hdbscan" and cluster.choose_clusterer(50_001) == "kmeans"


@pytest.mark.parametrize("block", [2000, 37])
def test_density_clusters_find_blobs(spark, block):
    rng = np.random.default_rng(0)
    pts = np.concatenate([rng.normal(c, 0.3, (60, 2)) for c in ((0, 0), (5, 5), (0, 6))] + [rng.uniform(-20, 20, (15, 2))])
    df = spark.createDataFrame([(i, p.tolist()) for i, p in enumerate(pts)], "sample_id long, embedding array<double>")
    got = {r.sample_id: r.cluster_id for r in cluster.hdbscan(df, 20, 5, "own_cluster", block=block).collect()}
    for b in range(3):
        labels = [got[i] for i in range(60 * b, 60 * b + 60)]
        top = max(set(labels), key=labels.count)
        assert top >= 0 and labels.count(top) >= 54
    assert len({got[i] for i in range(180)} - {-1}) == 3
    assert cluster.hdbscan(df, 20, 5, "nearest", block=block).where("cluster_id < 0").count() == 0
    assert cluster.hdbscan(df, 20, 5, "drop", block=block).count() == sum(v >= 0 for v in got.values())


def test_spanning_tree_weight_is_minimal(spark):
    rng = np.random.default_rng(1)
    pts = rng.normal(size=(70, 3))
    df = spark.createDataFrame([(i, p.tolist()) for i, p in enumerate(pts)], "sample_id long, embedding array<double>")
    _, w, _, _ = cluster.mutual_tree(df, 4, block=20)
    d = np.sqrt(((pts[:, None] - pts[None]) ** 2).sum(-1))
    core = np.sort(d, axis=1)[:, 3]
    m = np.maximum(d, np.maximum(core[:, None], core[None]))
    np.fill_diagonal(m, np.inf)
    assert w.sum() == pytest.approx(cluster._prim(m)[0].sum())


def test_kmeans_branch(spark, small):
    pool = runner.pool_of(spark, small, "MD-1")
    got = domain.cluster_pool(pool, CascadeConfig(k=20, n_c=50, k_c=6, n_init=2))
    j = got.join(pool.select("sample_id", "lang"), "sample_id").groupBy("cluster_id", "lang").count().groupBy("cluster_id").agg(F.max("count").alias("m"), F.sum("count").alias("n")).agg(F.sum("m") / F.sum("n")).first()[0]
    assert j > 0.85


def test_plans(spark, small):
    s = from_documents(read_table(spark, small, "documents"))
    plan = C.match(s, Policy(), stored_length=True).select("sample_id")._jdf.queryExecution().executedPlan().toString()
    assert "GreaterThanOrEqual(n_chars,40)" in plan and "Python" not in plan and "Exchange" not in plan
    plan = registry.queries()["info_topk"](spark, small)._jdf.queryExecution().executedPlan().toString()
    assert "TakeOrderedAndProject" in plan
    plan = registry.queries()["cluster_sample"](spark, small)._jdf.queryExecution().executedPlan().toString()
    assert "WindowGroupLimit" in plan
    plan = registry.queries()["scan_parquet"](spark, small)._jdf.queryExecution().executedPlan().toString()
    assert "ReadSchema: struct<doc_id:bigint,n_chars:bigint>" in plan


def test_stream_equals_batch(spark, small):
    got = {(r.sample_id, r.score) for r in E.replay_documents(spark, small).collect()}
    s = from_documents(read_table(spark, small, "documents"))
    want = E.scored(s, Policy(), E.WEIGHTS, E.BOUNDS, E.seeded_metrics, E.FLOOR)
    assert got == {(r.sample_id, r.score) for r in want.select("sample_id", F.round("score", 6).alias("score")).collect()}


def run_stream(spark, df, name, mode="append"):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


@pytest.fixture(scope="module")
def event_stream(spark, small, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("events") / "in")
    e = read_table(spark, small, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    e.orderBy("ts").coalesce(1).write.parquet(path)
    return e, lambda: spark.readStream.schema(e.schema).parquet(path)


def test_stream_windows_dedup_and_joins(spark, small, event_stream):
    e, stream = event_stream
    got = {(r.window.start, r.event_type): r.n for r in run_stream(spark, E.tumbling(stream(), "1 day", "1 hour"), "s_tumbling", "complete").collect()}
    assert got == {(r.window.start, r.event_type): r.n for r in E.tumbling(e, "1 day").collect()}
    assert run_stream(spark, E.deduplicated(stream().unionByName(stream())), "s_dedup").count() == e.count()
    c = read_table(spark, small, "customer")
    assert run_stream(spark, E.with_static(stream(), c), "s_static").count() == E.with_static(e, c).count()
    pairs = {tuple(r) for r in run_stream(spark, E.paired(stream(), stream(), within="10 hours", late="12 hours"), "s_pairs").collect()}
    assert pairs and pairs == {tuple(r) for r in R.interval_pairs(e, "view", "purchase", 36_000).collect()}


def test_running_top_k(spark, small, tmp_path):
    docs = read_table(spark, small, "documents").select(F.col("doc_id").alias("sample_id"), F.col("n_chars").cast("double").alias("score"))
    docs.repartition(4).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(docs.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    E.running_top_k(stream, str(tmp_path / "top"), 7).option("checkpointLocation", str(tmp_path / "ck")).trigger(availableNow=True).start().awaitTermination()
    last = max(int(p.name) for p in (tmp_path / "top").iterdir())
    got = {r.sample_id for r in spark.read.parquet(str(tmp_path / "top" / str(last))).collect()}
    assert got == {r.sample_id for r in docs.orderBy(F.desc("score"), "sample_id").limit(7).collect()}


def test_late_rows_are_counted_and_not_merged(spark, tmp_path):
    folder = str(tmp_path / "in")
    row = lambda t, n: spark.createDataFrame([(f"2024-01-01 {t}:00", "click", float(n))], "ts string, event_type string, value double").select(F.to_timestamp("ts").alias("ts"), "event_type", "value")
    first = row("10:00", 1)
    first.write.parquet(folder)
    q = E.tumbling(spark.readStream.schema(first.schema).parquet(folder), "10 minutes", "5 minutes").writeStream.format("memory").queryName("s_late").outputMode("append").start()
    q.processAllAvailable()
    for t, n in (("11:00", 2), ("10:01", 4), ("12:00", 8)):  # the third comes after the watermark
        row(t, n).write.mode("append").parquet(folder)
        q.processAllAvailable()
    assert E.late_rows(q) == 1
    q.stop()
    assert {(r.window.start.hour, r.total) for r in spark.table("s_late").collect()} == {(10, 1.0), (11, 2.0)}


def test_windowed_pass_rate(spark):
    rows = [(i, "x" * 10, "", "y" * (100 if i % 4 else 3), "x" * 10 + "y" * 100, "s", f"2024-01-01 1{i % 2}:00:00") for i in range(40)]
    df = spark.createDataFrame(rows, "sample_id long, instruction string, input string, output string, text string, source string, ts string").withColumn("ts", F.to_timestamp("ts"))
    got = {r.window.start.hour: (r.rate, r.n, r.alarm) for r in E.pass_rate_alarm(df, Policy(), 1.0, 0.1, "1 hour").collect()}
    assert got == {10: (0.5, 20, True), 11: (1.0, 20, False)}


def test_a_restarted_stream_goes_on_from_its_checkpoint(spark, small, tmp_path):
    docs = read_table(spark, small, "documents")
    a, b = docs.where("doc_id < 120"), docs.where("doc_id >= 120")
    folder, out, mark = (str(tmp_path / n) for n in ("in", "out", "mark"))
    for part in (a, b):
        part.write.mode("append").parquet(folder)
        s = from_documents(spark.readStream.schema(docs.schema).parquet(folder))
        rows = E.scored(s, Policy(), E.WEIGHTS, E.BOUNDS, E.seeded_metrics, E.FLOOR).select("sample_id", "score")
        rows.writeStream.format("parquet").option("path", out).option("checkpointLocation", mark).trigger(availableNow=True).start().awaitTermination()
    got = [r.sample_id for r in spark.read.schema(rows.schema).parquet(out).collect()]
    want = E.scored(from_documents(docs), Policy(), E.WEIGHTS, E.BOUNDS, E.seeded_metrics, E.FLOOR)
    assert len(got) == len(set(got)) and set(got) == {r.sample_id for r in want.collect()}


def test_buckets_join_without_a_shuffle(spark, small):
    from poolcurator.plans import shapes
    from poolcurator.workloads.source_queries import bucketed_join

    joined = bucketed_join(spark, small)
    assert shapes.operators(joined)["SortMergeJoin"] == 1 and shapes.operators(joined)["Exchange"] == 0


def test_plans_of_comparators(spark, small):
    from poolcurator.plans import shapes

    q = registry.queries()
    assert not shapes.uses_python(q["sim_text"](spark, small)) and not shapes.uses_python(q["dsir_logratio"](spark, small))
    plan = q["metric_nll"](spark, small)
    assert shapes.operators(plan)["BroadcastHashJoin"] == 2 and shapes.operators(plan)["SortMergeJoin"] == 0  # counted and small
    assert any("lang" in f for f in shapes.pushed_filters(runner.pool_of(spark, small, "SD-1").select("sample_id")))


def test_wide_neighbourhoods_cost_alignment(spark):
    near = spark.createDataFrame([(0, i, 1 - d) for i, d in enumerate((0.0, 0.1, 0.2, 0.8))], "query int, vec_id long, similarity double")
    width = lambda a: B.aligned(near, a).count()
    assert [width(a) for a in (0.999, 0.8, 0.5, 0.3)] == [1, 2, 3, 4] and width(0.9) == 2


def test_light_rows_can_be_drawn(spark):
    mass = spark.range(40_000).select(F.lit(0).alias("query"), F.col("id").alias("vec_id"), F.lit(2e-8).alias("mass"))
    got = B.categorical_draw(mass, 2_000).collect()
    assert len(got) == 2_000 and len({r.vec_id for r in got}) > 1_900
    heavy = spark.createDataFrame([(0, 1, 0.75), (0, 2, 0.25), (0, 3, 0.0)], "query int, vec_id long, mass double")
    drawn = [r.vec_id for r in B.categorical_draw(heavy, 4_000).collect()]
    assert len(drawn) == 4_000 and abs(drawn.count(1) - 3_000) < 150 and 3 not in drawn


def test_comparators_keep_to_their_terms(spark, small):
    pool = runner.pool_of(spark, small, "SD-1")
    with pytest.raises(ConfigRejected):
        B.deft(pool, None, None, 5, mode="multi")
    canned = ReplayBackbone({"plan": ['{"max_noise": 2}', json.dumps({"max_noise": 1.0, "min_output": 0, "variety": 0, "clean": 0, "length": 1})]})
    ledger = CostLedger()
    best = B.single_pass(pool, 3, runner.request("R-en"), canned, ledger=ledger).collect()
    assert len(best) == 3 and ledger.summary()["calls"] == 2 and ledger.summary()["retries"] == 1
    ids = runner.pool_of(spark, small, "MD-2").select("sample_id")
    assert ids.count() == ids.distinct().count()
    with pytest.raises(ValueError):
        B.held_by_all(spark.range(5), "rows", 4)


def test_paid_judge_is_in_the_ledger(spark, small):
    pool = runner.pool_of(spark, small, "SD-1")
    ledger = CostLedger("r", Decimal(5), Decimal(25))
    r = run_cascade(pool, runner.request("R-en"), runner.target_for(spark, small, "unigram"), CascadeConfig(k=10), stages=(2, 3, 4), judge=lambda rubric: quality.rule_judge(list(rubric.weights)), ledger=ledger)
    calls = {(row[1], row[2]): row[3] for row in ledger.table()}
    assert calls[4, "judge"] == 3 and r.selected.count() == 10 and ledger.summary()["usd"] > 0


def test_idempotent_sink_and_replay_source(spark, tmp_path):
    path = str(tmp_path / "stage")
    for _ in range(2):
        files.write_stage(spark.range(5).toDF("sample_id"), path, "r1", "b0")
    files.write_stage(spark.range(3).toDF("sample_id"), path, "r1", "b1")
    assert spark.read.parquet(path).count() == 8
    spark.dataSource.register(files.ReplayVerdicts)
    raw = spark.read.format("replay_verdicts").options(rows=14, partitions=3, broken_every=7).load()
    assert raw.count() == 14 and quality.parse_verdicts(raw).count() == 12


def test_salted_join_and_running_total(spark):
    df = spark.range(1000).select("id", (F.col("id") % 3).alias("k"), F.lit(2).alias("v"))
    assert {(r.k, r.total) for r in R.salted_sum(df, "k", "v", "id").collect()} == {(0, 668), (1, 666), (2, 666)}
    assert R.running_total(df, "v", "id", 7).where("total <> (id + 1) * 2").count() == 0


def test_schemas_parse():
    for ddl in (schema.SAMPLE, schema.POLICY, schema.WEIGHTS, schema.METRIC, schema.SELECT, schema.LEDGER, schema.OBSERVATION):
        assert schema.struct(ddl).fields


#: One query of each kind; the driver holds all of them against DuckDB on larger tables.
PARITY = "policy_filter metric_nll metric_drift kmeans_assign cluster_sample quality_topk base_ifd base_dsir base_tsds base_joint_rank deft_score selectit_model acc_exact measure_shared_lr join_asof join_range win_cume_dist agg_cube scrub_pii json_schema events_session ingest_pages".split()


@pytest.mark.parametrize("name", PARITY)
def test_parity(spark, small, name):
    assert difference(registry.queries()[name](spark, small), connect(small), registry.oracle_sql()[name]) == ""


def test_registry_needs_no_session():
    import subprocess
    import sys
    from pathlib import Path

    out = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; print(len(e.queries()), set(e.oracle_sql()) <= set(e.queries()))"], cwd=Path(__file__).parents[1], capture_output=True, text=True)
    assert out.stdout.split()[-1] == "True", out.stderr
