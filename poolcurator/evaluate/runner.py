"""Experiments: pools, requests and comparators, each with the same budget, and what can be measured of the subsets."""

from __future__ import annotations

from decimal import Decimal
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from poolcurator.backbone.core import CostLedger
from poolcurator.backbone.rules import RuleBackbone
from poolcurator.baselines import selectors as B
from poolcurator.cascade import run_cascade
from poolcurator.config import METRICS, CascadeConfig, SelectionRequest, budget_for
from poolcurator.functions import text as X
from poolcurator.operators.embed import embed, embed_counted
from poolcurator.operators.topk import random_k, top_k
from poolcurator.sources.adapters import pool_of, read_table
from poolcurator.sources.files import durable
from poolcurator.stages import quality
from poolcurator.stages.domain import labelled_clusters, select_domain
from poolcurator.target.ngram import BigramTarget, Known, Measured, PromptCacheTarget, UnigramTarget

#: Requests in our own words, by id.
REQUESTS = {
    "R-en": "This pool is all English. Keep tidy, well structured samples and leave out junk.",
    "R-fr": "This pool is all French. Prefer accurate, reliable wording with precise terms.",
    "R-chat": "This pool is all chat. Keep replies laid out step by step that answer the question.",
    "R-mix-en": "The pool mixes languages. Take the English samples, clean and non-trivial.",
    "R-mix-de": "The pool mixes languages. Take the German samples, clean and non-trivial.",
    "R-mix-es": "The pool mixes languages. Take the Spanish samples, clean and non-trivial.",
    "R-any": "Take generally good samples.",
}
SINGLE = (("SD-1", "R-en"), ("SD-2", "R-en"), ("SD-3", "R-fr"), ("SD-4", "R-fr"), ("SD-5", "R-chat"), ("SD-6", "R-chat"))
MULTI = (("MD-1", "R-mix-en"), ("MD-1", "R-mix-de"), ("MD-1", "R-mix-es"), ("MD-2", "R-mix-en"), ("MD-2", "R-mix-de"))
TARGETS = ("unigram", "bigram", "cache")
DEPTHS = (("SD-1", "R-en"), ("SD-2", "R-en"), ("SD-3", "R-fr"), ("SD-5", "R-chat"))
#: Cosine between character-bigram vectors above which the diverse score skips a sample; texts of one language are all alike there.
TAU = 0.985
#: Target examples of a multi-domain comparator.
EXAMPLES = 100

#: Licences by source, as a table to filter on.
LICENCES = {f"src{i}": ("apache-2.0", "mit", "cc-by-4.0", "cc-by-nc-4.0", "unknown")[i % 5] for i in range(20)}
ALLOWED = ("apache-2.0", "mit", "cc-by-4.0")


def request(name: str) -> SelectionRequest:
    return SelectionRequest(name, REQUESTS[name])


#: Smoothing of the targets, and of the proxy: a flatter model of the same tokens.
SMOOTHING, PROXY_SMOOTHING = 0.1, 1.0


def target_for(spark: SparkSession, sf_dir: str, name: str):
    """The stand-in model by name, fitted on all documents."""
    docs = pool_of(spark, sf_dir, "MD-1")
    if name == "unigram":
        return UnigramTarget.fit(docs)
    base = BigramTarget.fit(docs)
    return base if name == "bigram" else PromptCacheTarget(base)


def proxy_for(spark: SparkSession, sf_dir: str) -> BigramTarget:
    """The small proxy of the difficulty score, which is none of the targets."""
    return BigramTarget.fit(pool_of(spark, sf_dir, "MD-1"), PROXY_SMOOTHING)


def models_for(spark: SparkSession, sf_dir: str, names: tuple[str, ...], pool: DataFrame | None = None) -> tuple[BigramTarget, dict[str, object]]:
    """The proxy and the targets by name, all from one count of the documents' tokens, and of a pool from one table of its tokens."""
    base, proxy = BigramTarget.fit_all(pool_of(spark, sf_dir, "MD-1"), (SMOOTHING, PROXY_SMOOTHING))
    if pool is not None:
        base.known = proxy.known = Known(pool, base.known_tokens(pool))
    make = {
        "unigram": lambda: UnigramTarget.of(base.words, SMOOTHING, base.known),
        "bigram": lambda: base,
        "cache": lambda: PromptCacheTarget(base),
    }
    return proxy, {n: make[n]() for n in names}


def config(pool: DataFrame, **changes) -> CascadeConfig:
    return CascadeConfig(k=budget_for(pool.count()), **changes)


def cascade(spark: SparkSession, sf_dir: str, pool_name: str, request_name: str, target: str = "bigram", stages=(1, 2, 3, 4), judge=None, ledger=None, model=None, **changes):
    """One run; `model` is a target that an earlier run has fitted."""
    pool = pool_of(spark, sf_dir, pool_name)
    return run_cascade(pool, request(request_name), model or target_for(spark, sf_dir, target), config(pool, **changes), stages=stages, judge=judge, ledger=ledger)


def methods(rows: list[tuple[str, DataFrame]]) -> DataFrame:
    """(method, sample_id) of named subsets."""
    return reduce(DataFrame.unionByName, [df.select(F.lit(name).alias("method"), "sample_id") for name, df in rows])


def picked(spark: SparkSession, ids: list[int]) -> DataFrame:
    return spark.createDataFrame([(i,) for i in ids], "sample_id long")


def depths(spark: SparkSession, sf_dir: str, pool_name: str = "SD-1", request_name: str = "R-en", target: str = "bigram", model=None) -> DataFrame:
    """(method, sample_id): what the cascade would select if it ended after stage 2, 3 or 4; one run knows all three."""
    pool = pool_of(spark, sf_dir, pool_name)
    cfg = config(pool)
    r = run_cascade(pool, request(request_name), model or target_for(spark, sf_dir, target), cfg, stages=(2, 3, 4))
    return methods([("2", random_k(r.survivors[2], cfg.k, cfg.seed)), ("2+3", top_k(r.scores[3], "score", cfg.k)), ("2+3+4", r.selected)])


def stage1_then_ifd(spark: SparkSession, sf_dir: str, pool_name: str = "MD-1", request_name: str = "R-mix-en", labelled=None) -> DataFrame:
    """The difficulty score on the first stage's output."""
    pool = pool_of(spark, sf_dir, pool_name)
    cfg = config(pool)
    kept = select_domain(pool, request(request_name), RuleBackbone(), cfg, labelled=labelled)
    return B.ifd_top_k(kept, proxy_for(spark, sf_dir), cfg.k)


def tags_of(pool: DataFrame) -> DataFrame:
    """(sample_id, tag, quality): language and source as tags, with a seeded stand-in for the tagger's quality."""
    tags = F.array_compact(F.array("lang", "source"))
    return pool.select("sample_id", F.explode(F.when(F.size(tags) > 0, tags).otherwise(F.array("pool"))).alias("tag"), X.seeded_uniform("sample_id", "tagq").alias("quality"))


def text_rankers(pool: DataFrame, labels: DataFrame) -> DataFrame:
    """(sample_id, complexity, quality) of the two distilled rankers: difficulty from rollouts of half the pool, quality from labels.

    A pool without labels of its own, such as chats, takes its cleanness for quality.
    """
    u = X.seeded_uniform(F.concat_ws("|", F.col("sample_id").cast("string"), F.col("t").cast("string")), "rollout")
    f = durable(pool.select("sample_id", F.length("text").alias("n"), F.log1p(F.length("text")).alias("size"), X.unique_share("text").alias("variety"), X.share_of("text", X.noise_class()).alias("noise"), X.share_of("text", "[A-Z]").alias("upper")), "ranker-features")
    solved = f.select("sample_id", "n", F.explode(F.sequence(F.lit(0), F.lit(7))).alias("t")).select("sample_id", (u < 1.0 / (1 + F.col("n") / 2000.0)).alias("correct"))
    half = F.pmod(F.xxhash64("sample_id"), F.lit(2)) == 0  # the rest gets its difficulty from the fit
    known = B.solve_rate(solved).where(half).select("sample_id", (1 - F.col("rate")).alias("difficulty"))
    rows = f.join(known, "sample_id", "left").join(labels.select(F.col("doc_id").alias("sample_id"), F.col("quality").cast("double").alias("label")), "sample_id", "left")
    spread = B.fit_difficulty(rows, ("size", "variety"))(rows).withColumnRenamed("prediction", "complexity")
    if rows.where("label IS NOT NULL").select(F.count_distinct("label")).first()[0] < 2:
        return spread.select("sample_id", "complexity", (1 - F.col("noise")).alias("quality"))
    rank = B.fit_ranker(spread.where("label IS NOT NULL"), ("variety", "noise", "upper"))
    return rank(spread).select("sample_id", "complexity", F.col("p").alias("quality"))


def pool_labels(spark: SparkSession, sf_dir: str, pool_name: str) -> DataFrame:
    """Labels of the pool's samples; chats have none, and their ids are no document's."""
    labels = read_table(spark, sf_dir, "labels")
    return labels.limit(0) if pool_name in ("SD-5", "SD-6") else labels


def compare(spark: SparkSession, sf_dir: str, pool_name: str, request_name: str, targets: tuple[str, ...] = ("bigram",)) -> DataFrame:
    """(target, method, sample_id): every single-domain comparator's subset and the cascade's at the same budget.

    Comparators that ask no target are run once and stand in every target's rows. The models share one count of the
    tokens and one table of the pool's token rows, the diverse scores one table of vectors, and the cascades what they find
    out before they ask their target.
    """
    pool = durable(pool_of(spark, sf_dir, pool_name), "pool")
    cfg = config(pool)
    proxy, models = models_for(spark, sf_dir, targets, pool)
    k, tags = cfg.k, tags_of(pool)
    vectors = durable(embed(pool.select("sample_id", "text")).select("sample_id", "embedding"), "vectors")
    tokens = B.rating_probabilities(pool).select("sample_id", "prompt_id", "model", B.selectit_token().alias("token"))
    rated = B.selectit_model(B.selectit_sentence(tokens), {"7B": 7.0, "13B": 13.0}).withColumn("score", F.round("score", 6))
    ranks = durable(text_rankers(pool, pool_labels(spark, sf_dir, pool_name)), "rankers")
    joint = pool.select("sample_id", B.effective_length().alias("length")).join(ranks.select("sample_id", F.round("complexity", 6).alias("difficulty")), "sample_id")
    common = durable(
        methods(
            [
                ("full_pool", B.full_pool(pool)),
                ("random", random_k(pool, k)),
                ("ifd", B.ifd_top_k(pool, proxy, k)),
                ("rating", top_k(rated, "score", k)),
                ("tag_gain", picked(spark, [i for i, _ in B.mig_greedy(tags, B.tag_edges(tags), k)])),
                ("joint_rank", B.joint_rank(joint, k)),
                ("single_pass", B.single_pass(pool, k, request(request_name), RuleBackbone())),
            ]
        ),
        "common",
    )
    out, front = [], {}
    for name, target in models.items():
        own = [("diverse_score", picked(spark, B.deft(pool, target, ranks, k, tau=TAU, vectors=vectors))), ("cascade", run_cascade(pool, request(request_name), target, cfg, front=front).selected)]
        out.append(common.unionByName(methods(own)).select(F.lit(name).alias("target"), "method", "sample_id"))
    return reduce(DataFrame.unionByName, out)


def compare_multi(spark: SparkSession, sf_dir: str, pool_name: str, requests: tuple[str, ...], target: str = "bigram") -> DataFrame:
    """(request, method, sample_id): the multi-domain comparators and the cascade for each request; clusters are named once.

    So is all that knows no request: both models come from one count of the tokens and score the pool in one pass, and vectors,
    bags of n-grams and the neighbours of all requests' examples are made once.
    """
    pool = durable(pool_of(spark, sf_dir, pool_name), "pool")
    cfg = config(pool)
    base, proxy = BigramTarget.fit_all(pool_of(spark, sf_dir, "MD-1"), (SMOOTHING, PROXY_SMOOTHING))
    if target == "bigram":
        base.measured = proxy.measured = Measured(pool, base.measure(pool, (SMOOTHING, PROXY_SMOOTHING)))
    model = {"unigram": lambda: UnigramTarget.of(base.words, SMOOTHING), "bigram": lambda: base, "cache": lambda: PromptCacheTarget(base)}[target]()
    counted = durable(embed_counted(pool.select("sample_id", "text")).select("sample_id", "embedding", "counts"), "vectors")
    k, labelled = cfg.k, labelled_clusters(pool, RuleBackbone(), cfg, vectors=counted.select("sample_id", "embedding"))
    vectors, bags = counted.select(F.col("sample_id").alias("vec_id"), "embedding"), B.Bags.of(pool)
    langs = {name: RuleBackbone.wanted(REQUESTS[name])[0] for name in requests}
    # The target examples: a seeded draw of the benchmark's size from the wanted language.
    drawn_from = {lang: durable(random_k(pool.where(F.col("lang") == lang), EXAMPLES), "examples") for lang in dict.fromkeys(langs.values())}
    wanted = reduce(DataFrame.unionByName, [e.select(F.col("sample_id").alias("vec_id")) for e in drawn_from.values()])  # a sample has one language
    near = durable(B.aligned(B.knn(vectors.join(F.broadcast(wanted), "vec_id", "left_semi"), vectors), 0.6), "near")
    mass = durable(B.kde_mass(near, vectors), "mass")
    out = []
    for name, lang in langs.items():
        examples = drawn_from[lang]
        drawn = B.categorical_draw(mass.join(F.broadcast(examples.select(F.col("sample_id").alias("query"))), "query", "left_semi"), k).select(F.col("vec_id").alias("sample_id"))
        kept = select_domain(pool, request(name), RuleBackbone(), cfg, labelled=labelled)
        sets = [
            ("tag_ifd", B.tag_then_ifd(pool, proxy, [lang], k)),
            ("sim_ifd", B.sim_then_ifd(pool, B.text_similarity(pool, examples, reference_key="sample_id", counts=counted), proxy, cfg.k_star, k)),
            ("resampling", B.dsir(pool, examples, k, target_key="sample_id", bags=bags)),
            ("transport", drawn),
            ("single_pass", B.single_pass(pool, k, request(name), RuleBackbone())),
            ("stage1_ifd", B.ifd_top_k(kept, proxy, k)),
            ("cascade", run_cascade(pool, request(name), model, cfg, labelled=labelled).selected),
        ]
        out.append(durable(methods(sets).select(F.lit(name).alias("request"), "method", "sample_id"), "subsets"))
    return reduce(DataFrame.unionByName, out)


def precision_report(subsets: DataFrame, pool: DataFrame) -> DataFrame:
    """(request, method, n, precision): the share of each subset in the wanted language; repeated draws count."""
    wanted = F.create_map(*[F.lit(x) for name in REQUESTS for x in (name, (RuleBackbone.wanted(REQUESTS[name]) or [""])[0])])
    j = subsets.join(pool.select("sample_id", "lang"), "sample_id")
    return j.groupBy("request", "method").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg((F.col("lang").eqNullSafe(wanted[F.col("request")])).cast("double")), 4).alias("precision"))


def label_report(subsets: DataFrame, labels: DataFrame, by: tuple[str, ...] = ("method",)) -> DataFrame:
    """(*by, n, labelled, quality, toxic) of every subset."""
    j = subsets.join(labels.select(F.col("doc_id").alias("sample_id"), "quality", "toxic"), "sample_id", "left")
    return j.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), F.count("quality").alias("labelled"), F.round(F.avg("quality"), 4).alias("quality"), F.round(F.avg("toxic"), 4).alias("toxic"))


def costs(spark: SparkSession, sf_dir: str, price_in: Decimal = Decimal(5), price_out: Decimal = Decimal(25)) -> list[tuple]:
    """Ledger rows of a single-domain and a multi-domain run whose judge is a callable that is paid by the token; prices are dollars per million."""
    out, model = [], target_for(spark, sf_dir, "bigram")  # fitted on all documents, so it serves both
    for run, pool_name, request_name in (("single", "SD-1", "R-en"), ("multi", "MD-1", "R-mix-en")):
        ledger = CostLedger(run, price_in, price_out)
        cascade(spark, sf_dir, pool_name, request_name, judge=lambda rubric: quality.rule_judge(list(rubric.weights)), ledger=ledger, model=model)
        out += ledger.table()
    return out


def weight_allocations(chats: DataFrame) -> DataFrame:
    """(conv_id, turn, loss, entropy, drift, mean_diff): what the rule backbone makes of every user turn, read as a request."""
    from poolcurator.stages.informativeness import propose_weights

    def run(batches):
        for b in batches:
            got = [propose_weights(SelectionRequest("turn", t or ""), {}, RuleBackbone()).to_dict() for t in b["text"]]
            yield b[["conv_id", "turn"]].assign(**{m: [w[m] for w in got] for m in METRICS})

    turns = chats.where("role = 'user'").select("conv_id", "turn", "text")
    return turns.mapInPandas(run, "conv_id long, turn long, " + ", ".join(f"{m} double" for m in METRICS))
