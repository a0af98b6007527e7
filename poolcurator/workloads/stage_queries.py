"""Queries of the four stages and of inspection."""

from __future__ import annotations

from pyspark.sql import functions as F

from poolcurator import inspect as I
from poolcurator.config import METRICS, Policy, Weights
from poolcurator.functions import text as X
from poolcurator.operators import cluster
from poolcurator.operators.embed import bigram_buckets
from poolcurator.operators.topk import per_group, top_k
from poolcurator.registry import query
from poolcurator.stages import characteristic as C
from poolcurator.stages import informativeness as N
from poolcurator.stages import quality as Q
from poolcurator.target import probe
from poolcurator.target.ngram import BigramTarget
from poolcurator.workloads.cascade_sql import ADAMW_SQL, GENERATED
from poolcurator.workloads.common import BUCKETS_SQL, FDOC, LM, NOISE_SQL, SEED, VEC_SQL, key_sql, r6, read_spread, read_table, samples, share_sql, spread_samples, tokens_sql, uniform_sql, unique_sql

# ---- stage 2 -------------------------------------------------------------------------------------

POLICY = Policy()
ALL_OF = [
    "length(text) BETWEEN 40 AND 4096",
    "length(instruction) >= 5",
    "length(output) >= 15",
    "length(output) >= 0.2 * length(instruction)",
    "NOT (" + " OR ".join("contains(output, '" + p.replace("'", "''") + "')" for p in POLICY.refusal_phrases) + ")",
    f"{share_sql('text', NOISE_SQL)} <= 0.15",
    f"{share_sql('text', '[A-Za-z]')} >= 0.30",
]


def rule_query(name: str, tests: list[str], wanted: tuple[str, ...], policy: Policy = POLICY):
    def run(spark, d):
        test = F.lit(True)
        for n, rule in C.rules(policy):
            if n in wanted:
                test = test & rule
        return samples(spark, d).where(test).select("sample_id")

    query(name, f"WITH {FDOC} SELECT sample_id FROM fdoc WHERE {' AND '.join(tests)}")(run)


rule_query("rule_required", ["instruction IS NOT NULL AND output IS NOT NULL AND text IS NOT NULL"], ("required",))
rule_query("rule_total_len", ALL_OF[:1], ("total_len",))
rule_query("rule_field_len", ALL_OF[1:3], ("inst_len", "out_len"))
rule_query("rule_ratio", ALL_OF[3:4], ("ratio",))
rule_query("rule_noise", ALL_OF[5:6], ("noise",))
rule_query("rule_noise_math", [f"{share_sql('text', NOISE_SQL[:-1] + X.FIELD_SIGNS['math'] + ']')} <= 0.02"], ("noise",), Policy(noise_regex=X.noise_class("math"), max_noise_ratio=0.02))
rule_query("rule_noise_code", [f"{share_sql('text', NOISE_SQL[:-1] + X.FIELD_SIGNS['code'].replace(chr(39), chr(39) * 2) + ']')} <= 0.02"], ("noise",), Policy(noise_regex=X.noise_class("code"), max_noise_ratio=0.02))
rule_query("rule_english", ALL_OF[6:], ("english",))
rule_query("rule_refusal", ["NOT (contains(output, 'idiot') OR contains(output, 'AKIA'))"], ("refusal",), Policy(refusal_phrases=("idiot", "AKIA")))


@query("policy_filter", f"WITH {FDOC} SELECT sample_id FROM fdoc WHERE {' AND '.join(ALL_OF)}")
def policy_filter(spark, d):
    """All rules of the default policy; the stored length reaches the scan."""
    return C.match(samples(spark, d), POLICY, stored_length=True).select("sample_id")


@query(
    "policy_reject_counts",
    f"""WITH {FDOC} SELECT CASE {' '.join(f"WHEN NOT ({t}) THEN '{n}'" for n, t in zip(("total_len", "inst_len", "out_len", "ratio", "refusal", "noise", "english"), ALL_OF, strict=True))} ELSE 'kept' END AS reason, count(*) AS n
    FROM fdoc GROUP BY ALL""",
)
def policy_reject_counts(spark, d):
    return C.reject_reasons(samples(spark, d), POLICY).groupBy("reason").agg(F.count(F.lit(1)).alias("n"))


# ---- stage 3 -------------------------------------------------------------------------------------


def bigram(spark, d) -> tuple[BigramTarget, object]:
    """The bigram model of all documents, and all documents."""
    pool = spread_samples(spark, d)
    return BigramTarget.fit(pool), pool


@query("metric_nll", f"WITH {LM} SELECT sample_id, round(avg(-ln(p)), 6) AS value FROM scored GROUP BY sample_id")
def metric_nll(spark, d):
    model, rest = bigram(spark, d)
    return model.metrics(rest).select("sample_id", r6("loss").alias("value"))


@query("metric_entropy", f"WITH {LM} SELECT sample_id, round(avg(ent), 6) AS value FROM scored GROUP BY sample_id")
def metric_entropy(spark, d):
    model, rest = bigram(spark, d)
    return model.metrics(rest).select("sample_id", r6("entropy").alias("value"))


@query("embed_hash", f"SELECT id AS doc_id, bucket, n FROM ({BUCKETS_SQL.format(id='doc_id', c='text', t='documents')})")
def embed_hash(spark, d):
    return bigram_buckets(read_spread(spark, d, "documents", "doc_id"), "doc_id").select("doc_id", "bucket", F.col("n").cast("long").alias("n"))


DRIFT_SQL = """u AS (SELECT id, bucket, sum(a) AS a, sum(b) AS b FROM (SELECT id, bucket, n AS a, 0 AS b FROM a UNION ALL SELECT id, bucket, 0, n FROM b) GROUP BY ALL),
    s AS (SELECT id, sum(a * b)::double AS ab, sum(a * a)::double AS aa, sum(b * b)::double AS bb FROM u GROUP BY id)
    SELECT sample_id, round(1 - coalesce(CASE WHEN aa > 0 AND bb > 0 THEN ab / sqrt(aa * bb) ELSE 0 END, 0), 6) AS drift FROM fdoc LEFT JOIN s ON sample_id = id"""


@query(
    "metric_drift",
    f"""WITH RECURSIVE {FDOC}, {LM[len(FDOC) + 2:LM.index("\nrows AS (")]} matched AS (SELECT * FROM fdoc), {GENERATED["bigram"].format(x=tokens_sql("instruction"))},
    a AS ({BUCKETS_SQL.format(id='sample_id', c='generated', t='spoken')}), b AS ({BUCKETS_SQL.format(id='sample_id', c='output', t='spoken')}), {DRIFT_SQL}""",
)
def metric_drift(spark, d):
    """What the bigram model says to every prompt against the sample's answer."""
    model, pool = bigram(spark, d)
    return N.drift(pool.join(model.generate(pool), "sample_id")).select("sample_id", r6("drift").alias("drift"))


@query("text_drift", f"WITH {FDOC}, a AS ({BUCKETS_SQL.format(id='sample_id', c='instruction', t='fdoc')}), b AS ({BUCKETS_SQL.format(id='sample_id', c='output', t='fdoc')}), {DRIFT_SQL}")
def text_drift(spark, d):
    """The drift formula between prompt and answer, which needs no model."""
    return N.drift(spread_samples(spark, d), "instruction", "output").select("sample_id", r6("drift").alias("drift"))


@query(
    "metric_meandiff_sgd",
    f"""WITH {FDOC}, v AS (SELECT sample_id, {VEC_SQL.format(t=tokens_sql('instruction'))} AS x, {VEC_SQL.format(t=tokens_sql('output'))} AS y FROM fdoc)
    SELECT sample_id, round(1e6 * 1e-5 * list_sum(list_transform(range(1, 17), lambda i: abs(0.5 * x[i] - y[i]))) / 16 * list_sum(list_transform(x, lambda e: abs(e))) / 16, 6) AS value FROM v""",
)
def metric_meandiff_sgd(spark, d):
    return probe.mean_diff(spread_samples(spark, d), "sgd").select("sample_id", r6(1e6 * F.col("mean_diff")).alias("value"))


@query(
    "metric_shift_table",
    f"""WITH {LM}, c AS (SELECT sample_id, h, w, count(*) AS c, any_value(p) AS p FROM scored GROUP BY ALL), g AS (SELECT *, sum(c) OVER (PARTITION BY sample_id, h) AS ch FROM c),
    t AS (SELECT sample_id, h, sum(abs(ch * p - c) - ch * p) AS moved, any_value(ch) AS ch FROM g GROUP BY ALL)
    SELECT sample_id, round(1e12 * 1e-5 * sum(moved + ch) / sum(ch) / ((SELECT count(*) FROM tot) * (SELECT v FROM vv)), 4) AS value FROM t GROUP BY sample_id""",
)
def metric_shift_table(spark, d):
    """Shift of the bigram model's own logits after one plain gradient step."""
    model, pool = bigram(spark, d)
    return model.table_shift(pool).select("sample_id", F.round(1e12 * F.col("mean_diff"), 4).alias("value"))


@query(
    "metric_meandiff_adamw",
    f"""WITH {FDOC}, v AS (SELECT sample_id, {VEC_SQL.format(t=tokens_sql('instruction'))} AS x, {VEC_SQL.format(t=tokens_sql('output'))} AS y FROM fdoc)
    SELECT sample_id, round(1e6 * {ADAMW_SQL}, 4) AS value FROM v""",
)
def metric_meandiff_adamw(spark, d):
    return probe.mean_diff(spread_samples(spark, d), "adamw").select("sample_id", F.round(1e6 * F.col("mean_diff"), 4).alias("value"))


GIVEN = "given AS (SELECT doc_id AS sample_id, " + ", ".join(f"{uniform_sql('doc_id', m)} AS {m}" for m in METRICS) + " FROM documents)"
SCALED = GIVEN + ", b AS (SELECT " + ", ".join(f"min({m}) AS lo_{m}, max({m}) AS hi_{m}" for m in METRICS) + " FROM given), o AS (SELECT sample_id, " + ", ".join(
    (f"1 - ({m} - lo_{m}) / (hi_{m} - lo_{m})" if m == "mean_diff" else f"({m} - lo_{m}) / (hi_{m} - lo_{m})") + f" AS {m}" for m in METRICS
) + " FROM given, b)"
WEIGHTS = Weights(0.20, 0.15, 0.25, 0.40)
SCORED = SCALED + ", s AS (SELECT sample_id, round(" + " + ".join(f"{w} * {m}" for m, w in WEIGHTS.to_dict().items()) + ", 6) AS score FROM o)"


def oriented(spark, d):
    return N.orient(N.minmax(N.given_metrics(samples(spark, d))))


@query("minmax_norm", f"WITH {SCALED} SELECT sample_id, " + ", ".join(f"round({m}, 6) AS {m}" for m in METRICS) + " FROM o")
def minmax_norm(spark, d):
    return oriented(spark, d).select("sample_id", *[r6(m).alias(m) for m in METRICS])


@query("info_score", f"WITH {SCORED} SELECT * FROM s")
def info_score(spark, d):
    return N.composite(oriented(spark, d), WEIGHTS).select("sample_id", r6("score").alias("score"))


@query("info_topk", f"WITH {SCORED} SELECT * FROM s ORDER BY score DESC, sample_id LIMIT 300")
def info_topk(spark, d):
    return N.informative(N.given_metrics(samples(spark, d)), WEIGHTS, 300).select("sample_id", "score")


def single_metric(m: str):
    @query(f"topk_{m.replace('_', '')}", f"WITH {SCALED} SELECT sample_id, round({m}, 6) AS score FROM o ORDER BY score DESC, sample_id LIMIT 100")
    def run(spark, d):
        return top_k(oriented(spark, d).select("sample_id", r6(m).alias("score")), "score", 100)


for _m in METRICS:
    single_metric(_m)


# ---- stage 1 -------------------------------------------------------------------------------------


@query("domain_passthrough", f"WITH {FDOC} SELECT sample_id FROM fdoc")
def domain_passthrough(spark, d):
    from poolcurator.backbone.rules import RuleBackbone
    from poolcurator.config import SelectionRequest
    from poolcurator.stages.domain import select_domain

    return select_domain(samples(spark, d), SelectionRequest("R-en", "This pool is all English."), RuleBackbone()).select("sample_id")


CENT = f"""cent AS (SELECT row_number() OVER (ORDER BY {key_sql('vec_id')}, vec_id) - 1 AS cluster_id, embedding::double[] AS c FROM embeddings QUALIFY cluster_id < 20),
ds AS (SELECT vec_id, cluster_id, list_sum(list_transform(range(1, 65), lambda i: (e[i] - c[i]) * (e[i] - c[i]))) AS dist FROM (SELECT vec_id, embedding::double[] AS e FROM embeddings), cent),
assigned AS (SELECT vec_id, cluster_id::int AS cluster_id, dist FROM ds QUALIFY row_number() OVER (PARTITION BY vec_id ORDER BY round(dist, 9), cluster_id) = 1)"""


def centroids(spark, d):
    """The 20 vectors with the least seeded keys."""
    rows = read_table(spark, d, "embeddings").orderBy(X.seeded_key("vec_id", SEED), "vec_id").limit(20).select("embedding").collect()
    return [(i, r[0]) for i, r in enumerate(rows)]


def kmeans_given(spark, d):
    return cluster.assign_nearest(read_table(spark, d, "embeddings"), centroids(spark, d), "vec_id")


@query("kmeans_assign", f"WITH {CENT} SELECT vec_id, cluster_id, round(dist, 6) AS dist FROM assigned")
def kmeans_assign(spark, d):
    return kmeans_given(spark, d).select("vec_id", "cluster_id", r6("dist").alias("dist"))


@query("kmeans_lloyd_step", f"WITH {CENT} SELECT cluster_id, dim::int AS dim, round(avg(x), 6) AS value FROM (SELECT cluster_id, unnest(range(64)) AS dim, unnest(embedding::double[]) AS x FROM embeddings JOIN assigned USING (vec_id)) GROUP BY ALL")
def kmeans_lloyd_step(spark, d):
    return cluster.lloyd_step(kmeans_given(spark, d), read_table(spark, d, "embeddings"), "vec_id").select("cluster_id", "dim", r6("value").alias("value"))


@query("cluster_sample", f"WITH {CENT} SELECT cluster_id, vec_id FROM assigned QUALIFY row_number() OVER (PARTITION BY cluster_id ORDER BY {key_sql('vec_id')}, vec_id) <= 8")
def cluster_sample(spark, d):
    return per_group(kmeans_given(spark, d), "cluster_id", 8, SEED, "vec_id").select("cluster_id", "vec_id")


LANG_CLUSTER = f"""lc AS (SELECT doc_id AS sample_id, lang, ('0x' || substr(md5(source), 1, 4))::int % 6 AS c0 FROM documents),
cl AS (SELECT sample_id, lang, CASE WHEN c0 < 3 THEN c0 ELSE 10 + ascii(lang) % 7 END::int AS cluster_id FROM lc),
draw AS (SELECT * FROM cl QUALIFY row_number() OVER (PARTITION BY cluster_id ORDER BY {key_sql('sample_id')}, sample_id) <= 8),
per AS (SELECT cluster_id, lang, count(*) AS n, sum(count(*)) OVER (PARTITION BY cluster_id) AS total FROM draw GROUP BY cluster_id, lang),
labels_of AS (SELECT cluster_id, CASE WHEN max(n) >= 0.6 * any_value(total) THEN max_by(lang, n) ELSE 'mixed' END AS label FROM per GROUP BY cluster_id)"""


def language_clusters(spark, d):
    """Clusters that are partly mixed and partly of one language, to label by a draw."""
    c0 = F.pmod(F.conv(F.substring(F.md5("source"), 1, 4), 16, 10).cast("int"), F.lit(6))
    return read_table(spark, d, "documents").select(F.col("doc_id").alias("sample_id"), "lang", F.when(c0 < 3, c0).otherwise(10 + F.ascii("lang") % 7).cast("int").alias("cluster_id"))


def language_labels(spark, d):
    draw = per_group(language_clusters(spark, d), "cluster_id", 8)
    per = draw.groupBy("cluster_id", "lang").agg(F.count(F.lit(1)).alias("n"))
    agg = per.groupBy("cluster_id").agg(F.max("n").alias("best"), F.sum("n").alias("total"), F.max_by("lang", "n").alias("lang"))
    return agg.select("cluster_id", F.when(F.col("best") >= 0.6 * F.col("total"), F.col("lang")).otherwise("mixed").alias("label"))


@query("cluster_label_langs", f"WITH {LANG_CLUSTER} SELECT cluster_id, label FROM labels_of")
def cluster_label_langs(spark, d):
    return language_labels(spark, d)


@query("domain_select", f"WITH {LANG_CLUSTER} SELECT sample_id FROM cl WHERE cluster_id IN (SELECT cluster_id FROM labels_of WHERE label = 'en')")
def domain_select(spark, d):
    from poolcurator.stages.domain import keep_clusters

    wanted = [r[0] for r in language_labels(spark, d).where("label = 'en'").collect()]  # cluster ids
    rows = language_clusters(spark, d)
    return keep_clusters(rows, rows, wanted).select("sample_id")


@query("cluster_match_any", f"WITH {LANG_CLUSTER} SELECT cluster_id FROM labels_of WHERE list_has_any([label, upper(label)], ['en', 'DE'])")
def cluster_match_any(spark, d):
    names = F.array("label", F.upper("label"))
    return language_labels(spark, d).where(F.arrays_overlap(names, F.array(F.lit("en"), F.lit("DE")))).select("cluster_id")


# ---- stage 4 -------------------------------------------------------------------------------------

BATCHED = f"{FDOC}, bt AS (SELECT *, ((row_number() OVER (ORDER BY {key_sql('sample_id')}, sample_id) - 1) // 10)::bigint AS batch_id FROM fdoc)"
RULED = f"""{BATCHED}, ft AS (SELECT batch_id, sample_id, round({unique_sql('text')}, 6) AS variety, round(1 - ({share_sql('text', NOISE_SQL)}), 6) AS clean, length(text) AS len FROM bt),
rs AS (SELECT batch_id, sample_id, ntile(5) OVER (PARTITION BY batch_id ORDER BY variety, sample_id)::int AS d1, ntile(5) OVER (PARTITION BY batch_id ORDER BY clean, sample_id)::int AS d2, ntile(5) OVER (PARTITION BY batch_id ORDER BY len, sample_id)::int AS d3 FROM ft),
qs AS (SELECT sample_id, round(0.5 * d1 + 0.3 * d2 + 0.2 * d3, 6) AS q FROM rs)"""
RUBRIC = {"d1": 0.5, "d2": 0.3, "d3": 0.2}


@query("judge_batches", f"WITH {BATCHED} SELECT sample_id, batch_id FROM bt")
def judge_batches(spark, d):
    return Q.assign_batches(spread_samples(spark, d), 10).select("sample_id", "batch_id")


@query("judge_rule", f"WITH {RULED} SELECT sample_id, d1, d2, d3 FROM rs")
def judge_rule(spark, d):
    return Q.rule_scores(Q.assign_batches(spread_samples(spark, d), 10)).select("sample_id", "d1", "d2", "d3")


def judged(spark, d):
    v = Q.rule_verdicts(Q.assign_batches(spread_samples(spark, d), 10), list(RUBRIC))
    return Q.quality_score(v, RUBRIC).withColumn("q", r6("q"))


@query("quality_score", f"WITH {RULED} SELECT sample_id, q FROM qs")
def quality_score(spark, d):
    return judged(spark, d)


@query("quality_topk", f"WITH {RULED}, {SCORED} SELECT sample_id, q FROM qs JOIN s USING (sample_id) ORDER BY q DESC, score DESC, sample_id LIMIT 100")
def quality_topk(spark, d):
    s = info_score(spark, d)
    return Q.best_by_quality(judged(spark, d).join(s, "sample_id"), 100).select("sample_id", "q")


@query("judge_flagged", "SELECT doc_id AS sample_id, quality * 5 AS q FROM labels WHERE toxic = 0")
def judge_flagged(spark, d):
    v = read_table(spark, d, "labels").select(F.col("doc_id").alias("sample_id"), (F.col("quality") * 5).alias("q"), (F.col("toxic") == 1).alias("flagged"))
    return Q.apply_flags(v, drop_flagged=True).select("sample_id", "q")


VERDICT_SQL = """raw AS (SELECT doc_id // 10 AS batch_id, doc_id AS sample_id, CASE WHEN (doc_id // 10) % 7 = 6 THEN 'broken' ELSE 'ok' END AS state,
  [['clean', (quality * 4 + 1)::varchar], ['safe', (5 - toxic * 5)::varchar]] AS dims FROM labels)"""


@query(
    "verdict_parse",
    f"WITH {VERDICT_SQL} SELECT batch_id, sample_id, dm[1] AS dim, dm[2]::int AS q FROM (SELECT batch_id, sample_id, unnest(dims) AS dm FROM raw WHERE state = 'ok') WHERE dm[2]::int BETWEEN 1 AND 5",
)
def verdict_parse(spark, d):
    """Replies made from labels, every seventh batch broken, scores of 0 out of range."""
    rows = read_table(spark, d, "labels").withColumn("batch_id", F.floor(F.col("doc_id") / 10))
    one = F.struct(F.col("doc_id").alias("sample_id"), F.create_map(F.lit("clean"), F.col("quality") * 4 + 1, F.lit("safe"), 5 - F.col("toxic") * 5).alias("scores"), F.lit("").alias("reasoning"), (F.col("toxic") == 1).alias("flagged"))
    raw = rows.groupBy("batch_id").agg(F.collect_list("doc_id").alias("members"), F.to_json(F.collect_list(one)).alias("json"))
    raw = raw.withColumn("raw", F.when(F.col("batch_id") % 7 == 6, F.substring("json", 1, 20)).otherwise(F.col("json")))
    return Q.parse_verdicts(raw).select("batch_id", "sample_id", "dim", "q")


# ---- inspection ----------------------------------------------------------------------------------


@query(
    "inspect_stats",
    f"""WITH {FDOC} SELECT count(*) AS n, count(*) FILTER (length(output) = 0) AS empty_output, round(avg(length(instruction)), 6) AS mean_x, round(avg(length(output)), 6) AS mean_y,
    min(length(text))::int AS min_t, max(length(text))::int AS max_t, round(avg({share_sql('text', NOISE_SQL)}), 6) AS noise, round(avg({share_sql('text', '[A-Za-z]')}), 6) AS latin FROM fdoc""",
)
def inspect_stats(spark, d):
    return I.stats(samples(spark, d))


@query("inspect_nulls", f"WITH {FDOC} SELECT " + ", ".join(f"count(*) FILTER ({c} IS NULL OR {c} = '') AS {c}" for c in ("instruction", "input", "output", "text", "lang", "source")) + " FROM fdoc")
def inspect_nulls(spark, d):
    return I.nulls(samples(spark, d))


@query("inspect_lengths", f"WITH {FDOC} SELECT " + ", ".join(f"round(quantile_cont(length(text)::double, {p}), 6) AS t_{int(p * 100)}, round(quantile_cont(length(output) / nullif(length(instruction), 0), {p}), 6) AS r_{int(p * 100)}" for p in (0.1, 0.5, 0.9)) + ", round(stddev_samp(length(text)::double), 6) AS t_sd FROM fdoc")
def inspect_lengths(spark, d):
    return I.lengths(samples(spark, d), exact=True)


@query("inspect_charset", f"WITH {FDOC} SELECT " + ", ".join(f"round(avg({share_sql('text', c)}), 6) AS {n}" for n, c in (("noise", NOISE_SQL), ("latin", "[A-Za-z]"), ("digit", "[0-9]"), ("upper", "[A-Z]"))) + " FROM fdoc")
def inspect_charset(spark, d):
    return I.charset(samples(spark, d))


@query("inspect_langs", "SELECT lang, count(*) AS n FROM documents GROUP BY lang")
def inspect_langs(spark, d):
    return I.value_counts(samples(spark, d), "lang")


@query("inspect_sources", "SELECT source, count(*) AS n FROM documents GROUP BY source")
def inspect_sources(spark, d):
    return I.value_counts(samples(spark, d), "source")


@query("inspect_dups", "SELECT md5(text) AS digest, count(*) AS n FROM documents GROUP BY text HAVING count(*) > 1")
def inspect_dups(spark, d):
    return I.duplicates(samples(spark, d))


@query("inspect_vocab", f"SELECT token, count(*) AS n FROM (SELECT unnest({tokens_sql('text')}) AS token FROM documents) GROUP BY token ORDER BY n DESC, token LIMIT 20")
def inspect_vocab(spark, d):
    return I.vocabulary(samples(spark, d))


@query("inspect_distinct")
def inspect_distinct(spark, d):
    return samples(spark, d).agg(*[F.approx_count_distinct(c).alias(c) for c in ("text", "lang", "source")])


@query("inspect_corr", f"WITH {GIVEN} SELECT round(corr(loss, entropy), 6) AS loss_entropy, round(corr(loss, drift), 6) AS loss_drift, round(corr(drift, mean_diff), 6) AS drift_mean_diff FROM given")
def inspect_corr(spark, d):
    g = N.given_metrics(samples(spark, d))
    return g.agg(r6(F.corr("loss", "entropy")).alias("loss_entropy"), r6(F.corr("loss", "drift")).alias("loss_drift"), r6(F.corr("drift", "mean_diff")).alias("drift_mean_diff"))


@query("inspect_hist", "SELECT CASE WHEN n_chars < 0 THEN 0 WHEN n_chars >= 8000 THEN 17 ELSE (n_chars // 500) + 1 END AS bucket, count(*) AS n FROM documents GROUP BY ALL")
def inspect_hist(spark, d):
    return I.histogram(samples(spark, d), F.col("n_chars"), 0.0, 8000.0, 16)


@query("inspect_preview", f"WITH {FDOC} SELECT sample_id, substr(instruction, 1, 200) AS instruction, substr(output, 1, 200) AS output FROM fdoc ORDER BY {key_sql('sample_id')}, sample_id LIMIT 5")
def inspect_preview(spark, d):
    return I.preview(samples(spark, d))


