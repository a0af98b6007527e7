"""Queries of the comparators."""

from __future__ import annotations

import json

from pyspark.sql import functions as F

from poolcurator.backbone.rules import RuleBackbone
from poolcurator.baselines import selectors as B
from poolcurator.config import SelectionRequest
from poolcurator.evaluate.runner import REQUESTS
from poolcurator.functions import text as X
from poolcurator.operators.embed import embed
from poolcurator.operators.topk import random_k, top_k
from poolcurator.registry import query
from poolcurator.workloads.common import BUCKETS_SQL, FDOC, LM, NOISE_SQL, key_sql, pool_of, r6, read_spread, read_table, samples, share_sql, spread_samples, tokens_sql, uniform_sql, unique_sql
from poolcurator.workloads.stage_queries import bigram


@query("base_full_pool", f"WITH {FDOC} SELECT sample_id FROM fdoc")
def base_full_pool(spark, d):
    return B.full_pool(samples(spark, d)).select("sample_id")


@query("base_random", f"WITH {FDOC} SELECT sample_id FROM fdoc ORDER BY {key_sql('sample_id')}, sample_id LIMIT 100")
def base_random(spark, d):
    return random_k(samples(spark, d), 100).select("sample_id")


IFD = (
    LM
    + f""", bare AS (SELECT sample_id, y[1] AS w FROM tok WHERE len(y) > 0),
bs AS (SELECT sample_id, -ln((coalesce(n, 0) + 0.1) / (coalesce(total, 0) + 0.1 * v)) AS bare FROM bare LEFT JOIN pairs ON pairs.h = '<s>' AND pairs.w = bare.w LEFT JOIN tot ON tot.h = '<s>', vv),
gv AS (SELECT sample_id, avg(-ln(p)) AS given, count(*) AS n, sum(-ln(p)) FILTER (pos = 0) AS first FROM scored GROUP BY sample_id),
ifd AS (SELECT sample_id, round(given / (given + (bare - first) / n), 6) AS ifd FROM gv JOIN bs USING (sample_id))"""
)


@query("base_ifd", f"WITH {IFD} SELECT sample_id, ifd FROM ifd ORDER BY ifd DESC, sample_id LIMIT 100")
def base_ifd(spark, d):
    model, rest = bigram(spark, d)
    return B.ifd_top_k(rest, model, 100)


@query("base_ifd_capped", f"WITH {IFD} SELECT sample_id, ifd FROM ifd WHERE ifd <= 1 ORDER BY ifd DESC, sample_id LIMIT 100")
def base_ifd_capped(spark, d):
    model, rest = bigram(spark, d)
    return B.ifd_top_k(rest, model, 100, cap=1.0)


@query("base_tag_ifd", f"WITH {IFD} SELECT sample_id, ifd FROM ifd JOIN fdoc USING (sample_id) WHERE lang IN ('de', 'es') ORDER BY ifd DESC, sample_id LIMIT 50")
def base_tag_ifd(spark, d):
    model, rest = bigram(spark, d)
    return B.tag_then_ifd(rest, model, ["de", "es"], 50)


SIM = """vecs AS (SELECT vec_id, embedding::double[] AS e FROM embeddings),
centre AS (SELECT list(m ORDER BY i) AS c FROM (SELECT i, avg(x) AS m FROM (SELECT unnest(range(64)) AS i, unnest(e) AS x FROM vecs WHERE vec_id % 100 = 0) GROUP BY i)),
sim AS (SELECT vec_id AS sample_id, round(list_inner_product(e, c) / sqrt(list_inner_product(e, e) * list_inner_product(c, c)), 6) AS similarity FROM vecs, centre)"""


TEXT_SIM = f"""rb AS ({BUCKETS_SQL.format(id='item_id', c='text', t='benchmark')}), rn AS (SELECT id, sqrt(sum(n * n)::double) AS norm FROM rb GROUP BY id),
rm AS (SELECT bucket, sum(n / norm) AS m FROM rb JOIN rn USING (id) GROUP BY bucket), rl AS (SELECT sqrt(sum(m * m)) AS len FROM rm),
mb AS ({BUCKETS_SQL.format(id='sample_id', c='text', t='fdoc')}),
ts AS (SELECT id, sum(n * coalesce(m, 0) / len) / sqrt(sum(n * n)::double) AS similarity FROM mb LEFT JOIN rm USING (bucket), rl GROUP BY id),
tsim AS (SELECT sample_id, round(coalesce(similarity, 0), 6) AS similarity FROM fdoc LEFT JOIN ts ON id = sample_id)"""


@query("sim_text", f"WITH {FDOC}, {TEXT_SIM} SELECT * FROM tsim")
def sim_text(spark, d):
    """Documents against the mean vector of the benchmark's items, the target examples."""
    s = B.text_similarity(spread_samples(spark, d), read_table(spark, d, "benchmark"))
    return s.select("sample_id", r6("similarity").alias("similarity"))


@query("base_sim_ifd", f"WITH {IFD}, {TEXT_SIM}, near AS (SELECT sample_id FROM tsim ORDER BY similarity DESC, sample_id LIMIT 300) SELECT sample_id, ifd FROM ifd JOIN near USING (sample_id) ORDER BY ifd DESC, sample_id LIMIT 30")
def base_sim_ifd(spark, d):
    model, pool = bigram(spark, d)
    return B.sim_then_ifd(pool, B.text_similarity(pool, read_table(spark, d, "benchmark")), model, 300, 30)


@query("sim_centroid", f"WITH {SIM} SELECT * FROM sim")
def sim_centroid(spark, d):
    v = read_table(spark, d, "embeddings")
    return B.centroid_similarity(v, v.where("vec_id % 100 = 0"), "vec_id").select(F.col("vec_id").alias("sample_id"), r6("similarity").alias("similarity"))


@query("sim_max", "SELECT a.vec_id, round(max(list_inner_product(a.embedding::double[], b.embedding::double[]) / sqrt(list_inner_product(a.embedding::double[], a.embedding::double[]) * list_inner_product(b.embedding::double[], b.embedding::double[]))), 6) AS similarity FROM embeddings a, embeddings b WHERE b.vec_id % 100 = 0 GROUP BY a.vec_id")
def sim_max(spark, d):
    v = read_table(spark, d, "embeddings")
    return B.reference_similarity(v, v.where("vec_id % 100 = 0"), "max", "vec_id").select("vec_id", r6("similarity").alias("similarity"))


RATED = f"""rp AS (SELECT doc_id AS sample_id, p AS prompt_id, m AS model FROM documents, (SELECT unnest(range(1, 6)) AS p), (SELECT unnest(['7B', '13B']) AS m)),
us AS (SELECT *, [{', '.join(uniform_sql("(sample_id::varchar || '|' || prompt_id::varchar || '|' || model)", f'rating{r}') for r in range(1, 6))}] AS u FROM rp),
ps AS (SELECT sample_id, prompt_id, model, list_transform(u, lambda x: x / list_sum(u)) AS p FROM us),
ts AS (SELECT sample_id, prompt_id, model, list_position(p, list_max(p)) * list_sum(list_transform(p, lambda x: abs(list_max(p) - x))) / 4 AS token FROM ps),
ss AS (SELECT sample_id, model, avg(token) / (1 + 0.2 * stddev_pop(token)) AS sentence FROM ts GROUP BY ALL),
ms AS (SELECT sample_id, sum(sentence * CASE model WHEN '7B' THEN 7 ELSE 13 END) / sum(CASE model WHEN '7B' THEN 7 ELSE 13 END) AS score FROM ss GROUP BY ALL)"""


def token_scores(spark, d):
    return B.rating_probabilities(samples(spark, d)).select("sample_id", "prompt_id", "model", B.selectit_token().alias("token"))


@query("selectit_token", f"WITH {RATED} SELECT sample_id, prompt_id::int AS prompt_id, model, round(token, 6) AS value FROM ts")
def selectit_token(spark, d):
    return token_scores(spark, d).select("sample_id", "prompt_id", "model", r6("token").alias("value"))


@query("selectit_sentence", f"WITH {RATED} SELECT sample_id, model, round(sentence, 6) AS value FROM ss")
def selectit_sentence(spark, d):
    return B.selectit_sentence(token_scores(spark, d)).select("sample_id", "model", r6("sentence").alias("value"))


def model_scores(spark, d):
    return B.selectit_model(B.selectit_sentence(token_scores(spark, d)), {"7B": 7.0, "13B": 13.0})


@query("selectit_model", f"WITH {RATED} SELECT sample_id, round(score, 6) AS value FROM ms")
def selectit_model(spark, d):
    return model_scores(spark, d).select("sample_id", r6("score").alias("value"))


@query("base_selectit", f"WITH {RATED} SELECT sample_id, round(score, 6) AS score FROM ms ORDER BY round(score, 6) DESC, sample_id LIMIT 100")
def base_selectit(spark, d):
    return top_k(model_scores(spark, d).select("sample_id", r6("score").alias("score")), "score", 100)


TAGGED = f"""tg AS (SELECT doc_id AS sample_id, lang AS tag, {uniform_sql('doc_id', 'tagq')} AS quality FROM documents UNION ALL SELECT doc_id, source, {uniform_sql('doc_id', 'tagq')} FROM documents),
sup AS (SELECT tag, count(DISTINCT sample_id) AS n FROM tg GROUP BY tag),
pr AS (SELECT a.tag AS a, b.tag AS b, count(DISTINCT sample_id) AS c FROM tg a JOIN tg b USING (sample_id) GROUP BY ALL),
ed AS (SELECT a, b, c / (sa.n + sb.n - c) AS weight FROM pr JOIN sup sa ON sa.tag = a JOIN sup sb ON sb.tag = b WHERE c / (sa.n + sb.n - c) >= 0.05)"""


def language_source_tags(spark, d):
    q = X.seeded_uniform("doc_id", "tagq")
    t = read_table(spark, d, "documents").select(F.col("doc_id").alias("sample_id"), F.explode(F.array("lang", "source")).alias("tag"), q.alias("quality"))
    return t


@query("mig_first_pick", f"WITH {TAGGED}, ma AS (SELECT sample_id, b, sum(quality * weight) AS m FROM tg JOIN ed ON tag = a GROUP BY ALL) SELECT sample_id, round(sum(pow(m, 0.8)), 6) AS gain FROM ma GROUP BY sample_id ORDER BY gain DESC, sample_id LIMIT 20")
def mig_first_pick(spark, d):
    t = language_source_tags(spark, d)
    return top_k(B.mig_first_gains(t, B.tag_edges(t)).select("sample_id", r6("gain").alias("gain")), "gain", 20)


@query("mig_information", f"WITH {TAGGED}, ma AS (SELECT b, sum(quality * weight) AS m FROM tg JOIN ed ON tag = a GROUP BY b) SELECT round(sum(pow(m, 0.8)), 6) AS information FROM ma")
def mig_information(spark, d):
    t = language_source_tags(spark, d)
    e = B.mig_information(t, B.tag_edges(t), t.select("sample_id").distinct())
    return spark.createDataFrame([(round(e, 6),)], "information double")


@query("base_mig")
def base_mig(spark, d):
    t = language_source_tags(spark, d)
    return spark.createDataFrame(B.mig_greedy(t, B.tag_edges(t), 100), "sample_id long, gain double")


@query(
    "tags_tfidf",
    f"""WITH n AS (SELECT count(*)::double AS n FROM documents), tf AS (SELECT doc_id AS sample_id, tag, count(*) AS tf FROM (SELECT doc_id, unnest({tokens_sql('text')}) AS tag FROM documents) GROUP BY ALL),
    df AS (SELECT tag, count(*) AS df FROM tf GROUP BY tag), w AS (SELECT sample_id, tag, round(tf * ln(n / df), 6) AS weight FROM tf JOIN df USING (tag), n)
    SELECT * FROM w QUALIFY row_number() OVER (PARTITION BY sample_id ORDER BY weight DESC, tag) <= 3""",
)
def tags_tfidf(spark, d):
    return B.tfidf_tags(spread_samples(spark, d))


ROLL = f"""ro AS (SELECT doc_id AS sample_id, t, {uniform_sql("(doc_id::varchar || '|' || t::varchar)", 'rollout')} < 1.0 / (1 + n_chars / 2000.0) AS correct FROM documents, (SELECT unnest(range(8)) AS t))"""


def rollouts(spark, d):
    """Seeded solve attempts that long samples fail more often."""
    rows = read_table(spark, d, "documents").select(F.col("doc_id").alias("sample_id"), "n_chars", F.explode(F.sequence(F.lit(0), F.lit(7))).alias("t"))
    u = X.seeded_uniform(F.concat_ws("|", F.col("sample_id").cast("string"), F.col("t").cast("string")), "rollout")
    return rows.select("sample_id", "t", (u < 1.0 / (1 + F.col("n_chars") / 2000.0)).alias("correct"))


@query("solve_rate", f"WITH {ROLL} SELECT sample_id, avg(correct::int) AS rate FROM ro GROUP BY sample_id")
def solve_rate(spark, d):
    return B.solve_rate(rollouts(spark, d))


EFF_SQL = "length(array_to_string(list_filter(string_split(output, chr(10)), lambda x, i: list_position(string_split(output, chr(10)), x) = i), chr(10)))"


@query("trace_effective_len", f"WITH {FDOC} SELECT sample_id, {EFF_SQL}::int AS length FROM fdoc")
def trace_effective_len(spark, d):
    return samples(spark, d).select("sample_id", B.effective_length().alias("length"))


@query(
    "base_joint_rank",
    f"""WITH {FDOC}, {ROLL}, di AS (SELECT sample_id, 1 - avg(correct::int) AS difficulty FROM ro GROUP BY sample_id),
    r AS (SELECT sample_id, rank() OVER (ORDER BY difficulty DESC) AS rd, rank() OVER (ORDER BY {EFF_SQL} DESC) AS rl FROM fdoc JOIN di USING (sample_id))
    SELECT sample_id, round(0.25 * rd + 0.75 * rl, 6) AS score FROM r ORDER BY score, sample_id LIMIT 100""",
)
def base_joint_rank(spark, d):
    """Difficulty is the share of failed rollouts; length that of the trace without repeated steps."""
    difficulty = B.solve_rate(rollouts(spark, d)).select("sample_id", (1 - F.col("rate")).alias("difficulty"))
    rows = samples(spark, d).select("sample_id", B.effective_length().alias("length")).join(difficulty, "sample_id")
    return B.joint_rank(rows, 100)


@query("fit_difficulty")
def fit_difficulty(spark, d):
    known = B.solve_rate(rollouts(spark, d).where("sample_id % 2 = 0")).select("sample_id", (1 - F.col("rate")).alias("difficulty"))
    rows = samples(spark, d).join(known, "sample_id", "left").select("sample_id", "difficulty", F.log1p(F.length("text")).alias("size"), X.unique_share("text").alias("variety"))
    return B.fit_difficulty(rows, ("size", "variety"))(rows).select("sample_id", r6("prediction").alias("difficulty"))


MINK = LM + ", lst AS (SELECT sample_id, list_sort(list(-ln(p)), 'DESC') AS l FROM scored GROUP BY sample_id), mk AS (SELECT sample_id, list_sum(l[1:ceil(len(l) * 0.2)::int]) / ceil(len(l) * 0.2) AS knowledge FROM lst)"


@query("min_k_nll", f"WITH {MINK} SELECT sample_id, round(knowledge, 6) AS value FROM mk")
def min_k_nll(spark, d):
    model, rest = bigram(spark, d)
    return model.min_k(rest).select("sample_id", r6("knowledge").alias("value"))


def deft_terms(spark, d):
    model, rest = bigram(spark, d)
    f = rest.select("sample_id", X.unique_share("text").alias("complexity"), (1 - X.share_of("text", X.noise_class())).alias("quality"))
    return f.join(model.min_k(rest), "sample_id")


DEFT = MINK + f""", te AS (SELECT sample_id, {unique_sql('text')} AS c, 1 - ({share_sql('text', NOISE_SQL)}) AS q, knowledge AS k FROM fdoc JOIN mk USING (sample_id)),
bd AS (SELECT min(c) c0, max(c) c1, min(q) q0, max(q) q1, min(k) k0, max(k) k1 FROM te),
dsc AS (SELECT sample_id, (c - c0) / (c1 - c0) * ((q - q0) / (q1 - q0)) + (q - q0) / (q1 - q0) * ((k - k0) / (k1 - k0)) AS score FROM te, bd)"""


@query("deft_score", f"WITH {DEFT} SELECT sample_id, round(score, 6) AS score FROM dsc")
def deft_score(spark, d):
    return B.deft_score(deft_terms(spark, d)).select("sample_id", r6("score").alias("score"))


def rankers(spark, d):
    """(sample_id, complexity, quality): difficulty spread from half of the rollouts, and quality learnt from the labels."""
    complexity = fit_difficulty(spark, d).select("sample_id", F.col("difficulty").alias("complexity"))
    return complexity.join(fit_ranker(spark, d).select("sample_id", F.col("p").alias("quality")), "sample_id")


@query("base_deft")
def base_deft(spark, d):
    """Both rankers and the bigram model's knowledge in the score; a walk over the documents' own vectors."""
    model, pool = bigram(spark, d)
    ids = B.deft(pool, model, rankers(spark, d), 50)
    return spark.createDataFrame([(i, n) for n, i in enumerate(ids)], "sample_id long, place int")


@query("fit_ranker")
def fit_ranker(spark, d):
    rows = samples(spark, d).join(read_table(spark, d, "labels").select(F.col("doc_id").alias("sample_id"), F.col("quality").cast("double").alias("label")), "sample_id", "left")
    f = rows.select("sample_id", "label", X.unique_share("text").alias("variety"), X.share_of("text", X.noise_class()).alias("noise"), X.share_of("text", "[A-Z]").alias("upper"))
    rank = B.fit_ranker(f.where("label IS NOT NULL"), ("variety", "noise", "upper"))
    return rank(f).select("sample_id", F.round("p", 4).alias("p"))


GRAMS = "list_concat({t}, list_transform(range(1, len({t})), lambda i: {t}[i] || ' ' || {t}[i + 1]))"


def bag_sql(table: str, key: str) -> str:
    t = tokens_sql("text")
    return f"SELECT {key} AS id, ('0x' || substr(md5(g), 1, 8))::bigint % 10000 AS bucket, count(*) AS n FROM (SELECT {key}, unnest({GRAMS.format(t='t')}) AS g FROM (SELECT {key}, {t} AS t FROM {table})) GROUP BY ALL"


DSIR = f"""mine AS ({bag_sql('documents', 'doc_id')}), them AS ({bag_sql('benchmark', 'item_id')}),
cq AS (SELECT bucket, sum(n) AS q FROM mine GROUP BY bucket), cp AS (SELECT bucket, sum(n) AS p FROM them GROUP BY bucket),
cc AS (SELECT bucket, coalesce(p, 0) AS p, coalesce(q, 0) AS q FROM cq FULL JOIN cp USING (bucket)), tt AS (SELECT sum(p) AS tp, sum(q) AS tq FROM cc),
rr AS (SELECT bucket, ln((p + 1) / (tp + 10000)) - ln((q + 1) / (tq + 10000)) AS r FROM cc, tt),
lr AS (SELECT id AS doc_id, sum(n * r) AS value FROM mine JOIN rr USING (bucket) GROUP BY id)"""


@query("dsir_logratio", f"WITH {DSIR} SELECT doc_id, round(value, 6) AS value FROM lr")
def dsir_logratio(spark, d):
    v = B.dsir_logratio(read_spread(spark, d, "documents", "doc_id"), read_table(spark, d, "benchmark"), "doc_id")
    return v.select("doc_id", r6("value").alias("value"))


@query("base_dsir", f"WITH {DSIR} SELECT doc_id, round(value - ln(-ln(greatest(1e-9, least(1 - 1e-9, {uniform_sql('doc_id', 'gumbel')})))), 6) AS score FROM lr ORDER BY score DESC, doc_id LIMIT 100")
def base_dsir(spark, d):
    return B.dsir(read_spread(spark, d, "documents", "doc_id"), read_table(spark, d, "benchmark"), 100, "doc_id")


KNN = """vs AS (SELECT vec_id, embedding::double[] AS e FROM embeddings),
kn AS (SELECT q.vec_id AS query, c.vec_id, round(list_inner_product(q.e, c.e) / sqrt(list_inner_product(q.e, q.e) * list_inner_product(c.e, c.e)), 6) AS similarity FROM vs q, vs c WHERE q.vec_id % 100 = 0
  QUALIFY row_number() OVER (PARTITION BY q.vec_id ORDER BY similarity DESC, c.vec_id) <= 10)"""
MASS = KNN + """, kv AS (SELECT query, vec_id, e FROM kn JOIN vs USING (vec_id)),
de AS (SELECT a.query, a.vec_id, sum(exp(-list_sum(list_transform(range(1, 65), lambda i: (a.e[i] - b.e[i]) * (a.e[i] - b.e[i]))) / (2 * 0.5 * 0.5))) AS density FROM kv a JOIN kv b ON a.query = b.query GROUP BY ALL),
ma AS (SELECT query, vec_id, (1 / density) / sum(1 / density) OVER (PARTITION BY query) AS mass FROM de)"""


def neighbours(spark, d):
    v = read_table(spark, d, "embeddings")
    return B.knn(v.where("vec_id % 100 = 0"), v), v


@query("tsds_knn", f"WITH {KNN} SELECT query, vec_id, similarity FROM kn")
def tsds_knn(spark, d):
    return neighbours(spark, d)[0]


@query("tsds_mass", f"WITH {MASS} SELECT query, vec_id, round(mass, 6) AS mass FROM ma")
def tsds_mass(spark, d):
    return B.kde_mass(*neighbours(spark, d)).select("query", "vec_id", r6("mass").alias("mass"))


@query("tsds_uniform", f"WITH {KNN} SELECT query, vec_id, round(1.0 / count(*) OVER (PARTITION BY query), 6) AS mass FROM kn")
def tsds_uniform(spark, d):
    return B.kde_mass(*neighbours(spark, d), kde=False).select("query", "vec_id", r6("mass").alias("mass"))


ALIGNED = """al AS (SELECT query, vec_id, similarity FROM (SELECT *, round(row_number() OVER w * (1 - similarity) - sum(1 - similarity) OVER (w ROWS UNBOUNDED PRECEDING), 9) AS closer
  FROM kn WINDOW w AS (PARTITION BY query ORDER BY similarity DESC, vec_id)) WHERE closer <= (1 - 0.6) / 0.6 * 1.0)"""


@query("tsds_aligned", f"WITH {KNN}, {ALIGNED} SELECT * FROM al")
def tsds_aligned(spark, d):
    """Neighbourhoods as wide as the trade between alignment and diversity allows."""
    return B.aligned(neighbours(spark, d)[0], 0.6).select("query", "vec_id", "similarity")


@query(
    "base_tsds",
    f"""WITH {KNN}, {ALIGNED}, {MASS[len(KNN) + 2:].replace("FROM kn JOIN", "FROM al JOIN")}, tm AS (SELECT vec_id, sum(mass) AS m FROM ma GROUP BY vec_id),
    ce AS (SELECT vec_id, sum(m) OVER (ORDER BY vec_id) - m AS lo, sum(m) OVER (ORDER BY vec_id) AS hi, sum(m) OVER () AS whole FROM tm),
    dr AS (SELECT i AS draw, ('0x' || substr(md5('draw42:' || i::varchar), 1, 13))::bigint / 4503599627370496.0::double AS u FROM (SELECT unnest(range(100)) AS i)) SELECT draw, vec_id FROM dr JOIN ce ON u * whole >= lo AND u * whole < hi""",
)
def base_tsds(spark, d):
    near, v = neighbours(spark, d)
    return B.categorical_draw(B.kde_mass(B.aligned(near, 0.6), v), 100)


SP = json.loads(RuleBackbone().complete("plan", "", {"request": REQUESTS["R-en"]}))


@query(
    "base_single_pass",
    f"""WITH {FDOC}, f AS (SELECT sample_id, round({share_sql('text', NOISE_SQL)}, 6) AS noise, round({unique_sql('text')}, 6) AS variety, length(output) AS n FROM fdoc WHERE lang = 'en')
    SELECT sample_id, round({SP['variety']} * variety + {SP['clean']} * (1 - noise) + {SP['length']} * least(n / 2000, 1.0), 6) AS score
    FROM f WHERE noise <= {SP['max_noise']} AND n >= {SP['min_output']} ORDER BY score DESC, sample_id LIMIT 100""",
)
def base_single_pass(spark, d):
    """One call for the request on the English pool, one scan."""
    return B.single_pass(pool_of(spark, d, "SD-1"), 100, SelectionRequest("R-en", REQUESTS["R-en"]), RuleBackbone())


@query("embed_arrow", "SELECT doc_id AS sample_id, CASE WHEN length(text) >= 2 THEN 1.0 ELSE 0.0 END AS norm FROM documents")
def embed_arrow(spark, d):
    """Vectors by the Arrow encoder: one row per document with its norm."""
    return embed(samples(spark, d).select("sample_id", "text")).select("sample_id", F.round(X.norm("embedding"), 4).alias("norm"))


