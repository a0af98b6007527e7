"""Queries of the accuracy and cost measures."""

from __future__ import annotations

from pyspark.sql import functions as F

from poolcurator.config import METRICS, PUBLISHED_WEIGHTS
from poolcurator.evaluate import scores as S
from poolcurator.evaluate import standin
from poolcurator.functions import text as X
from poolcurator.operators.topk import random_k
from poolcurator.registry import query
from poolcurator.stages import informativeness as N
from poolcurator.workloads.common import LM, key_sql, r6, read_table, samples, tokens_sql, uniform_sql
from poolcurator.workloads.stage_queries import bigram

ANSWERS = """ans AS (SELECT item_id, CASE item_id % 6 WHEN 0 THEN item_id::varchar WHEN 1 THEN '  ' || item_id::varchar || '. ' WHEN 2 THEN (2 * item_id)::varchar || '/2' WHEN 3 THEN item_id::varchar || '.0' WHEN 4 THEN 'X' || item_id::varchar ELSE (item_id + 1)::varchar END AS predicted,
  CASE item_id % 6 WHEN 4 THEN 'x' || item_id::varchar ELSE item_id::varchar END AS gold FROM benchmark),
nrm AS (SELECT item_id, regexp_replace(regexp_replace(lower(trim(predicted)), '\\$', '', 'g'), '\\.$', '') AS p, lower(gold) AS g FROM ans),
val AS (SELECT *, CASE WHEN contains(p, '/') THEN try_cast(split_part(p, '/', 1) AS double) / try_cast(split_part(p, '/', 2) AS double) ELSE try_cast(p AS double) END AS pv, try_cast(g AS double) AS gv FROM nrm)"""


def answers(spark, d):
    """Answers in exact, spaced, fraction, decimal, cased and wrong variants."""
    i = F.col("item_id")
    s = i.cast("string")
    kind = F.pmod(i, F.lit(6))
    p = (
        F.when(kind == 0, s)
        .when(kind == 1, F.concat(F.lit("  "), s, F.lit(". ")))
        .when(kind == 2, F.concat((2 * i).cast("string"), F.lit("/2")))
        .when(kind == 3, F.concat(s, F.lit(".0")))
        .when(kind == 4, F.concat(F.lit("X"), s))
        .otherwise((i + 1).cast("string"))
    )
    return read_table(spark, d, "benchmark").select("item_id", p.alias("predicted"), F.when(kind == 4, F.concat(F.lit("x"), s)).otherwise(s).alias("gold"))


@query("acc_exact", f"WITH {ANSWERS} SELECT round(100 * avg(CASE WHEN p = g OR abs(pv - gv) < 1e-9 THEN 1.0 ELSE 0.0 END), 2) AS accuracy FROM val")
def acc_exact(spark, d):
    return S.answer_accuracy(answers(spark, d))


@query("acc_choice", "SELECT round(100 * avg(CASE WHEN item_id % 4 = item_id % 3 THEN 1.0 ELSE 0.0 END), 2) AS accuracy FROM benchmark")
def acc_choice(spark, d):
    letter = lambda n: F.substring(F.lit("ABCDE"), F.pmod("item_id", F.lit(n)).cast("int") + 1, F.lit(1))
    rows = read_table(spark, d, "benchmark").select("item_id", F.when(F.col("item_id") % 2 == 0, F.concat(F.lit("so the answer is ("), F.lower(letter(4)), F.lit(")"))).otherwise(F.concat(letter(4), F.lit(") because"))).alias("predicted"), letter(3).alias("gold"))
    return S.choice_accuracy(rows)


PASSES = f"res AS (SELECT item_id, t, {uniform_sql('(item_id * 10 + t)', 'test')} < 0.9 AS passed FROM benchmark, (SELECT unnest(range(3)) AS t))"


@query("acc_pass1", f"WITH {PASSES} SELECT round(100 * avg(ok::int), 2) AS pass_at_1 FROM (SELECT item_id, bool_and(passed) AS ok FROM res GROUP BY item_id)")
def acc_pass1(spark, d):
    rows = read_table(spark, d, "benchmark").select("item_id", F.explode(F.sequence(F.lit(0), F.lit(2))).alias("t"))
    return S.pass_at_1(rows.select("item_id", (X.seeded_uniform(F.col("item_id") * 10 + F.col("t"), "test") < 0.9).alias("passed")))


GRID = f"""grid AS (SELECT lang AS setting, source AS method, lr, e AS epoch, 'b' || (doc_id % 3)::varchar AS benchmark, round(100 * {uniform_sql("(doc_id::varchar || '|' || lr::varchar || '|' || e::varchar)", 'lr')}, 2) AS score
  FROM documents, (SELECT unnest([1, 5, 10]) AS lr), (SELECT unnest([1, 2, 3]) AS e) QUALIFY row_number() OVER (PARTITION BY lang, source, lr, e, benchmark ORDER BY doc_id) = 1),
fin AS (SELECT setting, method, lr, benchmark, max_by(score, epoch) AS score FROM grid GROUP BY ALL)"""


def grid(spark, d):
    """A seeded cube of scores by setting, method, learning rate (in millionths), epoch and benchmark."""
    from pyspark.sql import Window

    docs = read_table(spark, d, "documents")
    rows = docs.select("doc_id", F.col("lang").alias("setting"), F.col("source").alias("method"), F.concat(F.lit("b"), (F.col("doc_id") % 3).cast("string")).alias("benchmark"), F.explode(F.array(F.lit(1), F.lit(5), F.lit(10))).alias("lr"))
    rows = rows.withColumn("epoch", F.explode(F.array(F.lit(1), F.lit(2), F.lit(3))))
    u = X.seeded_uniform(F.concat_ws("|", *[F.col(c).cast("string") for c in ("doc_id", "lr", "epoch")]), "lr")
    rn = F.row_number().over(Window.partitionBy("setting", "method", "lr", "epoch", "benchmark").orderBy("doc_id"))
    return rows.withColumn("score", F.round(100 * u, 2)).withColumn("rn", rn).where("rn = 1").drop("rn", "doc_id")


@query("measure_final_epoch", f"WITH {GRID} SELECT * FROM fin")
def measure_final_epoch(spark, d):
    return S.final_epoch(grid(spark, d))


@query(
    "measure_shared_lr",
    f"""WITH {GRID}, me AS (SELECT setting, lr, round(avg(score), 9) AS m FROM fin GROUP BY ALL), be AS (SELECT setting, lr FROM me QUALIFY row_number() OVER (PARTITION BY setting ORDER BY m DESC, lr) = 1)
    SELECT setting, lr, method, benchmark, score FROM fin JOIN be USING (setting, lr)""",
)
def measure_shared_lr(spark, d):
    return S.pick_shared_lr(S.final_epoch(grid(spark, d)))


@query("measure_setting_mean", f"WITH {GRID} SELECT setting AS model, lr::varchar AS pool, method, round(round(avg(score), 9), 2) AS score FROM fin GROUP BY ALL")
def measure_setting_mean(spark, d):
    g = S.final_epoch(grid(spark, d)).select(F.col("setting").alias("model"), F.col("lr").cast("string").alias("pool"), "benchmark", "method", "score")
    return S.setting_mean(g)


@query("measure_rank", f"WITH {GRID} SELECT setting AS model, lr::varchar AS pool, benchmark, method, score, dense_rank() OVER (PARTITION BY setting, lr, benchmark ORDER BY score DESC)::int AS place FROM fin WHERE method <> 'src0'")
def measure_rank(spark, d):
    g = S.final_epoch(grid(spark, d)).select(F.col("setting").alias("model"), F.col("lr").cast("string").alias("pool"), "benchmark", "method", "score")
    return S.rank_methods(g, ("model", "pool", "benchmark"), ("src0",))


LEDGER = "led AS (SELECT 'run' || (doc_id % 5)::varchar AS run_id, (doc_id % 4 + 1)::int AS stage, n_chars AS tokens_in, n_chars // 4 AS tokens_out FROM documents)"


@query("ledger_cost", f"WITH {LEDGER} SELECT run_id, count(*) AS calls, sum(tokens_in)::bigint AS tokens_in, sum(tokens_out)::bigint AS tokens_out, round(sum(tokens_in * 3 + tokens_out * 15) / 1000000, 6)::double AS usd FROM led GROUP BY run_id")
def ledger_cost(spark, d):
    """Dollars per run at 3 and 15 per million tokens."""
    led = read_table(spark, d, "documents").select(F.concat(F.lit("run"), (F.col("doc_id") % 5).cast("string")).alias("run_id"), F.col("n_chars").alias("i"), F.floor(F.col("n_chars") / 4).alias("o"))
    usd = F.sum(F.col("i").cast("decimal(18,0)") * 3 + F.col("o").cast("decimal(18,0)") * 15) / 1_000_000
    return led.groupBy("run_id").agg(F.count(F.lit(1)).alias("calls"), F.sum("i").alias("tokens_in"), F.sum("o").alias("tokens_out"), F.round(usd.cast("double"), 6).alias("usd"))


@query("eval_label_precision", f"WITH s AS (SELECT doc_id FROM documents ORDER BY {key_sql('doc_id')}, doc_id LIMIT 100) SELECT count(*) AS labelled, round(avg(quality), 6) AS quality, round(avg(toxic), 6) AS toxic FROM s JOIN labels USING (doc_id)")
def eval_label_precision(spark, d):
    return standin.label_precision(random_k(samples(spark, d), 100), read_table(spark, d, "labels"))


@query(
    "eval_domain_pr",
    "SELECT round(avg(CASE WHEN lang = 'en' THEN 1.0 ELSE 0.0 END), 6) AS precision, round(count(*) FILTER (lang = 'en') / (SELECT count(*) FROM documents WHERE lang = 'en'), 6) AS recall FROM documents WHERE (length(text) - length(regexp_replace(text, '[A-Za-z]+', '', 'g'))) / length(text) >= 0.78",
)
def eval_domain_pr(spark, d):
    pool = samples(spark, d)
    return standin.domain_pr(pool.where(X.latin_share("text") >= 0.78), pool, "en")


@query(
    "eval_proxy_ppl",
    f"""WITH {LM}, bt AS (SELECT item_id, {tokens_sql('text')} AS y FROM benchmark),
    br AS (SELECT item_id, unnest(list_concat(['<s>'], y[1:len(y) - 1])) AS h, unnest(y) AS w FROM bt WHERE len(y) > 0)
    SELECT round(exp(avg(-ln((coalesce(n, 0) + 0.1) / (coalesce(total, 0) + 0.1 * v)))), 4) AS perplexity FROM br LEFT JOIN tot ON tot.h = br.h LEFT JOIN pairs ON pairs.h = br.h AND pairs.w = br.w, vv""",
)
def eval_proxy_ppl(spark, d):
    model, _ = bigram(spark, d)
    return standin.proxy_downstream(model, read_table(spark, d, "benchmark"))


@query("eval_dups", "SELECT count(*) AS n, count(*) - count(DISTINCT text) AS surplus FROM documents")
def eval_dups(spark, d):
    return standin.surplus_copies(samples(spark, d))


@query(
    "eval_contam",
    r"""WITH dw AS (SELECT doc_id, regexp_extract_all(lower(text), '[\p{L}\p{N}]+') AS w FROM documents), bw AS (SELECT regexp_extract_all(lower(text), '[\p{L}\p{N}]+') AS w FROM benchmark),
    bs AS (SELECT DISTINCT array_to_string(w[i:i + 7], ' ') AS s FROM (SELECT w, unnest(range(1, len(w) - 6)) AS i FROM bw)),
    ds AS (SELECT doc_id, array_to_string(w[i:i + 7], ' ') AS s FROM (SELECT doc_id, w, unnest(range(1, len(w) - 6)) AS i FROM dw))
    SELECT count(DISTINCT doc_id) AS contaminated FROM ds JOIN bs USING (s)""",
)
def eval_contam(spark, d):
    return standin.contaminated(read_table(spark, d, "documents"), read_table(spark, d, "benchmark")).agg(F.count_distinct("doc_id").alias("contaminated"))


@query("eval_template_leaks", r"SELECT count(*) FILTER (len(m) > 0) AS rows, coalesce(sum(len(m)), 0)::bigint AS markers FROM (SELECT regexp_extract_all(text || CASE WHEN turn = 1 THEN ' <|im_end|><|im_start|>' ELSE '' END, '<\|[A-Za-z0-9_]+\|>|\[/?INST\]|<</?SYS>>|<(?:start|end)_of_turn>') AS m FROM conversations)")
def eval_template_leaks(spark, d):
    rows = read_table(spark, d, "conversations").withColumn("text", F.concat("text", F.when(F.col("turn") == 1, F.lit(" <|im_end|><|im_start|>")).otherwise(F.lit(""))))
    return S.count_leaks(rows)


@query(
    "eval_overlap",
    f"""WITH a AS (SELECT doc_id FROM documents ORDER BY {key_sql('doc_id')}, doc_id LIMIT 300), b AS (SELECT doc_id FROM documents ORDER BY {key_sql('doc_id', 43)}, doc_id LIMIT 300)
    SELECT (SELECT count(*) FROM a JOIN b USING (doc_id)) AS shared, round((SELECT count(*) FROM a JOIN b USING (doc_id)) / (SELECT count(*) FROM (SELECT * FROM a UNION SELECT * FROM b)), 6) AS jaccard""",
)
def eval_overlap(spark, d):
    s = samples(spark, d)
    return standin.subset_overlap(random_k(s, 300, 42), random_k(s, 300, 43))


@query("eval_diversity", "WITH e AS (SELECT embedding::double[] AS e FROM embeddings), u AS (SELECT i, sum(x / n) AS s FROM (SELECT unnest(range(64)) AS i, unnest(e) AS x, sqrt(list_inner_product(e, e)) AS n FROM e) GROUP BY i) SELECT round((sum(s * s) - any_value(n)) / (any_value(n) * (any_value(n) - 1)), 6) AS mean_cosine FROM u, (SELECT count(*) AS n FROM embeddings)")
def eval_diversity(spark, d):
    return standin.mean_cosine(read_table(spark, d, "embeddings"))


METRIC_MEANS = ", ".join(f"avg({'1 - ' if m == 'mean_diff' else ''}{uniform_sql('doc_id', m)}) AS {m}" for m in METRICS)


@query(
    "weights_sum",
    f"WITH a AS (SELECT {METRIC_MEANS} FROM documents) SELECT setting, pool, round(x + y + z + u, 6) AS total, round(x * loss + y * entropy + z * drift + u * mean_diff, 6) AS mean FROM (VALUES "
    + ", ".join(f"('{s}', '{p}', {', '.join(f'{x}::double' for x in w)})" for s, p, *w in PUBLISHED_WEIGHTS)
    + ") t(setting, pool, x, y, z, u), a",
)
def weights_sum(spark, d):
    """The published weight vectors, each of which sums to 1, and the mean score that they give the documents' seeded metrics."""
    weights = spark.createDataFrame([(s, p, *w) for s, p, *w in PUBLISHED_WEIGHTS], "setting string, pool string, " + ", ".join(f"w_{m} double" for m in METRICS))
    means = N.orient(N.given_metrics(samples(spark, d))).agg(*[F.avg(m).alias(m) for m in METRICS])  # one row
    total, mean = sum(F.col(f"w_{m}") for m in METRICS), sum(F.col(f"w_{m}") * F.col(m) for m in METRICS)
    return means.crossJoin(F.broadcast(weights)).select("setting", "pool", r6(total).alias("total"), r6(mean).alias("mean"))


@query("subset_report", f"WITH s AS (SELECT doc_id, text, lang FROM documents ORDER BY {key_sql('doc_id')}, doc_id LIMIT 200) SELECT count(*) AS n, count(DISTINCT text) AS texts, count(DISTINCT lang) AS langs, round(avg(length(text)), 6) AS mean_chars FROM s")
def subset_report(spark, d):
    """Size, redundancy and spread of a subset."""
    s = random_k(samples(spark, d), 200)
    return s.agg(F.count(F.lit(1)).alias("n"), F.count_distinct(F.md5("text")).alias("texts"), F.count_distinct("lang").alias("langs"), r6(F.avg(F.length("text"))).alias("mean_chars"))
