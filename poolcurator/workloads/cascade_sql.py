"""The cascade with the rule backbone as one DuckDB query: stage 2, stages 2-3, stages 2-4, for the unigram and bigram models.

Configurations are those that the rule backbone writes for the request; the SQL repeats nothing of the
plans but the definitions.
"""

from __future__ import annotations

import json

from poolcurator.backbone.rules import RuleBackbone
from poolcurator.config import METRICS, Policy, Rubric, Weights
from poolcurator.functions import text as X
from poolcurator.workloads.common import BUCKETS_SQL, FDOC, VEC_SQL, fitted_sql, key_sql, share_sql, tokens_sql, unique_sql


def written(kind: str, request: str):
    return json.loads(RuleBackbone().complete(kind, "", {"request": request}))


def policy_sql(policy: Policy) -> str:
    """The policy's conjunction over instruction, output and text."""
    quote = lambda t: t.replace("'", "''")
    tests = [
        f"length(text) BETWEEN {policy.min_total_len} AND {policy.max_total_len}",
        f"length(instruction) >= {policy.min_inst_len}",
        f"length(output) >= {policy.min_out_len}",
        f"length(output) >= {policy.out_inst_ratio_min} * length(instruction)",
        *[f"NOT contains(output, '{quote(p)}')" for p in policy.refusal_phrases],
        f"{share_sql('text', quote(X.unicode_words(policy.noise_regex)))} <= {policy.max_noise_ratio}",
    ]
    if policy.require_en:
        tests.append(f"{share_sql('text', '[A-Za-z]')} >= {policy.min_en_ratio}")
    return " AND ".join(tests)


#: One AdamW step of the probe from fresh state, from shares x and y by bucket.
ADAMW_SQL = "list_sum(list_transform(range(1, 17), lambda i: list_sum(list_transform(range(1, 17), lambda j: 1e-5 * abs((0.5 * x[i] - y[i]) * x[j]) / (abs((0.5 * x[i] - y[i]) * x[j]) + 1e-8))))) / 256"

GENERATED = {
    "bigram": """nx AS (SELECT h, w FROM pairs QUALIFY row_number() OVER (PARTITION BY h ORDER BY n DESC, w DESC) = 1),
gen AS (SELECT h, w AS last, w AS said, 1 AS step FROM nx UNION ALL SELECT gen.h, nx.w, said || ' ' || nx.w, step + 1 FROM gen JOIN nx ON nx.h = gen.last WHERE step < 20),
chain AS (SELECT h, max_by(said, step) AS said FROM gen GROUP BY h),
spoken AS (SELECT sample_id, output, coalesce(c.said, s.said, '') AS generated FROM (SELECT *, coalesce(({x})[-1], '<s>') AS h FROM matched) m LEFT JOIN chain c USING (h) LEFT JOIN chain s ON s.h = '<s>')""",
    "unigram": """spoken AS (SELECT sample_id, output, (SELECT array_to_string(list_transform(range(20), lambda i: w), ' ') FROM uni ORDER BY n DESC, w DESC LIMIT 1) AS generated FROM matched)""",
}
LOSSES = {
    "bigram": """lm AS (SELECT sample_id, avg(-ln((coalesce(n, 0) + 0.1) / (coalesce(total, 0) + 0.1 * v))) AS loss, avg(coalesce(ent, ln(v))) AS entropy
  FROM mrows LEFT JOIN ctx USING (h) LEFT JOIN pairs ON pairs.h = mrows.h AND pairs.w = mrows.w, vv GROUP BY sample_id)""",
    "unigram": """lm AS (SELECT sample_id, avg(-ln((coalesce(n, 0) + 0.1) / z)) AS loss, 1.0 AS entropy FROM mrows LEFT JOIN uni USING (w), (SELECT sum(n) + 0.1 * (count(*) + 1) AS z FROM uni) GROUP BY sample_id)""",
}


def cascade_ctes(pool: str, request: str, stages: tuple[int, ...], target: str = "bigram") -> str:
    """CTEs pool, k, matched, top3 (sample_id, score) and top4 (sample_id, score), as far as the stages go."""
    policy, weights = Policy.merge(written("policy", request)), Weights.parse(written("weights", request))
    rubric = Rubric.parse(written("rubric", request))
    parts = [FDOC, f"pool AS ({pool})", "k AS (SELECT greatest(20, count(*) // 10) AS k FROM pool)", f"matched AS (SELECT * FROM pool WHERE {policy_sql(policy)})"]
    if 3 in stages:
        last = "3 * k" if stages[-1] != 3 else "k"
        scaled = {m: f"CASE WHEN {m} IS NULL THEN NULL WHEN hi_{m} > lo_{m} THEN ({m} - lo_{m}) / (hi_{m} - lo_{m}) ELSE 0.0 END" for m in METRICS}
        scaled["mean_diff"] = f"1 - ({scaled['mean_diff']})"
        total = " + ".join(f"{w} * coalesce({scaled[m]}, 0.0)" for m, w in weights.to_dict().items())
        parts += [
            fitted_sql("fdoc"),
            f"mt AS (SELECT sample_id, {tokens_sql('output')} AS y, {tokens_sql('instruction')} AS x FROM matched)",
            "mrows AS (SELECT sample_id, unnest(list_concat([coalesce(x[-1], '<s>')], y[1:len(y) - 1])) AS h, unnest(y) AS w FROM mt WHERE len(y) > 0)",
            LOSSES[target],
            GENERATED[target].format(x=tokens_sql("instruction")),
            f"ga AS ({BUCKETS_SQL.format(id='sample_id', c='generated', t='spoken')})",
            f"gb AS ({BUCKETS_SQL.format(id='sample_id', c='output', t='spoken')})",
            "gu AS (SELECT id, bucket, sum(a) AS a, sum(b) AS b FROM (SELECT id, bucket, n AS a, 0 AS b FROM ga UNION ALL SELECT id, bucket, 0, n FROM gb) GROUP BY ALL)",
            "gs AS (SELECT id, sum(a * b)::double AS ab, sum(a * a)::double AS aa, sum(b * b)::double AS bb FROM gu GROUP BY id)",
            f"pv AS (SELECT sample_id, {VEC_SQL.format(t='x')} AS x, {VEC_SQL.format(t='y')} AS y FROM mt)",
            f"""metrics AS (SELECT m.sample_id, loss, entropy, 1 - coalesce(CASE WHEN aa > 0 AND bb > 0 THEN ab / sqrt(aa * bb) ELSE 0 END, 0) AS drift, {ADAMW_SQL} AS mean_diff
  FROM matched m LEFT JOIN lm USING (sample_id) LEFT JOIN gs ON gs.id = m.sample_id JOIN pv USING (sample_id))""",
            "bounds AS (SELECT " + ", ".join(f"min({m}) AS lo_{m}, max({m}) AS hi_{m}" for m in METRICS) + " FROM metrics)",
            f"scored3 AS (SELECT sample_id, round({total}, 6) AS score FROM metrics, bounds)",
            f"top3 AS (SELECT sample_id, score FROM scored3, k QUALIFY row_number() OVER (ORDER BY score DESC, sample_id) <= {last})",
        ]
    if 4 in stages:
        weighed = " + ".join(f"{d[2]} * d{i % 3 + 1}" for i, d in enumerate(rubric.dimensions))
        parts += [
            f"bt AS (SELECT m.*, score, (row_number() OVER (ORDER BY {key_sql('sample_id')}, sample_id) - 1) // 10 AS batch_id FROM matched m JOIN top3 USING (sample_id))",
            f"ft AS (SELECT batch_id, sample_id, score, round({unique_sql('text')}, 6) AS variety, round(1 - ({share_sql('text', X.noise_class())}), 6) AS clean, length(text) AS len FROM bt)",
            "rs AS (SELECT sample_id, score, " + ", ".join(f"ntile(5) OVER (PARTITION BY batch_id ORDER BY {c}, sample_id) AS d{i + 1}" for i, c in enumerate(("variety", "clean", "len"))) + " FROM ft)",
            f"qs AS (SELECT sample_id, score AS s3, round({weighed}, 6) AS q FROM rs)",
            "top4 AS (SELECT sample_id, q AS score FROM qs, k QUALIFY row_number() OVER (ORDER BY q DESC, s3 DESC, sample_id) <= k)",
        ]
    if 3 not in stages:
        parts.append(f"top2 AS (SELECT sample_id, NULL::double AS score FROM matched, k QUALIFY row_number() OVER (ORDER BY {key_sql('sample_id')}, sample_id) <= k)")
    return "WITH RECURSIVE " + ",\n".join(parts)


def cascade_sql(pool: str, request: str, stages: tuple[int, ...], target: str = "bigram") -> str:
    """(sample_id, stage, score, rank) of the selected samples."""
    n = stages[-1]
    return f"""{cascade_ctes(pool, request, stages, target)}
SELECT sample_id, {n} AS stage, round(score, 4) AS score, (row_number() OVER (ORDER BY score DESC NULLS LAST, sample_id))::int AS rank FROM top{n}"""


def funnel_sql(pool: str, request: str) -> str:
    """(stage, n) of a single-domain run."""
    return f"""{cascade_ctes(pool, request, (1, 2, 3, 4))}
SELECT * FROM (VALUES (0, (SELECT count(*) FROM pool)), (1, (SELECT count(*) FROM pool)), (2, (SELECT count(*) FROM matched)), (3, (SELECT count(*) FROM top3)), (4, (SELECT count(*) FROM top4))) AS f(stage, n)"""
