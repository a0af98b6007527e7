"""Queries of the cascade and of the experiments."""

from __future__ import annotations

from pyspark.sql import functions as F

from poolcurator.backbone.rules import WEIGHT_CUES
from poolcurator.evaluate import runner as R
from poolcurator.registry import query
from poolcurator.workloads.cascade_sql import cascade_sql, funnel_sql
from poolcurator.workloads.common import pool_of, read_table


EN = "SELECT * FROM fdoc WHERE lang = 'en'"
FR = "SELECT * FROM fdoc WHERE lang = 'fr'"
CHAT = """SELECT conv_id * 1000 + turn AS sample_id, text AS instruction, said AS output, concat_ws(chr(10), text, said) AS text
  FROM (SELECT *, lead(role) OVER w AS next_role, lead(text) OVER w AS said FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)) WHERE role = 'user' AND next_role = 'assistant'"""


def cascade_query(name: str, pool: str, request: str, stages=(1, 2, 3, 4), target: str = "bigram", rows: str | None = None, **changes):
    """Registers a run; with the pool's rows in SQL also its twin."""

    def run(spark, d):
        out = R.cascade(spark, d, pool, request, target, stages, **changes).selected
        return out.select("sample_id", "stage", F.round("score", 4).alias("score"), "rank")

    query(name, cascade_sql(rows, R.REQUESTS[request], stages, target) if rows else None)(run)


cascade_query("cascade_full", "SD-1", "R-en", rows=EN)
cascade_query("cascade_depth2", "SD-1", "R-en", (2,), rows=EN)
cascade_query("cascade_depth23", "SD-1", "R-en", (2, 3), rows=EN)
cascade_query("cascade_depth234", "SD-1", "R-en", (2, 3, 4), rows=EN)
cascade_query("cascade_multi", "MD-1", "R-mix-de")
cascade_query("cascade_multi_kmeans", "MD-1", "R-mix-de", n_c=500)
cascade_query("cascade_chat", "SD-5", "R-chat", rows=CHAT)
cascade_query("cascade_unigram", "SD-3", "R-fr", (2, 3, 4), "unigram", FR)
cascade_query("cascade_bigram_fr", "SD-3", "R-fr", (2, 3, 4), "bigram", FR)
cascade_query("cascade_cache", "SD-3", "R-fr", (2, 3, 4), "cache")


@query("funnel_counts", funnel_sql(EN, R.REQUESTS["R-en"]))
def funnel_counts(spark, d):
    """Survivors after every stage."""
    f = R.cascade(spark, d, "SD-1", "R-en").funnel()
    return spark.createDataFrame(f, "stage int, n long")


@query("ifd_stage1")
def ifd_stage1(spark, d):
    return R.stage1_then_ifd(spark, d)


def single_grid(pool: str, request: str):
    """Registers the comparison on one pool for all three targets: a third of the pool's share of the 18 settings each."""

    @query(f"experiment_{pool.lower().replace('-', '')}")
    def run(spark, d):
        return R.label_report(R.compare(spark, d, pool, request, R.TARGETS), R.pool_labels(spark, d, pool), ("target", "method"))


for _pool, _request in R.SINGLE:
    single_grid(_pool, _request)


def multi_grid(pool: str):
    """Registers the multi-domain comparison on one pool, a row per request and method; its rows are the stage-1 ablation too."""

    @query(f"experiment_{pool.lower().replace('-', '')}")
    def run(spark, d):
        requests = tuple(r for p, r in R.MULTI if p == pool)
        return R.precision_report(R.compare_multi(spark, d, pool, requests), pool_of(spark, d, pool))


for _pool in dict.fromkeys(p for p, _ in R.MULTI):
    multi_grid(_pool)


@query("experiment_depths")
def experiment_depths(spark, d):
    """Quality and toxic labels of the subsets after stages 2, 2-3 and 2-4 on four pools."""
    out, model = None, R.target_for(spark, d, "bigram")  # fitted on all documents, so it serves every pool
    for pool, name in R.DEPTHS:
        r = R.label_report(R.depths(spark, d, pool, name, model=model), R.pool_labels(spark, d, pool)).withColumn("pool", F.lit(pool))
        out = r if out is None else out.unionByName(r)
    return out


def cues_sql(cues: tuple[str, ...]) -> str:
    return " + ".join(f"contains(t, '{c}')::int" for c in cues)


#: Rounded as printed, which is how the backbone rounds: by the exact value, halves to even.
WEIGHTS_SQL = f"""WITH c AS (SELECT conv_id, turn, lower(coalesce(text, '')) AS t FROM conversations WHERE role = 'user'),
r AS (SELECT conv_id, turn, {", ".join(f"1 + 2 * ({cues_sql(c)}) AS {m}" for m, c in WEIGHT_CUES.items())} FROM c),
w AS (SELECT conv_id, turn, {", ".join(f"format('{{:.2f}}', {m} / ({' + '.join(WEIGHT_CUES)}))::double AS {m}" for m in ("loss", "entropy", "drift"))} FROM r)
SELECT *, format('{{:.2f}}', 1 - loss - entropy - drift)::double AS mean_diff FROM w"""


@query("experiment_weights", WEIGHTS_SQL)
def experiment_weights(spark, d):
    return R.weight_allocations(read_table(spark, d, "conversations"))


@query("experiment_licences", "SELECT doc_id FROM documents WHERE substr(source, 4)::int % 5 IN (0, 1, 2)")
def experiment_licences(spark, d):
    """Samples of sources whose licence is allowed."""
    allowed = [s for s, lic in R.LICENCES.items() if lic in R.ALLOWED]
    return read_table(spark, d, "documents").where(F.col("source").isin(allowed)).select("doc_id")


@query("cost_ledger")
def cost_ledger(spark, d):
    """Calls, tokens and dollars of a single-domain and a multi-domain run, the judge's calls included."""
    from poolcurator import schema

    return spark.createDataFrame(R.costs(spark, d), schema.LEDGER)
