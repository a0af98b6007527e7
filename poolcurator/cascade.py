"""The four stages in sequence, any sub-sequence of them, and what it costs."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from poolcurator.backbone.core import Backbone, CostLedger
from poolcurator.backbone.rules import RuleBackbone
from poolcurator.config import CascadeConfig, Policy, Rubric, SelectionRequest
from poolcurator.inspect import inspect_pool
from poolcurator.operators.topk import random_k, rehydrate, top_k, with_rank
from poolcurator.sources.files import drop_durable, durable
from poolcurator.stages import characteristic, domain, informativeness, quality
from poolcurator.target.probe import mean_diff


@dataclass
class CascadeResult:
    """Selected rows (sample_id, stage, score, rank) and what was decided on the way."""

    selected: DataFrame
    survivors: dict[int, DataFrame]
    configs: dict[str, object] = field(default_factory=dict)
    ledger: CostLedger = field(default_factory=CostLedger)
    scores: dict[int, DataFrame] = field(default_factory=dict)
    tables: list[DataFrame] = field(default_factory=list)

    def funnel(self) -> list[tuple[int, int]]:
        return [(s, df.count()) for s, df in sorted(self.survivors.items())]

    def release(self) -> None:
        """Removes the run's tables from the shared folder; the result can no longer be read then."""
        while self.tables:
            drop_durable(self.tables.pop())


def run_cascade(
    pool: DataFrame,
    request: SelectionRequest,
    target,
    cfg: CascadeConfig = CascadeConfig(),
    backbone: Backbone | None = None,
    stages: Sequence[int] = (1, 2, 3, 4),
    judge: Callable[[Rubric], Callable[[str, list[dict]], str]] | None = None,
    key: str = "sample_id",
    optimizer: str = "adamw",
    ledger: CostLedger | None = None,
    labelled: domain.Labelled | None = None,
    front: dict | None = None,
) -> CascadeResult:
    """The best k samples for the request; stages may be any sub-sequence, also in another order.

    What a stage keeps is written to the shared folder before the next one looks at it, so no plan is longer
    than a stage, texts are filtered once, and the next stage reads only the columns it needs. `judge` makes the
    judge for a rubric; without one the offline judge scores natively and costs nothing. `labelled` are clusters of
    the pool that an earlier run has named. `front` is filled with what the run finds out before it asks the target, and a
    later run of the same pool, request, backbone, settings and stages takes it from there: its ledger lacks those calls, and its
    tables are the earlier run's.
    """
    backbone = backbone or RuleBackbone(temperature=cfg.temperature)
    ledger = ledger or CostLedger()
    tables: list[DataFrame] = []

    def keep(df: DataFrame, name: str) -> DataFrame:
        tables.append(durable(df, name))
        return tables[-1]

    front, met = {} if front is None else front, []

    def once(name: str, make: Callable[[], object], asks: bool = False):
        if asks:  # the target had a say in what is looked at
            return make()
        place = len(met), name
        if place not in front:
            front[place] = make()
        return front[place]

    def matched() -> tuple[Policy, DataFrame]:
        policy = characteristic.propose_policy(request, inspect_pool(now, 2, backbone, request, ledger), backbone, cfg.max_retries, ledger)
        return policy, keep(characteristic.match(now, policy), "matched")

    now, survivors, configs, scored = pool, {0: pool}, {}, {}
    scores: DataFrame | None = None
    ranked = False
    for stage in stages:
        met.append(stage)
        if stage == 1:
            now = domain.select_domain(now, request, backbone, cfg, key, ledger, labelled)
            if now is not pool:
                now = keep(now, "domain")
        elif stage == 2:
            configs["policy"], now = once("matched", matched, ranked)
        elif stage == 3:
            weights = once("weights", lambda: informativeness.propose_weights(request, inspect_pool(now, 3, backbone, request, ledger), backbone, cfg.max_retries, ledger), ranked)
            configs["weights"] = weights
            own = hasattr(target, "shift") or optimizer == "table"
            shift = None if own else once("shift", lambda: keep(mean_diff(now, optimizer, cfg.lr, key=key), "shift"), ranked)
            metrics = keep(informativeness.measure(now, target, optimizer=optimizer, lr=cfg.lr, key=key, moved=shift), "metrics")
            k = cfg.k_star if stage != stages[-1] else cfg.k
            scores = keep(informativeness.informative(metrics, weights, k, key).select(key, "score"), "informative")
            now, ranked = keep(rehydrate(now, scores, key), "top"), True
        elif stage == 4:
            rubric = quality.propose_rubric(request, inspect_pool(now, 4, backbone, request, ledger), backbone, cfg.max_retries, ledger)
            configs["rubric"] = rubric
            n = now.count()
            batched = keep(quality.assign_batches(now, cfg.batch, cfg.seed, key, quality.batch_ranges(n, cfg.batch)), "batches")
            judge_now = judge(rubric) if judge else None
            if judge_now is None:
                verdicts = quality.rule_verdicts(batched, list(rubric.weights), key)
            else:
                raw = keep(quality.score_batches(batched, rubric, judge_now, cfg, key), "verdicts")
                quality.bill(raw, ledger)
                verdicts = quality.parse_verdicts(raw)
            q = quality.quality_score(quality.apply_flags(verdicts, cfg.drop_flagged), rubric.weights, key)
            joined = now.select(key).join(q, key, "left")
            joined = joined.join(scores, key, "left") if scores is not None else joined.withColumn("score", F.lit(0.0))
            best = quality.best_by_quality(joined.withColumn("q", F.round("q", 6)), cfg.k, key)
            scores = keep(best.select(key, F.col("q").alias("score")), "best")
            now, ranked = rehydrate(now, scores, key), True
        survivors[stage] = now
        if stage > 2:
            scored[stage] = scores
    if not ranked:
        now = random_k(now, cfg.k, cfg.seed, key)
        scores = now.select(key, F.lit(None).cast("double").alias("score"))
    best = with_rank(top_k(scores, "score", cfg.k, key), "score", cfg.k, key)
    selected = keep(best.select(F.col(key), F.lit(stages[-1]).alias("stage"), "score", "rank"), "selected")
    return CascadeResult(selected, survivors, configs, ledger, scored, tables)


def select_subset(pool: DataFrame, request: SelectionRequest, target, cfg: CascadeConfig = CascadeConfig(), backbone: Backbone | None = None) -> CascadeResult:
    """All four stages."""
    return run_cascade(pool, request, target, cfg, backbone)


def explain_cascade(n: int, cfg: CascadeConfig = CascadeConfig(), clusters: int = 20, multi: bool = True) -> dict[str, int]:
    """Calls, model passes and scans that a run needs, before it runs."""
    configuration = (clusters + 1 if multi else 0) + 3
    return {"configuration_calls": configuration, "judge_calls": -(-min(n, cfg.k_star) // cfg.batch), "model_passes": 3 * n, "scans": 5 + 2 * int(multi), "selected": min(n, cfg.k)}
