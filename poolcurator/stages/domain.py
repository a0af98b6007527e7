"""Stage 1: cluster, label by a small draw, keep the clusters that serve the request."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from poolcurator.backbone.core import Backbone, CostLedger, ask
from poolcurator.config import CascadeConfig, ConfigRejected, SelectionRequest
from poolcurator.operators import cluster
from poolcurator.operators.embed import embed
from poolcurator.operators.topk import per_group
from poolcurator.sources.files import durable

CUES = {"single": ("single-domain", "is all"), "multi": ("multi-domain", "mixes", "mixed")}


def decide_mode(request: SelectionRequest, backbone: Backbone | None = None, cues: dict = CUES, ledger: CostLedger | None = None) -> str:
    """single or multi, by words of the request, else by the model; single if neither tells."""
    asked = request.text.lower()
    for mode, words in cues.items():
        if any(w in asked for w in words):
            return mode
    if backbone is None:
        return "single"

    def parse(reply: str) -> str:
        if reply not in ("single", "multi"):
            raise ValueError(reply)
        return reply

    return ask(backbone, "mode", {"request": request.text}, parse, ledger=ledger)


def cluster_pool(pool: DataFrame, cfg: CascadeConfig = CascadeConfig(), key: str = "sample_id", vectors: DataFrame | None = None) -> DataFrame:
    """(key, cluster_id) by the clusterer that fits the pool's size; `vectors` are the pool's written (key, embedding) where they are at hand."""
    if vectors is None:
        vectors = pool if "embedding" in pool.columns else embed(pool.select(key, "text"))
        vectors = durable(vectors.select(key, "embedding"), "vectors")
    if cluster.choose_clusterer(vectors.count(), cfg.n_c) == "hdbscan":
        return cluster.hdbscan(vectors, cfg.min_cluster_size, cfg.min_samples, cfg.noise_policy, key)
    return cluster.kmeans(vectors, cfg.k_c, cfg.n_init, cfg.max_iter, cfg.seed, key).select(key, "cluster_id")


def label_clusters(assigned: DataFrame, pool: DataFrame, backbone: Backbone, cfg: CascadeConfig = CascadeConfig(), key: str = "sample_id", ledger: CostLedger | None = None) -> list[tuple[int, list[str]]]:
    """(cluster, names): one call per cluster on up to n_s samples; the request is not shown, so labels serve every request."""
    draw = per_group(assigned, "cluster_id", cfg.n_s, cfg.seed, key)
    shown = pool.join(F.broadcast(draw.select(key, "cluster_id")), key).select("cluster_id", key, F.substring("instruction", 1, cfg.trunc_chars).alias("instruction"), F.substring("output", 1, cfg.trunc_chars).alias("output"), "lang")
    groups: dict[int, list[dict]] = {}
    for r in shown.orderBy("cluster_id", key).collect():  # clusters x n_s rows
        groups.setdefault(r["cluster_id"], []).append(r.asDict())

    def parse(reply) -> list[str]:
        if not isinstance(reply, list) or not reply or not all(isinstance(x, str) and x for x in reply):
            raise ValueError("a list of names")
        return reply

    return [(c, ask(backbone, "label", {"samples": rows}, parse, cfg.max_retries, ledger)) for c, rows in sorted(groups.items())]


def match_clusters(request: SelectionRequest, labels: list[tuple[int, list[str]]], backbone: Backbone, cfg: CascadeConfig = CascadeConfig(), ledger: CostLedger | None = None) -> list[int]:
    known = {c for c, _ in labels}

    def parse(reply) -> list[int]:
        ids = reply["matching_cluster_ids"]
        if not all(isinstance(i, int) and not isinstance(i, bool) and i in known for i in ids):
            raise ConfigRejected("unknown cluster id")
        return sorted(set(ids))

    return ask(backbone, "match", {"request": request.text, "clusters": labels}, parse, cfg.max_retries, ledger)


def keep_clusters(pool: DataFrame, assigned: DataFrame, ids: list[int], key: str = "sample_id") -> DataFrame:
    """Rows of the pool in the given clusters."""
    return pool.join(assigned.where(F.col("cluster_id").isin(ids)).select(key), key, "left_semi")


Labelled = tuple[DataFrame, list[tuple[int, list[str]]]]


def labelled_clusters(pool: DataFrame, backbone: Backbone, cfg: CascadeConfig = CascadeConfig(), key: str = "sample_id", ledger: CostLedger | None = None, vectors: DataFrame | None = None) -> Labelled:
    """The pool's clusters and their names, which know no request and so serve all of them."""
    assigned = durable(cluster_pool(pool, cfg, key, vectors), "clusters")
    return assigned, label_clusters(assigned, pool, backbone, cfg, key, ledger)


def select_domain(pool: DataFrame, request: SelectionRequest, backbone: Backbone, cfg: CascadeConfig = CascadeConfig(), key: str = "sample_id", ledger: CostLedger | None = None, labelled: Labelled | None = None) -> DataFrame:
    """The pool itself when it holds one field; else the union of the clusters that match."""
    if decide_mode(request, backbone, ledger=ledger) == "single":
        return pool
    assigned, labels = labelled or labelled_clusters(pool, backbone, cfg, key, ledger)
    return keep_clusters(pool, assigned, match_clusters(request, labels, backbone, cfg, ledger), key)
