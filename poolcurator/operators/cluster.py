"""Clustering: k-means with restarts, exact HDBSCAN by blocks, assignment to centroids."""

from __future__ import annotations

from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.ml.clustering import KMeans
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame, SparkSession
from pyspark.util import inheritable_thread_target
from pyspark.sql import functions as F

from poolcurator.functions.text import squared_distance

#: Rows on which k-means is fitted; assignment covers all rows.
FIT_ROWS = 10_000_000
#: Rows up to which the restarts are fitted at the same time: each holds its own copy of the points.
SIDE_BY_SIDE = 200_000


def choose_clusterer(n: int, n_c: int = 50_000) -> str:
    return "hdbscan" if n <= n_c else "kmeans"


def assign_nearest(df: DataFrame, centroids: list[tuple[int, list[float]]], key: str = "sample_id", vector: str = "embedding") -> DataFrame:
    """(key, cluster_id, dist): the nearest centroid, ties to the least id; squared distance in one narrow pass.

    The centroids are literals of the plan: their number is the caller's parameter.
    """
    spark = df.sparkSession
    table = spark.createDataFrame([([(int(c), [float(x) for x in v]) for c, v in centroids],)], "cs array<struct<c:int,v:array<double>>>")
    near = F.array_min(F.transform("cs", lambda x: F.struct(squared_distance(F.col(vector), x["v"]).alias("d"), x["c"].alias("c"))))
    return df.crossJoin(F.broadcast(table)).select(key, near.alias("near")).select(key, F.col("near.c").alias("cluster_id"), F.col("near.d").alias("dist"))


def nearest_centre(df: DataFrame, centroids: list[tuple[int, list[float]]], key: str = "sample_id", vector: str = "embedding") -> DataFrame:
    """What assign_nearest says, a batch of rows against one centroid at a time."""
    ids, centres = [int(c) for c, _ in sorted(centroids, key=lambda x: x[0])], [np.array(v, dtype=np.float64) for _, v in sorted(centroids, key=lambda x: x[0])]

    def run(batches):
        for b in batches:
            if not len(b):
                continue
            x = b.column(vector).flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(b), -1)
            d = np.stack([np.square(x - v).sum(axis=1) for v in centres])
            at = d.argmin(axis=0)  # the first of equals
            yield pa.RecordBatch.from_arrays([b.column(key), pa.array(np.array(ids, dtype=np.int32)[at]), pa.array(d[at, np.arange(len(b))])], [key, "cluster_id", "dist"])

    return df.select(key, vector).mapInArrow(run, f"{key} {dict(df.dtypes)[key]}, cluster_id int, dist double")


def lloyd_step(assigned: DataFrame, vectors: DataFrame, key: str = "sample_id", vector: str = "embedding") -> DataFrame:
    """(cluster_id, dim, value): the clusters' mean vectors."""
    rows = vectors.join(assigned.select(key, "cluster_id"), key).select("cluster_id", F.posexplode(vector).alias("dim", "x"))
    return rows.groupBy("cluster_id", "dim").agg(F.avg(F.col("x").cast("double")).alias("value"))


def kmeans(df: DataFrame, k: int = 20, n_init: int = 3, max_iter: int = 300, seed: int = 42, key: str = "sample_id", vector: str = "embedding", fit_rows: int = FIT_ROWS) -> DataFrame:
    """(key, cluster_id, dist): the best of n_init seeded runs, by within-cluster cost, the first of equals.

    The runs do not know each other; they go on side by side while the points are few, as a round of a run is a small job.
    """
    n = df.count()
    rows = df.select(key, F.col(vector).cast("array<double>").alias("embedding"))
    fit = rows.where(F.pmod(F.xxhash64(key, F.lit(seed)), F.lit(1_000_000)) < int(1_000_000 * min(1.0, fit_rows / max(n, 1)))) if n > fit_rows else rows
    points = fit.select(array_to_vector("embedding").alias("features")).persist()
    points.count()  # else each run would compute them

    def one(i: int) -> tuple[float, list]:
        model = KMeans(k=min(k, max(n, 2)), maxIter=max_iter, seed=seed + i, solver="block").fit(points)
        return model.summary.trainingCost, model.clusterCenters()

    with ThreadPoolExecutor(n_init if n <= SIDE_BY_SIDE else 1) as side_by_side:
        runs = list(side_by_side.map(inheritable_thread_target(df.sparkSession)(one), range(n_init)))
    points.unpersist()
    _, best = min(runs, key=lambda r: r[0])
    return nearest_centre(rows, list(enumerate(best)), key)


def _pairwise(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    d = (a * a).sum(1)[:, None] + (b * b).sum(1)[None] - 2 * a @ b.T
    return np.sqrt(np.maximum(d, 0))


def _forest(n_left: int, w: np.ndarray, i: np.ndarray, j: np.ndarray) -> list[int]:
    """Positions of a minimum spanning forest's edges (Kruskal)."""
    parent = list(range(n_left))

    def find(x: int) -> int:
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    out = []
    for e in np.lexsort((j, i, w)):
        a, b = find(int(i[e])), find(int(j[e]))
        if a != b:
            parent[max(a, b)] = min(a, b)
            out.append(int(e))
    return out


def _prim(d: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Minimum spanning tree of a full distance matrix."""
    n = len(d)
    inside = np.zeros(n, dtype=bool)
    best, source = np.full(n, np.inf), np.zeros(n, dtype=int)
    at, out = 0, []
    for _ in range(n - 1):
        inside[at] = True
        closer = d[at] < best
        best[closer], source[closer] = d[at][closer], at
        best[inside] = np.inf
        at = int(np.argmin(best))
        out.append((best[at], source[at], at))
        best[at] = np.inf
    w, i, j = zip(*out, strict=True) if out else ((), (), ())
    return np.array(w), np.array(i, dtype=int), np.array(j, dtype=int)


def mutual_tree(df: DataFrame, min_samples: int, key: str = "sample_id", vector: str = "embedding", block: int = 2_000) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(ids, weight, i, j): minimum spanning tree of mutual reachability distances, exact.

    Rows are cut into blocks; tasks hold pairs of blocks. A first pass finds each row's distance to
    its min_samples-th neighbour (itself counts), a second the spanning tree of each pair of blocks.
    The tree of the whole is inside the union of the pairs' trees. For pools of up to n_c rows.
    """
    spark: SparkSession = df.sparkSession
    got = df.select(key, vector).orderBy(key).toPandas()
    ids = got[key].to_numpy()
    points = np.array(got[vector].tolist(), dtype=np.float64).reshape(len(ids), -1)
    n = len(ids)
    shared = spark.sparkContext.broadcast(points)  # at most n_c rows
    edges = list(range(0, n, block))
    m = min(min_samples, n)
    tasks = spark.range(0, len(edges), 1, max(1, len(edges)))

    def cores(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        x = shared.value
        for b in batches:
            for t in b["id"]:
                lo, hi = edges[t], min(n, edges[t] + block)
                near = np.full((hi - lo, m), np.inf)
                for s in edges:
                    near = np.partition(np.concatenate([near, _pairwise(x[lo:hi], x[s : s + block])], axis=1), m - 1, axis=1)[:, :m]
                yield pd.DataFrame({"row": np.arange(lo, hi), "core": near.max(axis=1)})

    c = tasks.mapInPandas(cores, "row long, core double").toPandas().sort_values("row")["core"].to_numpy()
    core = spark.sparkContext.broadcast(c)
    pairs = spark.createDataFrame([(a, b) for a in range(len(edges)) for b in range(a, len(edges))], "a int, b int").repartition(max(1, len(edges) * (len(edges) + 1) // 2))

    def trees(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        x, k = shared.value, core.value
        for batch in batches:
            for a, b in zip(batch["a"], batch["b"], strict=True):
                rows = np.arange(edges[a], min(n, edges[a] + block))
                if a != b:
                    rows = np.append(rows, np.arange(edges[b], min(n, edges[b] + block)))
                d = np.maximum(_pairwise(x[rows], x[rows]), np.maximum(k[rows][:, None], k[rows][None]))
                np.fill_diagonal(d, np.inf)
                w, i, j = _prim(d)
                yield pd.DataFrame({"w": w, "i": rows[i], "j": rows[j]})

    found = pairs.mapInPandas(trees, "w double, i long, j long").toPandas().drop_duplicates()
    w, i, j = found["w"].to_numpy(), found["i"].to_numpy(), found["j"].to_numpy()
    keep = _forest(n, w, np.minimum(i, j), np.maximum(i, j))
    return ids, w[keep], i[keep], j[keep]


def condense(n: int, w: np.ndarray, i: np.ndarray, j: np.ndarray, min_cluster_size: int) -> np.ndarray:
    """Cluster of each row by excess of mass over the condensed single-linkage tree; -1 is noise."""
    label = np.full(n, -1)
    if n < 2 or n < min_cluster_size:
        return label
    parent = list(range(2 * n - 1))
    size = [1] * n + [0] * (n - 1)
    child: dict[int, tuple[int, int, float]] = {}

    def find(x: int) -> int:
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    node = n
    for e in np.argsort(w, kind="stable"):
        a, b = find(int(i[e])), find(int(j[e]))
        parent[a] = parent[b] = node
        size[node] = size[a] + size[b]
        child[node] = (a, b, float(w[e]))
        node += 1

    def leaves(x: int) -> list[int]:
        out, work = [], [x]
        while work:
            y = work.pop()
            if y < n:
                out.append(y)
            else:
                work += child[y][:2]
        return out

    # clusters: (born, members' exits, children)
    born, stable, kids, top = {0: 0.0}, {0: 0.0}, {0: []}, {0: node - 1}
    work, fresh = [(node - 1, 0)], 1
    while work:
        x, c = work.pop()
        while x >= n:
            a, b, d = child[x]
            at = 1 / max(d, 1e-12)
            big = [y for y in (a, b) if size[y] >= min_cluster_size]
            if len(big) == 2:
                stable[c] += (size[a] + size[b]) * (at - born[c])
                for y in big:
                    born[fresh], stable[fresh], kids[fresh], top[fresh] = at, 0.0, [], y
                    kids[c].append(fresh)
                    work.append((y, fresh))
                    fresh += 1
                break
            if len(big) == 1:
                stable[c] += (size[x] - size[big[0]]) * (at - born[c])
                x = big[0]
            else:
                stable[c] += size[x] * (at - born[c])
                break
    chosen, value = {}, {}
    for c in sorted(born, reverse=True):
        below = sum(value[k] for k in kids[c])
        if c == 0 or (kids[c] and below > stable[c]):
            value[c], chosen[c] = below if kids[c] else stable[c], False
        else:
            value[c], chosen[c] = stable[c], True
    number, work = 0, [0]
    while work:
        c = work.pop(0)
        if chosen[c]:
            label[leaves(top[c])] = number
            number += 1
        else:
            work += kids[c]
    return label


def hdbscan(df: DataFrame, min_cluster_size: int = 50, min_samples: int | None = None, noise_policy: str = "drop", key: str = "sample_id", vector: str = "embedding", block: int = 2_000) -> DataFrame:
    """(key, cluster_id): density clusters; noise is -1, dropped, given the nearest cluster, or a cluster of its own."""
    spark = df.sparkSession
    ids, w, i, j = mutual_tree(df, min_samples or min_cluster_size, key, vector, block)
    label = condense(len(ids), w, i, j, min_cluster_size)
    table = spark.createDataFrame(pd.DataFrame({key: ids, "cluster_id": label.astype("int32")}), f"{key} long, cluster_id int")
    if noise_policy == "drop":
        return table.where("cluster_id >= 0")
    if noise_policy == "own_cluster":
        return table
    known = df.join(table, key).where("cluster_id >= 0")
    means = known.groupBy("cluster_id").agg(*[F.avg(F.get(vector, F.lit(d))).alias(f"d{d}") for d in range(len(df.select(vector).first()[0]) if len(ids) else 0)]).collect()
    noise = df.join(table.where("cluster_id < 0"), key, "left_semi")
    near = assign_nearest(noise, [(r[0], list(r[1:])) for r in means], key, vector)
    return table.where("cluster_id >= 0").unionByName(near.select(key, "cluster_id"))
