"""Connected components of an edge table by alternating large and small stars."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from poolcurator.llm.store import drop_path, write_table


def connected_components(edges: DataFrame, max_rounds: int = 200) -> tuple[DataFrame, str]:
    """(node, root) for every node of the edges (a, b); root is the smallest node of its component. Also the path of the table.

    Each round joins every neighbour of a node to the node's least neighbour: larger neighbours
    in the first half, the others in the second. Rounds end when the edges no longer change; the
    edges of a round are written to the shared folder, so lineage stays short and a lost executor
    costs one round. Rounds grow with the logarithm of a component's size; an error is raised if they do not end.
    """
    both = edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    now, path = write_table(both, "edges")
    mark = None
    for _ in range(max_rounds):
        sides = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = sides.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = sides.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.where("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        new, new_path = write_table(small, "edges")
        seen = new.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        drop_path(edges.sparkSession, path)
        now, path = new, new_path
        if seen == mark or not seen[0]:
            break
        mark = seen
    else:
        raise RuntimeError(f"components still change after {max_rounds} rounds")
    roots = now.groupBy("u").agg(F.min("v").alias("root")).select(F.col("u").alias("node"), "root")
    return roots.unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()), path
