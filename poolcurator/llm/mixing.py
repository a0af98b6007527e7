"""A mix of sources near target weights, with capped repetition.

Water-filling: each source's share of the budget follows its weight; a source whose share exceeds
`max_epochs` times its size is clamped there and the excess is shared again by weight among the
others, until none is above. A target is then met by whole repetitions of the source and one
fractional one, drawn by a seeded order: documents come in order of a seeded hash and are taken
until their sizes reach the fraction. The point where that happens is found from a histogram of the
hash per source, and row by row only inside the one bin that holds it, so no source is sorted whole.
Then, up to `CLOSING` times, the document whose size is nearest to what is still missing closes the gap.

Words are counted once, into a narrow table that all steps but the last read. Sources are few: their sizes are on the
driver, and tables with a row per source are broadcast only as far as their number allows.

Defined cases: null text has size 0 and is taken 0 words; a null source is a source of its own, last;
repeated rows are drawn alike; sources without words get target 0; weights repeat in order of the
sources' code points; an empty table gives an empty result. If all sources are clamped the mix is
smaller than the budget.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from poolcurator.llm.store import pick, small_side, write_table

BINS = 4096
#: Documents that may close what is left of a source's target.
CLOSING = 4


def water_fill(sizes: Sequence[float], weights: Sequence[float], budget: float, max_epochs: float) -> list[float]:
    """Targets by weight, none above max_epochs times its size."""
    caps = [float(max_epochs * s) for s in sizes]
    target = [0.0] * len(sizes)
    free = [i for i in range(len(sizes)) if sizes[i] > 0]
    left = float(budget)
    while free:
        weight = sum(weights[i] for i in free)
        over = [i for i in free if left * weights[i] / weight > caps[i]]
        if not over:
            for i in free:
                target[i] = left * weights[i] / weight
            break
        for i in over:
            target[i] = caps[i]
            left -= caps[i]
        free = [i for i in free if i not in set(over)]
    return target


def mix(docs: DataFrame, weights: Sequence[float] = (1, 2, 3), max_epochs: float = 3, share: float = 1.0, seed: int = 42, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", keep: Sequence[str] = ()) -> DataFrame:
    """One row per row of docs: (id, size, source_size, target, repeats, taken) and the columns in keep."""
    spark = docs.sparkSession
    words = F.coalesce(F.regexp_count(F.col(text_col), F.lit(r"[^\x20\x09\x0A\x0B\x0C\x0D]+")), F.lit(0)).cast("long")
    u = F.shiftrightunsigned(F.xxhash64(F.lit(seed), F.col("id")), 12)  # 52 bits
    whole_rows = docs.select(F.col(id_col).alias("id"), F.col(source_col).alias("source"), words.alias("size"), *[F.col(f"`{c}`").alias(f"k_{c}") for c in keep])
    whole_rows = whole_rows.withColumn("u", u).withColumn("bin", F.shiftrightunsigned("u", 40).cast("int"))
    rows, _ = write_table(whole_rows.select("id", "source", "size", "u", "bin"), "mix-sizes")
    bins, _ = write_table(rows.groupBy("source", "bin").agg(F.sum("size").alias("n"), F.count(F.lit(1)).alias("rows")), "mix-bins")
    # One row per source: as long as the list of sources.
    per = sorted(bins.groupBy("source").agg(F.sum("n").alias("n")).collect(), key=lambda r: (r.source is None, (r.source or "").encode("utf-8")))
    total = sum(r.n for r in per)
    w = [weights[i % len(weights)] for i in range(len(per))]
    targets = water_fill([r.n for r in per], w, share * total, max_epochs)
    plan = []
    for r, t in zip(per, targets, strict=True):
        whole = min(int(t // r.n), int(max_epochs)) if r.n else 0
        plan.append((r.source, r.n, t, whole, max(0.0, t - whole * r.n)))
    plan = spark.createDataFrame(plan, "source string, source_size long, target double, whole int, rest double")
    plan = small_side(plan, len(per))
    running = F.sum("n").over(Window.partitionBy("source").orderBy("bin"))
    edges = bins.join(plan, bins.source.eqNullSafe(plan.source)).select(bins.source, "bin", "n", "rest")
    edges = edges.withColumn("upto", running)
    cut = edges.where((F.col("upto") > F.col("rest")) & (F.col("upto") - F.col("n") <= F.col("rest"))).select(F.col("source").alias("c_source"), F.col("bin").alias("cut"), (F.col("upto") - F.col("n")).alias("below"))
    # Inside the one bin of each source that crosses its fraction, rows are taken in order up to it.
    inside = rows.join(small_side(cut, len(per)), rows.source.eqNullSafe(F.col("c_source")) & (rows.bin == F.col("cut")))
    order = Window.partitionBy("source").orderBy("u", "id", "size")
    inside = inside.groupBy("source", "u", "id", "size", "below").agg((F.sum("size")).alias("all")).withColumn("upto", F.col("below") + F.sum("all").over(order))
    near = inside.join(small_side(plan.select(F.col("source").alias("p_source"), "rest"), len(per)), F.col("source").eqNullSafe(F.col("p_source")))
    last = near.where(F.col("upto") <= F.col("rest")).groupBy("source").agg(F.max(F.struct("u", "id")).alias("last"), F.max("upto").alias("got"))
    cut = cut.join(last, F.col("c_source").eqNullSafe(F.col("source")), "left").select("c_source", "cut", "last", F.coalesce("got", "below").alias("got"))
    known = plan.join(cut, F.col("source").eqNullSafe(F.col("c_source")), "left").select(F.col("source").alias("p_source"), "source_size", "target", "whole", "cut", "last", "rest", (F.col("rest") - F.col("got")).alias("gap"))
    known, _ = write_table(known, "mix-plan")
    first = (
        F.when(F.col("rest") <= 0, 0)
        .when(F.col("cut").isNull(), 1)
        .when(F.col("bin") < F.col("cut"), 1)
        .when((F.col("bin") == F.col("cut")) & F.col("last").isNotNull() & (F.struct("u", "id") <= F.col("last")), 1)
        .otherwise(0)
    )
    # A document per source and round: the one not yet taken whose size comes nearest to what is missing.
    closing = None
    for _ in range(CLOSING):
        left = rows.join(small_side(known, len(per)), rows.source.eqNullSafe(F.col("p_source"))).withColumn("once", first).where((F.col("once") == 0) & (F.col("gap") > 0))
        if closing is not None:
            taken = small_side(closing.select(F.col("f_source").alias("t_source"), F.col("fill.u").alias("t_u"), F.col("fill.id").alias("t_id")), CLOSING * len(per))
            left = left.join(taken, left.source.eqNullSafe(F.col("t_source")) & (left.u == F.col("t_u")) & left.id.eqNullSafe(F.col("t_id")), "left_anti")
        off = F.abs(F.col("size") - F.col("gap"))
        found = left.where(off < F.col("gap")).groupBy("p_source").agg(F.min(F.struct(off.alias("off"), "u", "id", "size")).alias("fill"))
        found, _ = write_table(found.select(F.col("p_source").alias("f_source"), "fill"), "mix-closing")
        if found.isEmpty():
            break
        known = known.join(small_side(found, len(per)), F.col("p_source").eqNullSafe(F.col("f_source")), "left")
        known, _ = write_table(known.withColumn("gap", F.col("gap") - F.coalesce("fill.size", F.lit(0))).drop("f_source", "fill"), "mix-plan")
        closing = found if closing is None else closing.unionByName(found)
    last_rows = whole_rows if keep else rows
    out = last_rows.join(small_side(known, len(per)), last_rows.source.eqNullSafe(F.col("p_source")))
    once = first
    if closing is not None:
        taken = small_side(closing.select(F.col("f_source").alias("t_source"), F.col("fill.u").alias("t_u"), F.col("fill.id").alias("t_id")), CLOSING * len(per))
        out = out.join(taken, out.source.eqNullSafe(F.col("t_source")) & (out.u == F.col("t_u")) & out.id.eqNullSafe(F.col("t_id")), "left")
        once = F.when(F.col("t_u").isNotNull(), 1).otherwise(first)
    repeats = F.least(F.col("whole") + once, F.lit(int(max_epochs)))
    return out.withColumn("repeats", repeats).select(F.col("id").alias(id_col), "size", "source_size", "target", "repeats", (F.col("size") * F.col("repeats")).alias("taken"), *[F.col(f"k_{c}").alias(c) for c in keep])
