"""Shards of near-equal size by best-fit-decreasing packing of indivisible groups.

Rows of equal text form a group and stay together. Groups in falling order of size enter the bin with
the least remaining capacity that still takes them; bins stand in a balanced tree by remaining capacity.
The capacity is the smallest, within a tolerance, at which the packing uses no more bins than asked.

Every group is packed, whatever their number. Groups of one size are interchangeable, so the driver works
on (size, number of groups): the bin that took one group of a size is still the tightest for the
next, and is filled with as many as it takes before the next bin is searched, which is what packing them
one by one does. Different sizes are few: n of them need at least n * n / 2 bytes of groups, and texts of
up to a megabyte allow a million whatever the number of rows. The result, runs of ranks per size, goes
back to the groups by a join on size, and groups of a size are ranked in cells of bounded size, so neither a
hot size nor a hot text is one task's.

Defined cases: null text has size 8 as an empty one; equal texts always share a shard, and a group
larger than the mean shard makes its shard that large; groups of one size are dealt by their hash (two
texts that share a 64-bit hash are one group);
repeated rows are rows of their own; rows without an id are numbered as they come; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from poolcurator.llm.store import attach_by_group, pick, write_table

#: Rows, or groups of one size, numbered by one task.
CELL_ROWS = 100_000


class RoomTree:
    """Keys in a treap, a search tree balanced by pseudo-random priorities: add a key, take the least key not below another."""

    def __init__(self):
        self.root, self._seed = None, 1

    def _split(self, node, key):
        """(keys below key, the others)."""
        if node is None:
            return None, None
        if node[0] < key:
            a, b = self._split(node[3], key)
            return (node[0], node[1], node[2], a), b
        a, b = self._split(node[2], key)
        return a, (node[0], node[1], b, node[3])

    def _merge(self, a, b):
        if a is None or b is None:
            return a or b
        if a[1] > b[1]:
            return (a[0], a[1], a[2], self._merge(a[3], b))
        return (b[0], b[1], self._merge(a, b[2]), b[3])

    def add(self, key) -> None:
        self._seed = self._seed * 6364136223846793005 + 1442695040888963407 & (1 << 64) - 1
        a, b = self._split(self.root, key)
        self.root = self._merge(self._merge(a, (key, self._seed >> 32, None, None)), b)

    def take(self, least):
        """Removes and returns the least key that is not below `least`; None if there is none."""
        a, b = self._split(self.root, least)
        found = b
        while found is not None and found[2] is not None:
            found = found[2]
        if found is None:
            self.root = a
            return None
        _, rest = self._split(b, (*found[0], 0))
        self.root = self._merge(a, rest)
        return found[0]


def best_fit(sizes: list[tuple[int, int]], capacity: int, most: int | None = None) -> list[tuple[int, int, int]] | None:
    """[(size, groups, bin)] for (size, number of groups) in falling order; a group above the capacity has a bin of its own.

    None as soon as more than `most` bins are needed.
    """
    tree, bins, out = RoomTree(), 0, []
    for size, number in sizes:
        while number:
            tightest = tree.take((size, -1))
            if tightest is None:
                room, at, bins = capacity, bins, bins + 1
                if most is not None and bins > most:
                    return None
                at = bins - 1
            else:
                room, at = tightest
            n = min(number, max(1, room // size))
            out.append((size, n, at))
            number -= n
            if room > n * size:
                tree.add((room - n * size, at))
    return out


def pack(sizes: dict[int, int], shards: int, tolerance: float = 2e-4) -> list[tuple[int, int, int]]:
    """[(size, groups, shard)] from the number of groups by size: best fit decreasing at the smallest capacity that needs no more than `shards` bins."""
    items = sorted(sizes.items(), reverse=True)
    if not items:
        return []
    total = sum(s * n for s, n in items)
    low = max(-(-total // shards), 1)
    step = max(1, int(low * tolerance))
    high = low + step
    best = best_fit(items, high, shards)
    while best is None:  # doubling above the mean: what a group of the largest size may overhang
        low, high = high, high + 2 * (high - low)
        best = best_fit(items, high, shards)
    while high - low > step:
        mid = (low + high) // 2
        got = best_fit(items, mid, shards)
        low, high, best = (low, mid, got) if got is not None else (mid, high, best)
    return best


def ranked_in_cells(df: DataFrame, by: str, number: str, spread, order: list[str], out: str) -> DataFrame:
    """df with `out`, a gapless number from 0 within `by`; `number` has the rows of each `by`, which are numbered in cells of about CELL_ROWS."""
    cells = F.ceil(F.col(number) / CELL_ROWS).cast("int")
    dealt = df.withColumn("_cell", F.pmod(spread, cells).cast("int"))
    sizes = dealt.groupBy(by, "_cell").agg(F.count(F.lit(1)).alias("_n"))  # rows / CELL_ROWS, and one row per `by`
    before = F.sum("_n").over(Window.partitionBy(by).orderBy("_cell")) - F.col("_n")
    offsets = sizes.where(F.col("_n") > 0).select(by, "_cell", before.alias("_before"))
    numbered = dealt.withColumn(out, F.row_number().over(Window.partitionBy(by, "_cell").orderBy(*order)) - 1)
    return numbered.join(offsets, [by, "_cell"]).withColumn(out, (F.col(out) + F.col("_before")).cast("long")).drop("_cell", "_before")


def shard(docs: DataFrame, shards: int = 24, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of docs: (id, size, text_crc32, shard, slot); slots are gapless from 0 in each shard."""
    spark: SparkSession = docs.sparkSession
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = pick(docs, id_col, text_col).select(
        F.col(id_col).alias("id"),
        F.monotonically_increasing_id().alias("n_row"),
        (F.octet_length(text) + F.lit(8)).cast("long").alias("size"),
        F.crc32(text.cast("binary")).alias("crc"),
        F.xxhash64(text).alias("h"),
    )
    rows, _ = write_table(rows, "sized")
    groups, _ = write_table(rows.groupBy("h").agg(F.sum("size").alias("bytes"), F.count(F.lit(1)).alias("n")), "groups")
    # One row per different size: see the module's text for the bound.
    by_size = groups.groupBy("bytes").agg(F.count(F.lit(1)).alias("groups"), F.sum("n").alias("rows"))
    sizes = {r.bytes: r.groups for r in by_size.select("bytes", "groups").collect()}
    runs: dict[int, list[tuple[int, int]]] = {}
    taken: dict[int, int] = {}
    for size, n, at in pack(sizes, shards):
        runs.setdefault(size, []).append((taken.get(size, 0), at))
        taken[size] = taken.get(size, 0) + n
    plan = spark.createDataFrame([(s, sizes[s], [x[0] for x in r], [x[1] for x in r]) for s, r in runs.items()], "bytes long, groups long, starts array<long>, at array<int>")
    n_groups = sum(sizes.values())
    planned = attach_by_group(groups, plan, ["bytes"], "groups", n_groups)
    placed = ranked_in_cells(planned, "bytes", "groups", F.col("h"), ["h"], "rank")
    run = F.size(F.filter("starts", lambda s: s <= F.col("rank")))
    placed, _ = write_table(placed.select("h", F.col("n").alias("g_rows"), F.element_at("at", run).alias("shard")), "placed")
    # One row per shard.
    counts = placed.groupBy("shard").agg(F.sum("g_rows").alias("rows"))
    total = counts.agg(F.coalesce(F.sum("rows"), F.lit(0))).first()[0]
    put = attach_by_group(rows, placed, ["h"], "g_rows", total).drop("g_rows").join(F.broadcast(counts), "shard")
    mixed = F.xxhash64(F.coalesce(F.col("id"), F.col("n_row")), "size", "crc")
    numbered = ranked_in_cells(put.select("id", "n_row", "size", "crc", "shard", "rows"), "shard", "rows", mixed, ["id", "size", "crc", "n_row"], "slot")
    return numbered.select(F.col("id").alias(id_col), "size", F.col("crc").alias("text_crc32"), "shard", "slot")
