"""Near duplicates by probability MinHash, banding and exact verification.

A document is the set of its 5-word shingles, weighted 1 + ln(count). Each shingle sends a Poisson
process of arrivals whose rate is its weight; every arrival falls into a random one of the sketch's
slots and a slot keeps the shingle that arrived first. A shingle stops once its next arrival is later
than all slots' first ones, so the work barely depends on the sketch's length. Two documents agree in
a slot with the probability Jaccard similarity of their weights. Documents with the same word
sequence are one representative; representatives that agree in a whole band of slots are candidates.
Texts that repeat a shingle have a second sketch with all weights 1, whose slots agree with the plain
Jaccard similarity, so that either similarity finds its pairs with the chance of the bands.

All candidates are verified exactly, without a row for every pair: components of the candidate graph
go to tasks that hold all members (large components: all pairs of blocks of members) and compare the
shingle sets by matrix products. A link is a similarity of 0.8 or more, by plain Jaccard or by
probability Jaccard under the weights. Tasks return only a spanning forest of the links; classes are
the components of the links.

Defined cases: null counts as empty; texts without words are near only to identical texts (white
space counts); fewer than five words make one shingle; repeated rows and rows that repeat an id are
members of one class; rows without an id are classes of their own and stay; the smallest id names the
class; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from poolcurator.llm import wordhash as wh
from poolcurator.llm.components import connected_components
from poolcurator.llm.store import attach_by_group, drop_path, pick, small_side, write_table

WORDS = 5
SIMILARITY = 0.8
BANDS, BAND_ROWS = 32, 6
#: Members and words of a block; a component with more of either is compared block by block.
BLOCK_DOCS, BLOCK_WORDS = 1_000, 400_000
_U = wh.U


def weighted_shingles(word: np.ndarray, row: np.ndarray, rows: int, k: int = WORDS) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, 44-bit shingle, count), each shingle once per row, in order."""
    h, r, _ = wh.shingles(word, row, rows, k)
    if rows >= 1 << 20:
        raise ValueError("too many rows at once")
    key = np.sort((r.astype(_U) << _U(44)) | (h >> _U(20)))
    new = np.append(True, key[1:] != key[:-1]) if len(key) else np.zeros(0, bool)
    at = np.flatnonzero(new)
    count = np.diff(np.append(at, len(key)))
    key = key[new]
    return (key >> _U(44)).astype(np.int64), key & _U((1 << 44) - 1), count


def sketch(row: np.ndarray, item: np.ndarray, weight: np.ndarray, rows: int, slots: int) -> np.ndarray:
    """For every row and slot the item that arrives first; 0 for rows without items."""
    first = np.full(rows * slots, np.inf)
    owner = np.zeros(rows * slots, dtype=_U)
    live = np.arange(len(item))
    t0 = np.zeros(len(item))
    done = 0  # arrivals of each live item so far
    while len(live):
        steps = int(np.clip(60_000 // len(live), 1, 64))
        seeds = wh.mix(item[live][:, None] * _U(0x9E3779B97F4A7C15) + np.arange(done + 1, done + steps + 1, dtype=_U)[None] * _U(0xD1342543DE82EF95))
        wait = -np.log(((seeds >> _U(24)).astype(np.float64) + 0.5) * 2.0**-40) / weight[live][:, None]
        wait[:, 0] += t0[live]
        t = np.cumsum(wait, axis=1)
        slot = ((seeds & _U(0xFFFFFF)) * _U(slots) >> _U(24)).astype(np.int64)
        cell = (row[live][:, None] * slots + slot).ravel()
        flat = t.ravel()
        better = flat < first[cell]
        cell, when, who = cell[better], flat[better], np.repeat(item[live], steps)[better]
        np.minimum.at(first, cell, when)
        won = first[cell] == when
        owner[cell[won]] = who[won]
        t0[live] = t[:, -1]
        used = np.unique(row[live])
        limit = np.zeros(rows)
        limit[used] = first.reshape(rows, slots)[used].max(axis=1)
        live = live[t0[live] < limit[row[live]]]
        done += steps
    return owner.reshape(rows, slots)


def band_keys(owner: np.ndarray, bands: int, band_rows: int) -> np.ndarray:
    key = np.zeros((len(owner), bands), dtype=_U)
    parts = owner.reshape(len(owner), bands, band_rows)
    for j in range(band_rows):
        key = wh.mix(key * _U(0x9E3779B97F4A7C15) + parts[:, :, j])
    return wh.mix(key + np.arange(1, bands + 1, dtype=_U)[None])


def _sketches(bands: int, band_rows: int, k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in wh.slices(batch, "text", 1 << 20):
                n = part.num_rows
                raw, off = wh.utf8(part.column("text"))
                word, row, _ = wh.words(raw, off)
                k1, k2 = wh.row_keys(word, row, n)
                count = np.bincount(row, minlength=n)
                for i in np.flatnonzero(count == 0):
                    d = hashlib.blake2b(raw[off[i] : off[i + 1]].tobytes(), digest_size=16).digest()
                    k1[i], k2[i] = np.frombuffer(d, dtype=np.uint64)
                r, item, c = weighted_shingles(word, row, n, k)
                keys = band_keys(sketch(r, item, 1 + np.log(c), n, bands * band_rows), bands, band_rows)
                # Rows that repeat a shingle are sketched again with all weights 1; for the others both sketches are the same.
                again = np.unique(r[c > 1])
                mine = np.isin(r, again)
                flat = band_keys(sketch(np.searchsorted(again, r[mine]), item[mine], np.ones(int(mine.sum())), len(again), bands * band_rows), bands, band_rows)
                owner = np.concatenate([np.repeat(np.flatnonzero(count > 0), bands), np.repeat(again, bands)])
                order = np.argsort(owner, kind="stable")
                values = np.concatenate([keys[count > 0].ravel(), flat.ravel()])[order]
                lists = pa.ListArray.from_arrays(pa.array(np.append(0, np.cumsum(np.bincount(owner, minlength=n))).astype(np.int32)), pa.array(values.view(np.int64)))
                yield pa.RecordBatch.from_arrays([part.column("id"), pa.array(k1.view(np.int64)), pa.array(k2.view(np.int64)), pa.array(count.astype(np.int64)), lists], names=["id", "k1", "k2", "words", "bands"])

    return run


def probability_jaccard(a: np.ndarray, x: np.ndarray, b: np.ndarray, y: np.ndarray) -> float:
    """Exact probability Jaccard of two sorted item lists with weights."""
    items, inv = np.unique(np.concatenate([a, b]), return_inverse=True)
    wx, wy = np.bincount(inv[: len(a)], x, len(items)), np.bincount(inv[len(a) :], y, len(items))
    with np.errstate(divide="ignore"):
        ratio = np.where(wy > 0, wx / np.where(wy > 0, wy, 1), np.inf)
    order = np.argsort(-ratio, kind="stable")
    wx, wy, ratio = wx[order], wy[order], ratio[order]
    upto = np.searchsorted(-ratio, -ratio, "right")  # items whose ratio is no smaller
    sx, sy = np.append(0, np.cumsum(wx)), np.append(0, np.cumsum(wy))
    both = (wx > 0) & (wy > 0)
    total = sx[upto[both]] / wx[both] + (sy[-1] - sy[upto[both]]) / wy[both]
    return float((1 / total).sum())


def linked_pairs(row: np.ndarray, item: np.ndarray, weight: np.ndarray, rows: int, similarity: float, split: int = 0) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Row pairs whose similarity is at least the given one, in chunks; split > 0: only pairs of a row below with one from it on."""
    size = np.bincount(row, minlength=rows)
    mass = np.bincount(row, weight, minlength=rows)
    flat = np.bincount(row, weight, minlength=rows) == size  # all weights are 1: both similarities agree
    _, column, df = np.unique(item, return_inverse=True, return_counts=True)
    shared = df[column] > 1  # items of one row add to no intersection
    r, c, w = row[shared], column[shared], weight[shared]
    if not len(r):
        return
    _, c = np.unique(c, return_inverse=True)
    width = int(c.max()) + 1
    order = np.argsort(c, kind="stable")
    r, c, w = r[order], c[order], w[order]
    step = max(1, min(width, 8_000_000 // rows))
    left = slice(0, split or rows)
    right = slice(split, rows)
    common = np.zeros((len(range(*left.indices(rows))), len(range(*right.indices(rows)))), dtype=np.float32)
    part_a = None if flat.all() else np.zeros_like(common)  # weight of the shared items in the left row
    for lo in range(0, width, step):
        a, b = np.searchsorted(c, [lo, lo + step])
        has = np.zeros((rows, step), dtype=np.float32)
        has[r[a:b], c[a:b] - lo] = 1
        common += has[left] @ has[right].T
        if part_a is not None:
            weights = np.zeros((rows, step), dtype=np.float32)
            weights[r[a:b], c[a:b] - lo] = w[a:b]
            part_a += weights[left] @ has[right].T
    na, nb = size[left].astype(np.float32)[:, None], size[right].astype(np.float32)[None]
    jaccard = common / np.maximum(na + nb - common, 1)
    ok = jaccard >= similarity - 1e-6
    if not split:
        ok &= np.triu(np.ones((rows, rows), dtype=bool), 1)
    i, j = np.nonzero(ok)
    yield i, j + (split or 0)
    if part_a is not None:
        # the shared weight's share bounds the probability Jaccard from above
        maybe = (part_a >= (similarity - 1e-4) * mass[left].astype(np.float32)[:, None]) & ~ok & ~(flat[left][:, None] & flat[right][None])
        if not split:
            maybe &= np.triu(np.ones((rows, rows), dtype=bool), 1)
        begin = np.searchsorted(row, np.arange(rows + 1))
        found = []
        for i, j in zip(*np.nonzero(maybe), strict=True):
            p, q = slice(begin[i], begin[i + 1]), slice(begin[j + split], begin[j + split + 1])
            if probability_jaccard(item[p], weight[p], item[q], weight[q]) >= similarity:
                found.append((i, j + split))
        if found:
            yield tuple(np.array(x) for x in zip(*found, strict=True))


def forest(pairs: Iterator[tuple[np.ndarray, np.ndarray]], rows: int) -> np.ndarray:
    """The least row of every row's component."""
    root = np.arange(rows)
    for i, j in pairs:
        while len(i):
            a, b = root[i], root[j]
            differ = a != b
            i, j, a, b = i[differ], j[differ], a[differ], b[differ]
            np.minimum.at(root, np.maximum(a, b), np.minimum(a, b))
            while True:
                up = root[root]
                if (up == root).all():
                    break
                root = up
    return root


def _verify(similarity: float, k: int):
    def unit(table: pa.Table) -> pa.RecordBatch:
        side = np.asarray(table.column("side"))
        table = table.take(pa.array(np.argsort(side, kind="stable")))
        ids, side = np.asarray(table.column("id")), np.asarray(table.column("side"))
        n, split = len(ids), int((side == 0).sum())
        split = split if 0 < split < n else 0
        rows, items, weights, base = [], [], [], 0
        for part in wh.slices(table.select(["text"]).combine_chunks().to_batches()[0], "text"):
            raw, off = wh.utf8(part.column("text"))
            word, row, _ = wh.words(raw, off)
            r, item, c = weighted_shingles(word, row, part.num_rows, k)
            rows.append(r + base)
            items.append(item)
            weights.append(1 + np.log(c))
            base += part.num_rows
        row, item, weight = np.concatenate(rows), np.concatenate(items), np.concatenate(weights)
        root = forest(linked_pairs(row, item, weight, n, similarity, split), n)
        moved = root != np.arange(n)
        return pa.RecordBatch.from_arrays([pa.array(ids[moved]), pa.array(ids[root[moved]])], names=["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        now = None
        for batch in batches:  # sorted by unit, so a unit's rows follow each other
            u = np.asarray(batch.column("unit"))
            cuts = np.append(np.flatnonzero(u[1:] != u[:-1]) + 1, len(u))
            lo = 0
            for hi in cuts:
                if now is not None and u[lo] != now:
                    yield unit(pa.Table.from_batches(held))
                    held = []
                now = u[lo]
                held.append(batch.slice(lo, hi - lo))
                lo = hi
        if held:
            yield unit(pa.Table.from_batches(held))

    return run


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", similarity: float = SIMILARITY, k: int = WORDS, bands: int = BANDS, band_rows: int = BAND_ROWS, block_docs: int = BLOCK_DOCS, block_words: int = BLOCK_WORDS) -> DataFrame:
    """One row per row of docs: (id, class_id, class_size, rep_id, kept)."""
    spark = docs.sparkSession
    rows = pick(docs, id_col, text_col).select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text")).where("id is not null")
    signed, signed_path = write_table(rows.mapInArrow(_sketches(bands, band_rows, k), "id long, k1 long, k2 long, words long, bands array<long>"), "sketches")
    reps, reps_path = write_table(signed.groupBy("k1", "k2").agg(F.min("id").alias("rep"), F.count(F.lit(1)).alias("n")), "representatives")
    total = reps.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    # The band keys of one row of each representative (an id may be repeated).
    first = signed.where("words > 0").join(reps.select(F.col("k1").alias("r1"), F.col("k2").alias("r2"), "rep"), (F.col("id") == F.col("rep")) & (F.col("k1") == F.col("r1")) & (F.col("k2") == F.col("r2")))
    keyed = first.select("rep", "words", F.explode(F.array_distinct("bands")).alias("key"))
    shared, shared_path = write_table(keyed.groupBy("key").agg(F.min("rep").alias("lead"), F.max("rep").alias("last")).where("lead <> last").select("key", "lead"), "buckets")
    stars = keyed.join(small_side(shared, shared.count()), "key").where("rep <> lead").select(F.col("rep").alias("a"), F.col("lead").alias("b")).distinct()
    groups, groups_path = connected_components(stars)
    sizes = signed.groupBy("id").agg(F.max("words").alias("words"))
    members, members_path = write_table(groups.join(sizes, F.col("node") == F.col("id")).select(F.col("node").alias("id"), "root", "words"), "members")
    per = members.groupBy("root").agg(F.count(F.lit(1)).alias("n"), F.sum("words").alias("w"))
    per = per.select("root", F.greatest(F.ceil(F.col("n") / block_docs), F.ceil(F.col("w") / block_words)).cast("int").alias("blocks"))
    placed = members.join(per, "root").withColumn("block", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int"))
    # A block meets itself and every other block once; side 0 is the lower block.
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other")
    units = placed.select("id", "root", "blocks", "block", other).select(
        "id",
        F.when(F.col("blocks") == 1, F.xxhash64("root")).otherwise(F.xxhash64("root", F.least("block", "other"), F.greatest("block", "other"))).alias("unit"),
        F.when(F.col("block") <= F.col("other"), 0).otherwise(1).alias("side"),
    )
    units, units_path = write_table(units, "units")
    texts = rows.join(small_side(units, units.count()), "id")
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    checked = texts.repartition(max(parts, 24), "unit").sortWithinPartitions("unit", "id").mapInArrow(_verify(similarity, k), "a long, b long")
    links, links_path = write_table(checked, "links")
    classes, _ = connected_components(links)
    of_rep = reps.join(classes, F.col("rep") == F.col("node"), "left").select("k1", "k2", "rep", "n", F.coalesce("root", "rep").alias("class_id"))
    counts = of_rep.groupBy("class_id").agg(F.sum("n").alias("class_size"))
    of_rep, _ = write_table(of_rep.join(counts, "class_id"), "classes")
    for path in (groups_path, members_path, units_path, shared_path, links_path, reps_path):
        drop_path(spark, path)
    out = attach_by_group(signed.select("id", "k1", "k2"), of_rep, ["k1", "k2"], "n", total)
    out = out.select(F.col("id").alias(id_col), "class_id", "class_size", F.col("rep").alias("rep_id"), (F.col("id") == F.col("class_id")).alias("kept"))
    none = F.lit(None).cast(dict(out.dtypes)["class_id"])
    nameless = pick(docs, id_col).where(F.col(id_col).isNull()).select(id_col, none.alias("class_id"), F.lit(1).cast("long").alias("class_size"), none.alias("rep_id"), F.lit(True).alias("kept"))
    return out.unionByName(nameless)
