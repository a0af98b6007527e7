"""Test items inside long documents by size-partitioned MinHash containment search.

Items are sets of 5-word shingles (an item of fewer words is one shingle of its length). Shingles of a
document that no item has can't add to a containment, so a document is reduced, exactly, to its
shingles that some item has. Reduced documents are partitioned by size; for a partition with upper
size u and items of at least q shingles, containment c asks for a Jaccard similarity of c*q/(u+(1-c)*q)
at least, which sets the rows per band: as many as keep the chance of a miss under `miss`. Where
even single rows can't (a document full of test items), its candidates are all items that share a
shingle. Every candidate is verified by exact shingle containment.

The items are cut into blocks of bounded size; each block is shared with all tasks and passes over
all documents once, so no document is shuffled and a passage that everyone shares costs nothing extra.

Defined cases: null counts as empty; texts and items without words match nothing; items that repeat
an id are searched one by one and the best containment is kept (ties: the larger item); an item without
an id is one of its own, and its rows have a null item id; repeated document rows give repeated
results; empty tables give an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from poolcurator.llm import wordhash as wh
from poolcurator.llm.store import pick, write_table

WORDS = 5
CONTAINMENT = 0.8
HASHES = 128
ROWS = (8, 4, 2, 1)
#: Characters of items in a block, which bounds what is shared with the tasks.
BLOCK_CHARS = 8_000_000
_U = wh.U


def jaccard_floor(containment: float, q: int, u: int) -> float:
    """Least Jaccard similarity of an item of q shingles, contained to the given share, with a set of at most u."""
    return containment * q / (u + (1 - containment) * q)


def band_rows(containment: float, q: int, u: int, miss: float = 1e-4, hashes: int = HASHES) -> int:
    """Rows per band for a partition; 0 where banding can't keep the chance of a miss under `miss`."""
    j = min(1.0, jaccard_floor(containment, q, u))
    for r in ROWS:
        if (1 - j**r) ** (hashes // r) <= miss:
            return r
    return 0


def signature(items: np.ndarray, hashes: int = HASHES) -> np.ndarray:
    seeds = np.arange(1, hashes + 1, dtype=_U) * _U(0x9E3779B97F4A7C15)
    return wh.mix(items[None] ^ wh.mix(seeds)[:, None]).min(axis=1)


def bands(sign: np.ndarray, rows: int) -> np.ndarray:
    key = np.zeros(len(sign) // rows, dtype=_U)
    for part in sign.reshape(-1, rows).T:
        key = wh.mix(key * _U(0x9E3779B97F4A7C15) + part)
    return wh.mix(key + np.arange(1, len(key) + 1, dtype=_U) + _U(rows << 32))


@dataclass
class ItemBlock:
    """Index of one block of items."""

    ids: list
    sets: list[np.ndarray]  # positions in vocabulary
    vocabulary: np.ndarray  # sorted shingle hashes
    lengths: tuple[int, ...]  # words per shingle that occur
    classes: dict[int, list[int]]  # log2 of an item's size -> items
    tables: dict[tuple[int, int], dict[int, list[int]]]  # (size class, rows) -> band -> items
    holders: dict[int, list[int]]  # shingle -> items


def index_items(ids: list, texts: list[str], k: int = WORDS) -> ItemBlock:
    raw, off = wh.utf8(pa.array([t or "" for t in texts], pa.string()))
    word, row, _ = wh.words(raw, off)
    count = np.bincount(row, minlength=len(ids))
    length = np.minimum(count, k)
    held: list[np.ndarray] = [np.zeros(0, _U)] * len(ids)
    lengths = tuple(int(x) for x in np.unique(length[length > 0]))
    for n in lengths:
        h, r, _ = wh.shingles(word, row, len(ids), n)
        for i in np.flatnonzero(length == n):
            held[i] = np.unique(h[r == i])
    vocabulary = np.unique(np.concatenate(held)) if held else np.zeros(0, _U)
    sets = [np.searchsorted(vocabulary, x) for x in held]
    classes, tables, holders = defaultdict(list), {}, defaultdict(list)
    for i, s in enumerate(sets):
        for x in s:
            holders[int(x)].append(i)
        if len(s):
            classes[int(len(s)).bit_length() - 1].append(i)
    for c, members in classes.items():
        signs = {i: signature(vocabulary[sets[i]]) for i in members}
        for r in ROWS:
            table = tables[c, r] = defaultdict(list)
            for i, sign in signs.items():
                for key in bands(sign, r):
                    table[int(key)].append(i)
    return ItemBlock(ids, sets, vocabulary, lengths, dict(classes), tables, dict(holders))


def matches(block: ItemBlock, hits: np.ndarray, containment: float) -> list[tuple[int, int]]:
    """(item, shared shingles) of the items contained in a reduced document, given as sorted positions in the vocabulary."""
    u = 1 << int(len(hits)).bit_length()  # upper size of the document's partition
    candidates: set[int] = set()
    sign = None
    for c in block.classes:
        if len(hits) < containment * (1 << c):
            continue  # too few shingles for the smallest item of the class
        r = band_rows(containment, 1 << c, u)
        if not r:
            for x in hits:
                candidates.update(block.holders[int(x)])
            continue
        if sign is None:
            sign = signature(block.vocabulary[hits])
        table = block.tables[c, r]
        for key in bands(sign, r).tolist():
            if key in table:
                candidates.update(table[key])
    found = []
    for i in sorted(candidates):
        at = np.searchsorted(hits, block.sets[i])
        at[at == len(hits)] = 0
        shared = int((hits[at] == block.sets[i]).sum())
        if shared >= containment * len(block.sets[i]) - 1e-9:
            found.append((i, shared))
    return found


def best_of_each(block: ItemBlock, found: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Of matches whose items share an id the one with the best containment; items without an id stay apart."""
    best: dict[object, tuple[int, int]] = {}
    for i, shared in found:
        name = ("id", block.ids[i]) if block.ids[i] is not None else ("row", i)
        have = best.get(name)
        if have is None or (shared / len(block.sets[i]), shared) > (have[1] / len(block.sets[have[0]]), have[1]):
            best[name] = (i, shared)
    return list(best.values())


def _search(shared, containment: float, k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block: ItemBlock = shared.value
        seen = np.zeros(1 << 22, dtype=bool)
        seen[block.vocabulary >> _U(42)] = True
        memo: dict[bytes, list[tuple[int, int]]] = {}
        for batch in batches:
            for part in wh.slices(batch, "text"):
                raw, off = wh.utf8(part.column("text"))
                n = part.num_rows
                word, row, _ = wh.words(raw, off)
                keys = []
                for length in block.lengths:
                    h, r, _ = wh.shingles(word, row, n, length)
                    maybe = seen[h >> _U(42)]
                    h, r = h[maybe], r[maybe]
                    at = np.searchsorted(block.vocabulary, h)
                    at[at == len(block.vocabulary)] = 0
                    hit = block.vocabulary[at] == h if len(block.vocabulary) else np.zeros(len(h), bool)
                    keys.append(r[hit] * max(1, len(block.vocabulary)) + at[hit])
                pair = np.unique(np.concatenate(keys)) if keys else np.zeros(0, np.int64)
                if not len(pair):
                    continue
                r, at = pair // len(block.vocabulary), pair % len(block.vocabulary)
                cuts = np.append(np.flatnonzero(np.append(True, r[1:] != r[:-1])), len(r))
                out: list[tuple[int, int, int]] = []
                for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
                    hits = at[lo:hi]
                    name = hits.tobytes()
                    if name not in memo:
                        if len(memo) > 10_000:
                            memo.clear()
                        memo[name] = matches(block, hits, containment)
                    out += [(int(r[lo]), i, s) for i, s in best_of_each(block, memo[name])]
                if out:
                    rows, items, counts = zip(*out, strict=True)
                    sizes = np.array([len(block.sets[i]) for i in items], dtype=np.int64)
                    counts = np.array(counts, dtype=np.int64)
                    yield pa.RecordBatch.from_arrays(
                        [part.column("id").take(pa.array(rows)), pa.array([block.ids[i] for i in items], pa.int64()), pa.array(sizes), pa.array(counts), pa.array(counts / sizes)],
                        names=["id", "item_id", "item_shingles", "shared", "containment"],
                    )

    return run


def find_items(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_id: str = "item_id", item_text: str = "text", containment: float = CONTAINMENT, k: int = WORDS, block_chars: int = BLOCK_CHARS) -> DataFrame:
    """(id, item_id, item_shingles, shared, containment) for every document and item that it contains to the given share."""
    spark = docs.sparkSession
    rows = pick(docs, id_col, text_col).select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    wanted = pick(items, item_id, item_text).select(F.col(item_id).cast("long").alias("item"), F.coalesce(F.col(item_text), F.lit("")).alias("text"))
    chars = wanted.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    blocks = max(1, -(-chars // block_chars))
    found = None
    for b in range(blocks):
        # Texts of one id share a block, so that the best of them is known.
        spread = F.when(F.col("item").isNull(), F.xxhash64("text")).otherwise(F.xxhash64("item"))
        mine = wanted if blocks == 1 else wanted.where(F.pmod(spread, F.lit(blocks)) == b)
        got = sorted(((r.item, r.text) for r in mine.collect()), key=lambda x: (x[0] is None, x[0] or 0, x[1]))  # one block: about block_chars
        shared = spark.sparkContext.broadcast(index_items([i for i, _ in got], [t for _, t in got], k))
        part = rows.mapInArrow(_search(shared, containment, k), "id long, item_id long, item_shingles long, shared long, containment double")
        found = part if found is None else found.unionByName(part)
    return found.select(F.col("id").alias(id_col), "item_id", "item_shingles", "shared", "containment")


def decontaminate(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", **options) -> DataFrame:
    """docs without the documents that contain an item."""
    hits, _ = write_table(find_items(docs, items, id_col, **options).select(F.col(id_col).alias("_hit")).distinct(), "contaminated")
    return docs.join(hits, docs[id_col] == F.col("_hit"), "left_anti")
