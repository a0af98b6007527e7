"""Perplexity filter: an interpolated modified Kneser-Ney model of whole bytes over one of byte classes.

The outer model counts runs of five UTF-8 bytes as they are, so its tables grow with the trusted text; they
stay tables of the shared folder, dealt out by the hash of gram or context. Below its shortest run lies a
model of 64 byte classes, order 4, whose tables are bounded and which the tasks hold as a dense array.
Continuation counts of the lower orders, context totals and discounts come from the count tables by joins on
the context.

Scoring copies the texts to the shared folder in blocks and lists each block's different runs once. The
different runs of all blocks get their probabilities by joins in which a key has at most 256 rows, and go back
to their blocks as one file each; tasks add up the information of every position of every whole text. Before
every word but a text's first the model emits a flag that tells whether the word repeats the one before it, at
the rate of the trusted texts: runs of bytes are too short to notice that a text stutters. A document's
perplexity is per byte, drawn a little towards the mean of the trusted documents for short texts; documents
above a high quantile of trusted documents of their language are dropped. Texts that the model has counted
look better than new ones of their kind, so one in `HELD_OUT` trusted documents is left out of the counts, and
the quantile is that of those.

Defined cases: null and empty texts have the mean perplexity and stay; a language with few trusted documents
uses the higher of its own and the overall quantile, one with none, or null, the overall; repeated rows are
rows of their own; with too few trusted documents to hold any out, the quantile is that of the counted ones;
without trusted documents the model is trained on all texts; an empty table gives an empty result; other
columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.dataset
from pyarrow import fs
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from poolcurator.llm import wordhash as wh
from poolcurator.llm.store import drop_path, new_path, pick, small_side, write_table

ORDER, BITS = 4, 6
#: The outer model's symbols are bytes.
BYTE_ORDER, BYTE_BITS = 5, 8
#: Bytes of texts and different runs of a block.
BLOCK_BYTES, BLOCK_GRAMS = 1 << 26, 1 << 21
HELD_OUT = 8
QUANTILE = 0.995
#: Symbols of the model's mean that every text is taken to have besides its own.
PRIOR_SYMBOLS = 64
LEAST_TRUSTED = 20


def _classes() -> np.ndarray:
    """Class of every byte; 0 is the start of a text."""
    c = np.zeros(256, dtype=np.int64)
    c[:] = 45  # control bytes
    c[0x21:0x7F] = 44  # further punctuation
    c[0x61:0x7B] = np.arange(1, 27)
    c[0x41:0x5B] = 27
    c[0x30:0x3A] = 28
    c[0x20], c[0x0A] = 29, 30
    c[[0x09, 0x0B, 0x0C, 0x0D]] = 31
    for i, x in enumerate(b".,;:!?'\"()-/"):
        c[x] = 32 + i
    c[0x80:0xC0] = 46 + (np.arange(0x80, 0xC0) & 15)
    c[0xC0:] = 63
    c[0xC3] = 62
    return c


_CLASS = _classes()
_BYTE = np.arange(256, dtype=np.int64)


def grams(raw: np.ndarray, off: np.ndarray, order: int = ORDER, bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    """The gram that ends at every byte, and the byte's row; a text starts after order - 1 start symbols."""
    pad = order - 1
    row = np.repeat(np.arange(len(off) - 1), np.diff(off))
    at = np.arange(len(raw)) + pad * (row + 1)
    line = np.zeros(len(raw) + pad * len(off) + pad, dtype=np.int64)
    line[at] = (_CLASS if bits == BITS else _BYTE)[raw]
    code = np.zeros(len(raw), dtype=np.int64)
    for j in range(pad, -1, -1):
        code = code << bits | line[at - j]
    return code, row


def _count(order: int, bits: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []
        for batch in batches:
            for part in wh.slices(batch, "text"):
                code, _ = grams(*wh.utf8(part.column("text")), order, bits)
                held.append(np.unique(code, return_counts=True))
                if len(held) == 8:
                    held = [_added(held)]
                    if len(held[0][0]) > BLOCK_GRAMS:
                        yield pa.RecordBatch.from_arrays([pa.array(x) for x in held.pop()], names=["gram", "n"])
        if held:
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in _added(held)], names=["gram", "n"])

    return run


def _added(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    code, inv = np.unique(np.concatenate([c for c, _ in parts]), return_inverse=True)
    return code, np.bincount(inv, np.concatenate([n for _, n in parts])).astype(np.int64)


def count_grams(texts: DataFrame, order: int = ORDER, bits: int = BITS) -> DataFrame:
    """(gram, n) over all rows of a column `text`."""
    return texts.select(F.coalesce("text", F.lit("")).alias("text")).mapInArrow(_count(order, bits), "gram long, n long").groupBy("gram").agg(F.sum("n").alias("n"))


def repeats(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Per row the words that repeat the word before, and the other words that have one before."""
    word, row, _ = wh.words(raw, off)
    follows = row[1:] == row[:-1]
    same = follows & (word[1:] == word[:-1])
    n = len(off) - 1
    again = np.bincount(row[1:][same], minlength=n) if len(word) else np.zeros(n, np.int64)
    return again, (np.bincount(row[1:][follows], minlength=n) if len(word) else np.zeros(n, np.int64)) - again


def repeat_rate(texts: DataFrame) -> float:
    """Share of words that repeat the word before, over all rows of a column `text`; add-one smoothed."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(2, dtype=np.int64)
        for batch in batches:
            for part in wh.slices(batch, "text"):
                total += [x.sum() for x in repeats(*wh.utf8(part.column("text")))]
        yield pa.RecordBatch.from_arrays([pa.array(total[:1]), pa.array(total[1:])], names=["again", "other"])

    counted = texts.select(F.coalesce("text", F.lit("")).alias("text")).mapInArrow(run, "again long, other long")
    again, other = counted.agg(F.coalesce(F.sum("again"), F.lit(0)), F.coalesce(F.sum("other"), F.lit(0))).first()
    return (again + 1) / (again + other + 2)


def smoothed(counts: DataFrame, order: int = ORDER, bits: int = BITS) -> tuple[list[DataFrame], list[DataFrame]]:
    """Per order from 1: (gram, p, rest) of the seen grams, and (context, back) mass left for the order below.

    A gram's probability is p + rest times what lies below order 1. Orders below the highest count in
    how many different contexts a gram was seen one symbol longer.
    """
    levels = {order: counts}
    for k in range(order - 1, 0, -1):
        keep = (1 << bits * k) - 1
        levels[k] = levels[k + 1].groupBy(F.col("gram").bitwiseAND(F.lit(keep)).alias("gram")).agg(F.count(F.lit(1)).alias("n"))
    probs, backs = [], []
    for k in range(1, order + 1):
        level = levels[k].withColumn("context", F.shiftright("gram", bits))
        # Discounts from the counts of counts; one row.
        c = level.agg(*[F.count_if(F.col("n") == i).cast("double").alias(f"n{i}") for i in (1, 2, 3, 4)]).first()
        n1, n2, n3, n4 = (max(x or 0, 1.0) for x in c)
        y = n1 / (n1 + 2 * n2)
        d = [min(max(i - (i + 1) * y * b / a, 0.05), i - 0.05) for i, a, b in ((1, n1, n2), (2, n2, n3), (3, n3, n4))]
        discount = F.when(F.col("n") == 1, d[0]).when(F.col("n") == 2, d[1]).otherwise(d[2])
        contexts = level.groupBy("context").agg(F.sum("n").alias("total"), F.sum(discount).alias("mass")).select("context", "total", (F.col("mass") / F.col("total")).alias("back"))
        own = level.join(contexts, "context").select("gram", "back", ((F.col("n") - discount) / F.col("total")).alias("own"))
        if k == 1:
            p = own.select("gram", F.col("own").alias("p"), F.col("back").alias("rest"))
        else:
            lower = probs[-1].select(F.col("gram").alias("short"), F.col("p").alias("lower"), F.col("rest").alias("below"))
            p = own.withColumn("short", F.col("gram").bitwiseAND(F.lit((1 << bits * (k - 1)) - 1))).join(lower, "short").select("gram", (F.col("own") + F.col("back") * F.col("lower")).alias("p"), (F.col("back") * F.col("below")).alias("rest"))
        probs.append(write_table(p, f"kn-{k}")[0])
        backs.append(write_table(contexts.select("context", "back"), f"kn-back-{k}")[0])
    return probs, backs


@dataclass
class Model:
    """Seen probabilities and back-off mass per order, and the mean information per symbol of the training text."""

    probs: list[tuple[np.ndarray, np.ndarray]]
    backs: list[tuple[np.ndarray, np.ndarray]]
    mean: float

    def dense(self) -> np.ndarray:
        """Information of every possible 4-gram's last symbol."""
        p = np.full(1, 1.0 / (1 << BITS))
        for (gram, own), (context, mass) in zip(self.probs, self.backs, strict=True):
            k = int(len(p)).bit_length() - 1  # bits of the order below
            back = np.ones(1 << k if len(p) > 1 else 1)
            back[context] = mass
            # p(w | shorter context), for every context: the longest symbol varies slowest
            lower = np.tile(p, 1 << BITS) if len(p) > 1 else np.repeat(p, 1 << BITS)
            p = lower * np.repeat(back, 1 << BITS)
            p[gram] = own
        return -np.log(p).astype(np.float32)


def train(texts: DataFrame) -> Model:
    """A model of all rows of a column `text`."""
    counts, _ = write_table(count_grams(texts), "grams")
    probs, backs = smoothed(counts)
    probs = [p.select("gram", (F.col("p") + F.col("rest") / (1 << BITS)).alias("p")) for p in probs]

    def local(df: DataFrame, a: str, b: str) -> tuple[np.ndarray, np.ndarray]:
        got = df.select(a, b).toArrow()  # at most 64**4 rows
        return np.asarray(got[a]), np.asarray(got[b])

    mean = counts.join(probs[-1], "gram").agg(F.sum(-F.col("n") * F.log("p")) / F.sum("n")).first()[0]
    return Model([local(p, "gram", "p") for p in probs], [local(b, "context", "back") for b in backs], float(mean or np.log(1 << BITS)))


def perplexity(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = (), prior: float = PRIOR_SYMBOLS) -> DataFrame:
    """(id, *keep, symbols, perplexity) for every row of docs."""
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(model)
    rows = docs.select(F.col(f"`{id_col}`").alias("_id"), *[F.col(f"`{c}`").alias(f"k_{c}") for c in keep], F.col(f"`{text_col}`").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        information = None
        for batch in batches:
            for part in wh.slices(batch, "text"):
                if information is None:
                    information, mean = shared.value.dense(), shared.value.mean
                raw, off = wh.utf8(part.column("text"))
                code, row = grams(raw, off)
                total = np.bincount(row, information[code], minlength=part.num_rows)
                n = np.diff(off)
                value = np.exp((total + prior * mean) / (n + prior))
                yield pa.RecordBatch.from_arrays([*part.columns[:-1], pa.array(n.astype(np.int64)), pa.array(value)], names=[*part.schema.names[:-1], "symbols", "perplexity"])

    fields = rows.schema.fields[:-1]
    out = rows.mapInArrow(run, ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in fields) + ", symbols long, perplexity double")
    return out.select(F.col("_id").alias(id_col), *[F.col(f"k_{c}").alias(c) for c in keep], "symbols", "perplexity")


def _blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The rows with the block that they are in and, after a block's rows, its different grams in runs."""
    at, size = TaskContext.get().partitionId() << 24, 0
    held: list[np.ndarray] = []
    kinds: pa.Schema | None = None

    def listed(code: np.ndarray) -> Iterator[pa.RecordBatch]:
        for lo in range(0, len(code), 1 << 17):
            run = pa.ListArray.from_arrays(pa.array([0, min(len(code) - lo, 1 << 17)], pa.int32()), pa.array(code[lo : lo + (1 << 17)]))
            yield pa.RecordBatch.from_arrays([*[pa.nulls(1, f.type) for f in kinds], pa.array([at]), run], names=[*kinds.names, "block", "grams"])

    for batch in batches:
        kinds = batch.schema
        for part in wh.slices(batch, "text"):
            raw, off = wh.utf8(part.column("text"))
            held.append(np.unique(grams(raw, off, BYTE_ORDER, BYTE_BITS)[0]))
            size += len(raw)
            yield pa.RecordBatch.from_arrays([*part.columns, pa.array(np.full(part.num_rows, at)), pa.nulls(part.num_rows, pa.list_(pa.int64()))], names=[*kinds.names, "block", "grams"])
            if len(held) == 8:
                held = [np.unique(np.concatenate(held))]
            if size > BLOCK_BYTES or sum(map(len, held)) > BLOCK_GRAMS:
                yield from listed(np.unique(np.concatenate(held)))
                at, size, held = at + 1, 0, []
    if held:
        yield from listed(np.unique(np.concatenate(held)))


def gram_probabilities(wanted: DataFrame, probs: list[DataFrame], backs: list[DataFrame], bits: int = BYTE_BITS) -> DataFrame:
    """(gram, p, rest) of every different gram of `wanted`, seen or not. A join's key has at most 2**bits rows."""
    order = len(probs)
    asked = {order: wanted}
    for k in range(order - 1, 0, -1):
        asked[k] = asked[k + 1].select(F.col("gram").bitwiseAND(F.lit((1 << bits * k) - 1)).alias("gram")).distinct()
    lower = None
    for k in range(1, order + 1):
        rows = asked[k].join(probs[k - 1], "gram", "left").join(backs[k - 1], F.shiftright("gram", bits) == F.col("context"), "left")
        back = F.coalesce("back", F.lit(1.0))
        if lower is None:
            rows = rows.select("gram", F.coalesce("p", F.lit(0.0)).alias("p"), F.coalesce("rest", back).alias("rest"))
        else:
            below = lower.select(F.col("gram").alias("short"), F.col("p").alias("q"), F.col("rest").alias("left"))
            rows = rows.join(below, F.col("gram").bitwiseAND(F.lit((1 << bits * (k - 1)) - 1)) == F.col("short"))
            rows = rows.select("gram", F.coalesce("p", back * F.col("q")).alias("p"), F.coalesce("rest", back * F.col("left")).alias("rest"))
        before = lower_path if k > 1 else None
        lower, lower_path = write_table(rows, f"asked-{k}")
        if before:
            drop_path(wanted.sparkSession, before)
    return lower


def information(docs: DataFrame, model: Model, counts: DataFrame, rate: float, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """(id, *keep, symbols, total) for every row of docs: bytes, and their information under the byte counts over the model of classes, with the flags of repeated words."""
    spark = docs.sparkSession
    rows = docs.select(F.col(f"`{id_col}`").alias("_id"), *[F.col(f"`{c}`").alias(f"k_{c}") for c in keep], F.coalesce(F.col(f"`{text_col}`"), F.lit("")).alias("text"))
    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields)
    copy_path, path = new_path(spark, "blocks"), new_path(spark, "answers")
    copy = rows.mapInArrow(_blocks, f"{kinds}, block long, grams array<long>")
    copy.write.option("compression", "zstd").parquet(copy_path)
    copy = spark.read.schema(copy.schema).parquet(copy_path)
    pairs = copy.where("grams is not null").select("block", F.explode("grams").alias("gram"))
    scored = gram_probabilities(write_table(pairs.select("gram").distinct(), "asked")[0], *smoothed(counts, BYTE_ORDER, BYTE_BITS))
    answers = pairs.join(scored, "gram").select("block", "gram", F.col("p").cast("float").alias("p"), F.col("rest").cast("float").alias("rest"))
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    answers.repartition(parts, "block").sortWithinPartitions("block", "gram").write.option("compression", "zstd").partitionBy("block").parquet(path)
    shared = spark.sparkContext.broadcast(model)
    share = np.maximum(np.bincount(_CLASS, minlength=1 << BITS), 1).astype(np.float32)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        base = now = None
        for batch in batches:
            for part in wh.slices(batch, "text"):
                if base is None:
                    base = (np.exp(-shared.value.dense()).reshape(-1, 1 << BITS) / share).ravel()
                blocks = np.asarray(part.column("block"))
                edges = [0, *(np.flatnonzero(blocks[1:] != blocks[:-1]) + 1), len(blocks)]
                for lo, hi in zip(edges, edges[1:], strict=False):
                    some = part.slice(lo, hi - lo)
                    raw, off = wh.utf8(some.column("text"))
                    total = np.zeros(some.num_rows)
                    if len(raw):
                        if now != blocks[lo]:
                            now = blocks[lo]
                            where, inside = fs.FileSystem.from_uri(re.sub("^file:/+", "file:///", f"{path}/block={now}"))
                            got = pa.dataset.dataset(inside, filesystem=where, format="parquet").to_table(["gram", "p", "rest"])
                            gram, p, rest = (np.asarray(got[c]) for c in ("gram", "p", "rest"))
                        code, row = grams(raw, off, BYTE_ORDER, BYTE_BITS)
                        here, inv = np.unique(code, return_inverse=True)
                        spot = np.searchsorted(gram, here)
                        if spot[-1] >= len(gram) or (gram[spot] != here).any():
                            raise ValueError(f"block {now} lacks runs of its texts")
                        value = p[spot][inv] + rest[spot][inv] * base[grams(raw, off)[0]]
                        again, other = repeats(raw, off)
                        total = np.bincount(row, -np.log(value), minlength=some.num_rows) - again * np.log(rate) - other * np.log1p(-rate)
                    yield pa.RecordBatch.from_arrays([*some.columns[:-2], pa.array(np.diff(off).astype(np.int64)), pa.array(total)], names=[*some.schema.names[:-2], "symbols", "total"])

    texts = copy.where("grams is null").drop("grams")
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields[:-1])
    out = texts.mapInArrow(run, f"{fields}, symbols long, total double").select(F.col("_id").alias(id_col), *[F.col(f"k_{c}").alias(c) for c in keep], "symbols", "total")
    done, _ = write_table(out, "information")
    for old in (copy_path, path):
        drop_path(spark, old)
    return done


def quality_filter(docs: DataFrame, trusted: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", quantile: float = QUANTILE, least: int = LEAST_TRUSTED) -> DataFrame:
    """One row per row of docs: id, lang, symbols, perplexity, threshold, kept. trusted has the ids of trusted documents."""
    ids, _ = write_table(pick(trusted, id_col).select(F.col(id_col).alias("_t")).where("_t is not null").distinct(), "trusted")
    n = ids.count()
    side = small_side(ids, n)  # beyond the limit the texts are shuffled
    apart = F.pmod(F.crc32(F.col("_t").cast("string").cast("binary")), F.lit(HELD_OUT)) == 0
    left_out = n and ids.where(apart).count()
    split = left_out >= least
    seen, judged = (small_side(ids.where(~apart), n), small_side(ids.where(apart), n)) if split else (side, side)
    mine = F.col(id_col) == F.col("_t")
    good = pick(docs, id_col, text_col).join(seen, mine, "left_semi").select(F.col(text_col).alias("text")) if n else pick(docs, text_col).select(F.col(text_col).alias("text"))
    counts, _ = write_table(count_grams(good, BYTE_ORDER, BYTE_BITS), "byte-grams")
    scored = information(docs, train(good), counts, repeat_rate(good), id_col, text_col, keep=(lang_col,))
    known = scored.join(judged, mine, "left_semi") if n else scored
    mean = known.agg(F.sum("total") / F.sum("symbols")).first()[0] or 0.0
    value = F.exp((F.col("total") + PRIOR_SYMBOLS * mean) / (F.col("symbols") + PRIOR_SYMBOLS)).alias("perplexity")
    scored, known = (x.select(id_col, lang_col, "symbols", value) for x in (scored, known))
    at = F.percentile_approx("perplexity", F.lit(quantile), F.lit(20_000))
    everywhere = known.agg(at.alias("overall")).first()[0]
    per = known.groupBy(lang_col).agg(at.alias("own"), F.count(F.lit(1)).alias("n"))
    per = per.select(F.col(lang_col).alias("_lang"), F.when(F.col("n") >= least, F.col("own")).otherwise(F.greatest("own", F.lit(everywhere))).alias("limit"))
    limit = F.coalesce("limit", F.lit(everywhere), F.lit(float("inf")))
    # One row per language.
    return scored.join(F.broadcast(per), F.col(lang_col) == F.col("_lang"), "left").select(id_col, lang_col, "symbols", F.round("perplexity", 6).alias("perplexity"), F.round(limit, 6).alias("threshold"), (F.col("perplexity") <= limit).alias("kept"))
