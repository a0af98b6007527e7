"""Counterfactual-regularised toxicity classifier.

Features are presence flags of words and word beginnings. Labelled rows give, per feature, the
documents of either label that hold it; the features most tied to a label make the vocabulary. A
logistic model is fitted on the labelled rows with three terms: the log loss, a ridge, and a
counterfactual penalty: in each labelled text that mentions a group of people, the mention is
swapped for another of the same kind and the squared change of the logit is penalised, so neutral
mentions of groups carry no weight of their own. Fitting uses a bounded, seeded sample of labelled
rows (`max_rows`); scoring reads every whole text.

Defined cases: null and empty texts get the model's prior; repeated rows score alike; labels that
are null, not 0 or 1, or of missing ids are not used; with no labelled rows of both kinds every
score is the share of label 1 (0 without labels); other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import re
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from poolcurator.llm import wordhash as wh
from poolcurator.llm.store import pick

# Names of groups of people, by kind; swaps stay within a kind.
IDENTITY_TERMS: tuple[tuple[str, ...], ...] = (
    ("women", "men", "femmes", "hommes", "frauen", "männer", "mujeres", "hombres"),
    ("woman", "man", "femme", "homme", "frau", "mann", "mujer", "hombre"),
    ("muslim", "christian", "jewish", "hindu", "buddhist", "atheist", "catholic", "protestant", "sikh"),
    ("muslims", "christians", "jews", "hindus", "buddhists", "atheists", "catholics", "protestants", "sikhs"),
    ("gay", "lesbian", "straight", "bisexual", "transgender", "queer", "heterosexual", "homosexual"),
    ("black", "white", "asian", "latino", "hispanic", "african", "european", "american", "arab"),
    ("immigrant", "refugee", "foreigner", "migrant", "native"),
    ("immigrants", "refugees", "foreigners", "migrants", "natives"),
    ("deaf", "blind", "disabled", "autistic", "elderly", "young"),
    ("musulman", "chrétien", "juif", "athée", "catholique"),
    ("muslimisch", "christlich", "jüdisch", "atheistisch", "katholisch"),
    ("musulmán", "cristiano", "judío", "ateo", "católico"),
)
_KIND = {term: (k, i) for k, kind in enumerate(IDENTITY_TERMS) for i, term in enumerate(kind)}
_MENTION = re.compile(r"(?<!\w)(" + "|".join(sorted(map(re.escape, _KIND), key=len, reverse=True)) + r")(?!\w)", re.IGNORECASE)

HEADS = (3, 4, 5, 6)


def swap_mentions(text: str, shift: int = 1) -> str:
    """The text with every group mention replaced by another of its kind; the same text if it has none."""

    def other(m: re.Match) -> str:
        kind, i = _KIND[m[0].lower()]
        terms = IDENTITY_TERMS[kind]
        return terms[(i + shift) % len(terms)]

    return _MENTION.sub(other, text)


@dataclass
class ToxicityModel:
    """Sorted feature hashes with their weights."""

    features: np.ndarray
    weights: np.ndarray
    bias: float
    stats: dict = field(default_factory=dict)

    def logits(self, raw: np.ndarray, off: np.ndarray) -> np.ndarray:
        z = np.full(len(off) - 1, self.bias)
        if len(self.features):
            row, column = active(raw, off, self.features)
            z += np.bincount(row, self.weights[column], minlength=len(z))
        return z


def _all_features(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Different (row, feature hash) of every text; a word beginning is a feature of longer words only."""
    word, row, heads = wh.words(raw, off, HEADS)
    h = np.concatenate([word, *[heads[p] for p in HEADS]])
    r = np.concatenate([row] * (1 + len(HEADS)))
    return r[h != 0], h[h != 0]


def active(raw: np.ndarray, off: np.ndarray, features: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Different (row, column) of the texts' features that are in the sorted list."""
    seen = np.zeros(1 << 18, dtype=bool)
    seen[features >> wh.U(46)] = True
    r, h = _all_features(raw, off)
    maybe = seen[h >> wh.U(46)]
    r, h = r[maybe], h[maybe]
    at = np.searchsorted(features, h)
    at[at == len(features)] = 0
    hit = features[at] == h
    pair = np.unique(r[hit] * len(features) + at[hit])
    return pair // len(features), pair % len(features)


def _label_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    size = 0

    def flush() -> pa.RecordBatch:
        h, n, p = (np.concatenate(x) for x in zip(*held, strict=True))
        u, inv = np.unique(h, return_inverse=True)
        return pa.RecordBatch.from_arrays([pa.array(u.view(np.int64)), pa.array(np.bincount(inv, n).astype(np.int64)), pa.array(np.bincount(inv, p).astype(np.int64))], names=["h", "n", "p"])

    for batch in batches:
        for part in wh.slices(batch, "text", 1 << 20):
            raw, off = wh.utf8(part.column("text"))
            label = np.asarray(part.column("label"))
            r, h = _all_features(raw, off)
            if not len(h):
                continue
            order = np.lexsort((h, r))
            r, h = r[order], h[order]
            new = np.append(True, (h[1:] != h[:-1]) | (r[1:] != r[:-1]))
            u, inv = np.unique(h[new], return_inverse=True)
            held.append((u, np.bincount(inv).astype(float), np.bincount(inv, label[r[new]])))
            size += len(u)
            if size > 500_000:
                out = flush()
                yield out
                held, size = [], 0
    if held:
        yield flush()


def _designs(features: np.ndarray, swaps: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in wh.slices(batch, "text"):
                rows, kinds, lists = [], [], []
                label = np.asarray(part.column("label"))
                raw, off = wh.utf8(part.column("text"))
                texts = [part.column("text").to_pylist()]
                sets = [(0, raw, off, np.arange(len(label)))]
                for s in range(1, swaps + 1):
                    changed = [(i, swap_mentions(t, s)) for i, t in enumerate(texts[0]) if t and _MENTION.search(t)]
                    if changed:
                        sets.append((s, *wh.utf8(pa.array([t for _, t in changed])), np.array([i for i, _ in changed])))
                for s, b, o, which in sets:
                    r, c = active(b, o, features)
                    for i, cols in enumerate(np.split(c, np.searchsorted(r, np.arange(1, len(which))))):
                        rows.append(int(which[i]))
                        kinds.append(s)
                        lists.append(cols.astype(np.int32))
                ids = np.asarray(part.column("key"))
                yield pa.RecordBatch.from_arrays([pa.array(ids[rows]), pa.array(np.array(kinds, np.int32)), pa.array(label[rows].astype(np.int32)), pa.array(lists, pa.list_(pa.int32()))], names=["key", "swap", "label", "cols"])

    return run


def fit_logistic(rows: list[np.ndarray], labels: np.ndarray, pairs: list[tuple[np.ndarray, np.ndarray]], scale: np.ndarray, ridge: float = 1e-4, fairness: float = 1.0, steps: int = 300) -> tuple[np.ndarray, float]:
    """Weights and bias that minimise log loss + ridge + fairness * mean squared logit change over counterfactual pairs.

    A column counts scale[column] where it is present, so weakly attested ones are shrunk more.
    """
    width = len(scale)

    def flat(lists: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        return np.repeat(np.arange(len(lists)), [len(x) for x in lists]), np.concatenate([np.zeros(0, np.int64), *lists]).astype(np.int64)

    r, c = flat(rows)
    r1, c1 = flat([a for a, _ in pairs])
    r2, c2 = flat([b for _, b in pairs])
    n, m = len(rows), max(1, len(pairs))
    y = labels.astype(float)
    base = np.clip(y.mean(), 1e-4, 1 - 1e-4)
    w, b = np.zeros(width), float(np.log(base / (1 - base)))
    moment, second, mb, sb = np.zeros(width), np.zeros(width), 0.0, 0.0
    for t in range(1, steps + 1):
        v = w * scale
        z = b + np.bincount(r, v[c], minlength=n)
        e = (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y) / n
        g = np.bincount(c, e[r], minlength=width)
        if pairs:
            d = np.bincount(r1, v[c1], minlength=len(pairs)) - np.bincount(r2, v[c2], minlength=len(pairs))
            g += 2 * fairness / m * (np.bincount(c1, d[r1], minlength=width) - np.bincount(c2, d[r2], minlength=width))
        g = g * scale + ridge * w
        gb = e.sum()
        moment, second = 0.9 * moment + 0.1 * g, 0.999 * second + 0.001 * g * g
        mb, sb = 0.9 * mb + 0.1 * gb, 0.999 * sb + 0.001 * gb * gb
        rate = 0.1 if t < steps * 0.7 else 0.02
        w -= rate * (moment / (1 - 0.9**t)) / (np.sqrt(second / (1 - 0.999**t)) + 1e-9)
        b -= rate * (mb / (1 - 0.9**t)) / (np.sqrt(sb / (1 - 0.999**t)) + 1e-9)
    return w * scale, b


def train(labelled: DataFrame, max_rows: int = 16_384, vocabulary: int = 4_096, min_count: int = 3, swaps: int = 2, ridge: float = 1.0, evidence: float = 24.0, fairness: float = 1.0, seed: int = 42) -> ToxicityModel:
    """A model from (text, label) rows, of which at most about max_rows are used, chosen by a seeded hash of the text."""
    rows = pick(labelled, "text", "label").where(F.col("label").isin(0, 1)).select(F.coalesce("text", F.lit("")).alias("text"), F.col("label").cast("int").alias("label"))
    rows = rows.withColumn("key", F.xxhash64(F.lit(seed), "text"))
    n, positive = rows.agg(F.count(F.lit(1)), F.coalesce(F.sum("label"), F.lit(0))).first()
    if not positive or positive == n:
        share = positive / n if n else 0.0
        return ToxicityModel(np.zeros(0, wh.U), np.zeros(0), float(np.log(max(share, 1e-6) / max(1 - share, 1e-6))))
    if n > max_rows:  # both labels are thinned alike
        rows = rows.where(F.shiftrightunsigned("key", 32) < int(max_rows / n * 2**32))
    counts = rows.mapInArrow(_label_counts, "h long, n long, p long").groupBy("h").agg(F.sum("n").alias("n"), F.sum("p").alias("p"))
    # Tie to a label: the log-likelihood ratio of presence, against the label's share.
    share = positive / n
    q = (F.col("p") + 0.5 * share) / (F.col("n") + 0.5)
    gain = F.col("p") * F.log(q / share) + (F.col("n") - F.col("p")) * F.log((1 - q) / (1 - share))
    chosen = counts.where(F.col("n") >= min_count).select("h", gain.alias("g")).orderBy(F.desc("g"), "h").limit(vocabulary).collect()
    features = np.array([r.h for r in chosen], dtype=np.int64).view(wh.U)
    order = np.argsort(features)
    features, gains = features[order], np.array([r.g for r in chosen])[order]
    if not len(features):
        return ToxicityModel(np.zeros(0, wh.U), np.zeros(0), float(np.log(share / (1 - share))))
    got = rows.mapInArrow(_designs(features, swaps), "key long, swap int, label int, cols array<int>").toArrow()
    kinds, labels, lists = np.asarray(got["swap"]), np.asarray(got["label"]), [np.asarray(x.values) for x in got["cols"]]
    keys = np.asarray(got["key"])
    order = np.lexsort((kinds, keys))
    base = {int(keys[i]): lists[i] for i in order if kinds[i] == 0}
    first = [i for i in order if kinds[i] == 0]
    pairs = [(base[int(keys[i])], lists[i]) for i in order if kinds[i] > 0]
    # `ridge` is spread over the rows; a feature with a gain of `evidence` or more counts in full.
    w, b = fit_logistic([lists[i] for i in first], labels[first], pairs, np.minimum(1.0, gains / evidence), ridge / len(first), fairness)
    return ToxicityModel(features, w, b, {"rows": len(first), "pairs": len(pairs), "features": len(features)})


def score(docs: DataFrame, model: ToxicityModel, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """(id, *keep, score) for every row of docs; keep may name the text itself."""
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(model)  # bounded by the vocabulary
    rows = docs.select(F.col(f"`{id_col}`").alias("_id"), *[F.col(f"`{c}`").alias(f"k_{c}") for c in keep if c != text_col], F.col(f"`{text_col}`").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            for part in wh.slices(batch, "text"):
                z = m.logits(*wh.utf8(part.column("text")))
                s = 1 / (1 + np.exp(-np.clip(z, -500, 500)))
                columns = [part.column(i) for i in range(part.num_columns) if part.schema.names[i] != "text" or text_col in keep]
                names = [x for x in part.schema.names if x != "text" or text_col in keep]
                yield pa.RecordBatch.from_arrays([*columns, pa.array(s)], names=[*names, "score"])

    fields = [f for f in rows.schema.fields if f.name != "text" or text_col in keep]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in fields) + ", score double"
    out = rows.mapInArrow(run, schema)
    return out.select(F.col("_id").alias(id_col), *[F.col("text").alias(c) if c == text_col else F.col(f"k_{c}").alias(c) for c in keep], "score")


def train_on_labels(docs: DataFrame, labels: DataFrame, max_rows: int = 16_384, seed: int = 42, **options) -> ToxicityModel:
    """A model from documents joined with their labels, without the held-out rows (crc32 of the id mod 4 is 2).

    Labels are thinned to about max_rows before the join, so that side is bounded and no text is shuffled.
    """
    known = pick(labels, "doc_id", "toxic").where(F.col("toxic").isin(0, 1) & (F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(4)) != 2))
    known = known.groupBy("doc_id").agg(F.max("toxic").alias("label"))
    n = known.count()
    if n > max_rows:
        known = known.where(F.shiftrightunsigned(F.xxhash64(F.lit(seed), "doc_id"), 32) < int(max_rows / n * 2**32))
    return train(pick(docs, "doc_id", "text").join(F.broadcast(known), "doc_id"), 2 * max_rows, seed=seed, **options)
