"""Target models whose token probabilities are count tables: unigram, bigram, bigram with a prompt cache.

Count tables and chains of likeliest tokens are tables of the shared folder, so a plan that scores or
generates starts from them. Each is joined by broadcast while its counted rows allow that, else by a
shuffle whose hot keys the engine splits.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from poolcurator.functions import text as X
from poolcurator.operators.topk import rehydrate
from poolcurator.sources.files import durable

BOS = "<s>"
#: Rows of a count table that may be broadcast, and of one shuffled part that may be hashed in memory.
BROADCAST_ROWS, PART_ROWS = 500_000, 1_000_000


def token_rows(samples: DataFrame, conditional: bool = True, key: str = "sample_id") -> DataFrame:
    """(key, pos, h, w): every output token with the token before it; the first one's is the prompt's last token, or the start."""
    first = last_token() if conditional else F.lit(BOS)
    rows = samples.select(key, first.alias("first"), "output")
    tokens = X.once(X.tokens("output"), lambda y: F.transform(y, lambda w, i: F.struct(F.get(y, i - 1).alias("h"), w.alias("w"))))
    out = rows.select(key, "first", F.posexplode_outer(tokens).alias("pos", "t")).where("pos IS NOT NULL")
    return out.select(key, "pos", F.coalesce("t.h", "first").alias("h"), F.col("t.w").alias("w"))


def bare_rows(samples: DataFrame, key: str = "sample_id") -> DataFrame:
    """(key, pos, h, w): every output's first token after the start."""
    return samples.select(key, F.lit(0).alias("pos"), F.lit(BOS).alias("h"), F.get(X.tokens("output"), F.lit(0)).alias("w")).where("w IS NOT NULL")


def last_token(c: str = "instruction") -> F.Column:
    return F.coalesce(F.try_element_at(X.tokens(c), F.lit(-1)), F.lit(BOS))


def asked(table: DataFrame, size: int, rows: DataFrame, n: int, on: list[str]) -> DataFrame:
    """The part of a count table of `size` rows that `n` rows ask for: while those may be broadcast, so may their part of a larger table."""
    if size > BROADCAST_ROWS >= n:
        return F.broadcast(table.join(F.broadcast(rows.select(*on).distinct()), on, "left_semi"))
    return side(table, size)


def side(df: DataFrame, rows: int) -> DataFrame:
    """df marked for broadcast, or for hash tables of its shuffled parts, as far as its counted rows allow."""
    if rows <= BROADCAST_ROWS:
        return F.broadcast(df)
    return hashed(df, rows)


def hashed(df: DataFrame, rows: int) -> DataFrame:
    """df marked for hash tables of its shuffled parts, as far as its counted rows allow."""
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return df.hint("shuffle_hash") if rows // parts <= PART_ROWS else df


@dataclass
class Known:
    """A pool and its token rows with the models' counts, so that scores of its samples meet the count tables no more."""

    pool: DataFrame
    tokens: DataFrame  # kind (0 given the prompt, 1 the first token without it), key, pos, h, w, n, total, entropy0 ..., n_w

    def of(self, samples: DataFrame, key: str) -> DataFrame:
        """Token rows of the pool or of a part of it."""
        return self.tokens if samples is self.pool else rehydrate(self.tokens, samples, key)


@dataclass
class Measured:
    """What one pass over a pool's tokens finds of every sample, so that no part of the pool meets the count tables again."""

    pool: DataFrame
    table: DataFrame  # key, loss0, entropy0, given0, alone0, ifd0, loss1 ...: by the models' places

    def of(self, samples: DataFrame, key: str, place: int, names: tuple[str, ...]) -> DataFrame:
        rows = self.table if samples is self.pool else rehydrate(self.table, samples, key)
        return rows.select(key, *[F.col(f"{n}{place}").alias(n) for n in names])


@dataclass
class BigramTarget:
    """p(w | h) = (N(h, w) + lambda) / (N(h) + lambda V); V counts one unknown token."""

    pairs: DataFrame  # h, w, n
    contexts: DataFrame  # h, total, kinds, entropy
    v: int
    smoothing: float = 0.1
    _sizes: tuple[int, int] | None = None
    _chains: dict[int, DataFrame] = field(default_factory=dict)
    _tails: dict[int, DataFrame] = field(default_factory=dict)
    _best: DataFrame | None = None
    _inner: DataFrame | None = None
    words: DataFrame | None = None  # w, n
    known: Known | None = None
    measured: Measured | None = None
    entropies: DataFrame | None = None  # h, total, kinds, entropy0, entropy1 ...: of all models from the same count
    place: int = 0  # the model's own among them

    @classmethod
    def fit(cls, samples: DataFrame, smoothing: float = 0.1) -> BigramTarget:
        return cls.fit_all(samples, (smoothing,))[0]

    @classmethod
    def fit_all(cls, samples: DataFrame, smoothings: tuple[float, ...]) -> list[BigramTarget]:
        """A model per smoothing from one count of the tokens.

        Over a context's pairs, -sum of p log p is (Z' log Z - sum of (n + lambda) log (n + lambda)) / Z with Z = N(h) + lambda V and
        Z' = N(h) + lambda times the pairs, so one aggregate serves all entropies.
        """
        pairs = durable(token_rows(samples, conditional=False).groupBy("h", "w").agg(F.count(F.lit(1)).alias("n")), "bigram-pairs")
        words = durable(pairs.groupBy("w").agg(F.sum("n").alias("n")), "unigram")
        v = words.count() + 1
        logs = [F.sum((F.col("n") + s) * F.log(F.col("n") + s)).alias(f"logs{i}") for i, s in enumerate(smoothings)]
        sums = pairs.groupBy("h").agg(F.sum("n").alias("total"), F.count(F.lit(1)).alias("kinds"), *logs)
        entropies = []
        for i, s in enumerate(smoothings):
            z = F.col("total") + s * v
            seen = ((F.col("total") + s * F.col("kinds")) * F.log(z) - F.col(f"logs{i}")) / z
            entropies.append((seen - (v - F.col("kinds")) * (s / z) * F.log(s / z)).alias(f"entropy{i}"))
        contexts = durable(sums.select("h", "total", "kinds", *entropies), "bigram-contexts")
        return [cls(pairs, contexts.select("h", "total", "kinds", F.col(f"entropy{i}").alias("entropy")), v, s, words=words, entropies=contexts, place=i) for i, s in enumerate(smoothings)]

    def sides(self) -> tuple[DataFrame, DataFrame]:
        """Contexts and pairs, each marked for broadcast if its counted rows allow."""
        if self._sizes is None:
            self._sizes = self.contexts.count(), self.pairs.count()
        return side(self.contexts.select("h", "total", "entropy"), self._sizes[0]), side(self.pairs, self._sizes[1])

    def scored(self, rows: DataFrame, n: int | None = None) -> DataFrame:
        """rows with p and entropy of every token; where they are `n` counted rows that may be broadcast, the tables need no shuffle."""
        contexts, pairs = self.sides()
        if n is not None:
            contexts = asked(self.contexts.select("h", "total", "entropy"), self._sizes[0], rows, n, ["h"])
            pairs = asked(self.pairs, self._sizes[1], rows, n, ["h", "w"])
        return self.with_p(rows.join(contexts, "h", "left").join(pairs, ["h", "w"], "left"))

    def with_p(self, out: DataFrame) -> DataFrame:
        """Rows with n, total and entropy, null where unknown, with p and the context's entropy instead."""
        p = (F.coalesce("n", F.lit(0)) + self.smoothing) / (F.coalesce("total", F.lit(0)) + self.smoothing * self.v)
        return out.withColumns({"p": p, "h_entropy": F.coalesce("entropy", F.lit(1.0) * F.log(F.lit(float(self.v))))}).drop("n", "total", "entropy")

    def known_tokens(self, samples: DataFrame, key: str = "sample_id") -> DataFrame:
        """The table of Known for all models from this one's count, a sample's rows side by side."""
        pairs, contexts = self.sides()[1], side(self.entropies.drop("kinds"), self._sizes[0])
        both = token_rows(samples, key=key).withColumn("kind", F.lit(0)).unionByName(bare_rows(samples, key).withColumn("kind", F.lit(1)))
        words = side(self.words.withColumnRenamed("n", "n_w"), self.v)
        rows = both.join(contexts, "h", "left").join(pairs, ["h", "w"], "left").join(words, "w", "left")
        return durable(rows.repartition(key).sortWithinPartitions(key), "known-tokens")

    def measure(self, samples: DataFrame, smoothings: tuple[float, ...], key: str = "sample_id") -> DataFrame:
        """The table of Measured for the models of these smoothings, all from this one's count."""
        pairs, contexts = self.sides()[1], side(self.entropies.drop("kinds"), self._sizes[0])
        both = token_rows(samples, key=key).withColumn("kind", F.lit(0)).unionByName(bare_rows(samples, key).withColumn("kind", F.lit(1)))
        rows, sums, out = both.join(contexts, "h", "left").join(pairs, ["h", "w"], "left"), [], [key]
        for i, s in enumerate(smoothings):
            nll = -F.log((F.coalesce("n", F.lit(0)) + s) / (F.coalesce("total", F.lit(0)) + s * self.v))
            entropy = F.coalesce(f"entropy{i}", F.lit(1.0) * F.log(F.lit(float(self.v))))
            given, bare, first = (F.sum(F.when(test, nll)) for test in (F.col("kind") == 0, F.col("kind") == 1, (F.col("kind") == 0) & (F.col("pos") == 0)))
            sums += [given.alias(f"sum{i}"), bare.alias(f"bare{i}"), first.alias(f"first{i}"), F.avg(F.when(F.col("kind") == 0, entropy)).alias(f"entropy{i}")]
            loss = F.col(f"sum{i}") / F.col("n")
            alone = loss + (F.col(f"bare{i}") - F.col(f"first{i}")) / F.col("n")
            out += [loss.alias(f"loss{i}"), F.col(f"entropy{i}"), loss.alias(f"given{i}"), alone.alias(f"alone{i}"), (loss / alone).alias(f"ifd{i}")]
        return durable(rows.groupBy(key).agg(F.count_if(F.col("kind") == 0).alias("n"), *sums).select(*out), "measured")

    def known_scores(self, samples: DataFrame, key: str) -> DataFrame:
        """The rows of Known with the model's own p and h_entropy."""
        rows = self.known.of(samples, key)
        return self.with_p(rows.select(key, "kind", "pos", "h", "w", "n", "total", F.col(f"entropy{self.place}").alias("entropy")))

    def token_scores(self, samples: DataFrame, key: str = "sample_id") -> DataFrame:
        """Every output token given the prompt, with p and h_entropy."""
        return self.scored(token_rows(samples, key=key)) if self.known is None else self.known_scores(samples, key).where("kind = 0").drop("kind")

    def metrics(self, samples: DataFrame, key: str = "sample_id") -> DataFrame:
        """(key, loss, entropy) in one pass over the tokens."""
        if self.measured is not None:
            return self.measured.of(samples, key, self.place, ("loss", "entropy"))
        s = self.token_scores(samples, key)
        return s.groupBy(key).agg(F.avg(-F.log("p")).alias("loss"), F.avg("h_entropy").alias("entropy"))

    def ifd(self, samples: DataFrame, key: str = "sample_id") -> DataFrame:
        """(key, given, alone, ifd): loss with and without the prompt, and their ratio, from one token pass.

        Only the first token's context differs between the two.
        """
        if self.measured is not None:
            return self.measured.of(samples, key, self.place, ("given", "alone", "ifd"))
        if self.known is None:
            scored = self.scored(token_rows(samples, key=key).withColumn("kind", F.lit(0)).unionByName(bare_rows(samples, key).withColumn("kind", F.lit(1))))
        else:
            scored = self.known_scores(samples, key)
        return ratio_of(scored.withColumn("nll", -F.log("p")), key)

    def min_k(self, samples: DataFrame, frac: float = 0.2, key: str = "sample_id") -> DataFrame:
        """(key, knowledge): mean loss of the share of tokens that the model finds least likely."""
        return least_likely(self.token_scores(samples, key), frac, key)

    def table_shift(self, samples: DataFrame, lr: float = 1e-5, key: str = "sample_id") -> DataFrame:
        """(key, mean_diff): mean absolute change of the model's own logits after one plain gradient step on the sample.

        The logit of (h, w) moves by lr times its share of the loss's gradient, (c(h) p(w | h) - c(h, w)) / n
        with the sample's counts c. Tokens that do not follow h in the sample add up in closed form,
        so the table of contexts times vocabulary is never made.
        """
        self.sides()
        n_contexts = self._sizes[0]
        c = token_rows(samples, key=key).groupBy(key, "h", "w").agg(F.count(F.lit(1)).alias("c"))
        per = self.scored(c).withColumn("c_h", F.sum("c").over(Window.partitionBy(key, "h")))
        moved = F.sum(F.abs(F.col("c_h") * F.col("p") - F.col("c")) - F.col("c_h") * F.col("p"))
        rest = per.groupBy(key, "h").agg(moved.alias("moved"), F.max("c_h").alias("c_h"))
        return rest.groupBy(key).agg((lr * F.sum(F.col("moved") + F.col("c_h")) / F.sum("c_h") / (n_contexts * self.v)).alias("mean_diff"))

    def best(self) -> DataFrame:
        """(h, last, n): the likeliest token after every context, the last by code point of equals, and its count."""
        top = self.pairs.groupBy("h").agg(F.max(F.struct("n", "w")).alias("top"))
        return top.select("h", F.col("top.w").alias("last"), F.col("top.n").alias("n"))

    def likeliest(self) -> DataFrame:
        """The table of best(), made once."""
        if self._best is None:
            self._best = durable(self.best(), "best")
        return self._best

    def chains(self, length: int) -> DataFrame:
        """(h, generated): the likeliest continuation of every context, by doubling: a chain followed by that of its last token."""
        if length not in self._chains:
            self.sides()
            self._chains[length] = self.doubled(self.likeliest(), self._sizes[0], length, side)
        return self._chains[length]

    @staticmethod
    def doubled(best: DataFrame, n: int, length: int, met) -> DataFrame:
        """(h, generated): chains within a table of `n` likeliest tokens, which `met` marks for the joins."""
        chain, steps = best.select("h", "last", F.array("last").alias("out")), 1
        while steps < length:
            then = chain.select(F.col("h").alias("last"), F.col("last").alias("end"), F.col("out").alias("more"))
            joined = chain.join(met(then, n), "last", "left")
            out = F.slice(F.when(F.col("more").isNull(), F.col("out")).otherwise(F.concat("out", "more")), 1, length)
            chain = durable(joined.select("h", F.coalesce("end", "last").alias("last"), out.alias("out")), "chain")
            steps *= 2
        return durable(chain.select("h", F.array_join("out", " ").alias("generated")), "chain")

    def generate(self, samples: DataFrame, length: int = 20, key: str = "sample_id") -> DataFrame:
        """(key, generated): the likeliest continuation of the prompt's last token, or of the start where that is unknown.

        From the second step on only tokens are met that are likeliest after some other. While those may be broadcast, their
        chains are built by doubling, and a sample looks up its first token and that one's chain; beyond that the chains of
        all contexts are built. Both say the same.
        """
        self.sides()
        at, n = samples.select(key, last_token().alias("h")), self._sizes[0]
        if self._inner is None:
            best = self.likeliest()
            self._inner = durable(best.join(best.select(F.col("last").alias("h")).distinct(), "h", "left_semi").select("h", "last"), "inner")
        inner = self._inner.count()
        if inner > BROADCAST_ROWS:
            chain = self.chains(length)
            start = chain.where(F.col("h") == BOS).agg(F.coalesce(F.max("generated"), F.lit("")).alias("fallback"))  # one row
            return at.join(side(chain, n), "h", "left").crossJoin(F.broadcast(start)).select(key, F.coalesce("generated", "fallback").alias("generated"))
        start = self.likeliest().where(F.col("h") == BOS).agg(F.max("last").alias("fallback"))  # one row
        first = at.join(side(self.likeliest().select("h", "last"), n), "h", "left").crossJoin(F.broadcast(start)).select(key, F.coalesce("last", "fallback").alias("h"))
        if length < 2:
            return first.select(key, F.coalesce("h", F.lit("")).alias("generated"))
        if length not in self._tails:
            self._tails[length] = self.doubled(self._inner, inner, length - 1, hashed)
        return first.join(hashed(self._tails[length], inner), "h", "left").select(key, F.concat_ws(" ", "h", "generated").alias("generated"))


def ratio_of(scored: DataFrame, key: str) -> DataFrame:
    """(key, given, alone, ifd) from token rows with nll: kind 0 given the prompt, kind 1 the first token without it."""
    agg = scored.groupBy(key).agg(
        F.avg(F.when(F.col("kind") == 0, F.col("nll"))).alias("given"),
        F.count_if(F.col("kind") == 0).alias("n"),
        F.sum(F.when(F.col("kind") == 1, F.col("nll"))).alias("bare"),
        F.sum(F.when((F.col("kind") == 0) & (F.col("pos") == 0), F.col("nll"))).alias("first"),
    )
    alone = F.col("given") + (F.col("bare") - F.col("first")) / F.col("n")
    return agg.select(key, "given", alone.alias("alone"), (F.col("given") / alone).alias("ifd"))


def least_likely(scored: DataFrame, frac: float, key: str) -> DataFrame:
    """(key, knowledge): mean loss of the least likely share of a sample's tokens."""
    s = scored.groupBy(key).agg(F.sort_array(F.collect_list(-F.log("p")), asc=False).alias("nll"))
    k = F.ceil(F.size("nll") * F.lit(frac)).cast("int")
    return s.select(key, (F.aggregate(F.slice("nll", F.lit(1), k), F.lit(0.0), lambda a, b: a + b) / k).alias("knowledge"))


@dataclass
class UnigramTarget:
    """p(w) = (N(w) + lambda) / (N + lambda V)."""

    counts: DataFrame
    total: int
    v: int
    smoothing: float = 0.1
    known: Known | None = None

    @classmethod
    def fit(cls, samples: DataFrame, smoothing: float = 0.1) -> UnigramTarget:
        return cls.of(durable(token_rows(samples, conditional=False).groupBy("w").agg(F.count(F.lit(1)).alias("n")), "unigram"), smoothing)

    @classmethod
    def of(cls, counts: DataFrame, smoothing: float = 0.1, known: Known | None = None) -> UnigramTarget:
        """The model of a table of counted words (w, n), such as a bigram model's."""
        total, kinds = counts.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count(F.lit(1))).first()
        return cls(counts, int(total), kinds + 1, smoothing, known)

    @property
    def z(self) -> float:
        return self.total + self.smoothing * self.v

    def scored(self, rows: DataFrame) -> DataFrame:
        return self.with_p(rows.join(side(self.counts.withColumnRenamed("n", "n_w"), self.v), "w", "left"))

    def with_p(self, rows: DataFrame) -> DataFrame:
        return rows.withColumn("p", (F.coalesce("n_w", F.lit(0)) + self.smoothing) / self.z).drop("n_w")

    def token_scores(self, samples: DataFrame, key: str = "sample_id") -> DataFrame:
        """Every output token with p."""
        return self.scored(token_rows(samples, key=key)) if self.known is None else self.with_p(self.known.of(samples, key).where("kind = 0").select(key, "pos", "h", "w", "n_w"))

    def metrics(self, samples: DataFrame, key: str = "sample_id") -> DataFrame:
        """(key, loss, entropy); the entropy is the model's own, the same everywhere."""
        p = (F.col("n") + self.smoothing) / self.z
        p0 = self.smoothing / self.z
        seen = self.counts.agg(F.coalesce(F.sum(-p * F.log(p)), F.lit(0.0)), F.count(F.lit(1))).first()
        entropy = seen[0] - (self.v - seen[1]) * p0 * math.log(p0)
        return self.token_scores(samples, key).groupBy(key).agg(F.avg(-F.log("p")).alias("loss"), F.lit(entropy).alias("entropy"))

    def ifd(self, samples: DataFrame, key: str = "sample_id") -> DataFrame:
        """(key, given, alone, ifd); the prompt is no help to a model without context, so the ratio is 1."""
        loss = self.metrics(samples, key).select(key, F.col("loss").alias("given"))
        return loss.select(key, "given", F.col("given").alias("alone"), F.lit(1.0).alias("ifd"))

    def min_k(self, samples: DataFrame, frac: float = 0.2, key: str = "sample_id") -> DataFrame:
        return least_likely(self.token_scores(samples, key), frac, key)

    def generate(self, samples: DataFrame, length: int = 20, key: str = "sample_id") -> DataFrame:
        """(key, generated): the likeliest token, over and over."""
        top = self.counts.agg(F.max_by("w", F.struct(F.col("n"), F.col("w")))).first()[0]
        return samples.select(key, F.lit(" ".join([top or ""] * length).strip()).alias("generated"))


@dataclass
class PromptCacheTarget:
    """(1 - beta) of the bigram model plus beta of the token's relative frequency in the prompt."""

    base: BigramTarget
    beta: float = 0.2
    _prompts: tuple[DataFrame, str, DataFrame, BigramTarget] | None = None

    def prompts(self, samples: DataFrame, key: str) -> tuple[DataFrame, BigramTarget]:
        """The table of cache(), and the bigram model with only the pairs whose token some prompt has; made once for the same samples."""
        if self._prompts is None or self._prompts[0] is not samples or self._prompts[1] != key:
            cache = durable(self.cache(samples, key), "prompt-words")
            words = cache.select("w").distinct()
            pairs = durable(self.base.pairs.join(side(words, words.count()), "w", "left_semi").select("h", "w", "n"), "prompt-pairs")
            self._prompts = samples, key, cache, replace(self.base, pairs=pairs, _sizes=None, known=None)
        return self._prompts[2:]

    def cache(self, samples: DataFrame, key: str) -> DataFrame:
        """(key, w, q): shares of the prompt's tokens."""
        counts = X.explode_rows(samples, [key], X.tokens("instruction"), "w").groupBy(key, "w").agg(F.count(F.lit(1)).alias("c"))
        return counts.withColumn("q", F.col("c") / F.sum("c").over(Window.partitionBy(key))).drop("c")

    def scored(self, samples: DataFrame, key: str) -> DataFrame:
        """The samples' token rows with the mixture's p, the bigram's entropy, and whether the prompt has tokens."""
        cache = self.prompts(samples, key)[0]
        has = cache.select(key).distinct().withColumn("has", F.lit(True))
        out = self.base.token_scores(samples, key).join(cache, [key, "w"], "left").join(has, key, "left")
        beta = F.when(F.col("has"), F.lit(self.beta)).otherwise(F.lit(0.0))
        return out.withColumn("p", (1 - beta) * F.col("p") + beta * F.coalesce("q", F.lit(0.0))).drop("q")

    def metrics(self, samples: DataFrame, key: str = "sample_id") -> DataFrame:
        """(key, loss, entropy). The entropy corrects the bigram's closed form on the prompt's different tokens only."""
        rows = self.scored(samples, key)
        # All that an entropy depends on is the sample and the token before.
        per = rows.groupBy(key, "h").agg(F.count(F.lit(1)).alias("spots"), F.sum(-F.log("p")).alias("nll"), F.max("h_entropy").alias("h_entropy"), F.max("has").alias("has"))
        heads = durable(per, "prompt-heads")
        fix = self.fixes(heads.where("has").select(key, "h"), samples, key)
        # entropy: all tokens outside the prompt have (1-beta) p; add the prompt's tokens as they are.
        scaled = (1 - self.beta) * F.col("h_entropy") - (1 - self.beta) * math.log(1 - self.beta)
        value = F.when(F.col("has"), scaled + F.coalesce("fix", F.lit(0.0))).otherwise(F.col("h_entropy"))
        n = F.sum("spots")
        return heads.join(fix, [key, "h"], "left").groupBy(key).agg((F.sum("nll") / n).alias("loss"), (F.sum(F.col("spots") * value) / n).alias("entropy"))

    def fixes(self, heads: DataFrame, samples: DataFrame, key: str) -> DataFrame:
        """(key, h, fix): what the prompt's tokens change in the entropy after h, for every token before of a sample with a prompt.

        A sample's heads times its prompt's tokens are by far the most rows of a run. So they are dealt once, to meet the pairs, with
        the context's total at hand, and only pairs that were counted go on; what all tokens would add if none had been, depends on
        the tokens' shares alone, of which a prompt has few different ones.
        """
        cache, b = self.prompts(samples, key)
        b.sides()
        z = F.coalesce("total", F.lit(0)) + b.smoothing * b.v

        def change(n, q):
            p = (1 - self.beta) * (n + F.lit(b.smoothing)) / F.col("z")
            m = p + self.beta * q
            return p * F.log(p) - m * F.log(m)

        at = durable(heads.join(side(b.contexts.select("h", "total"), b._sizes[0]), "h", "left").select(key, "h", z.alias("z")), "prompt-totals")
        shares = cache.groupBy(key, "q").agg(F.count(F.lit(1)).alias("c")).groupBy(key).agg(F.sort_array(F.collect_list(F.struct("q", "c"))).alias("shares"))
        none = at.join(shares, key).select(key, "h", F.aggregate("shares", F.lit(0.0), lambda a, x: a + x["c"] * change(F.lit(0), x["q"])).alias("fix"))
        seen = at.join(cache, key).join(side(b.pairs, b._sizes[1]), ["h", "w"])
        more = durable(seen.groupBy(key, "h").agg(F.sum(change(F.col("n"), F.col("q")) - change(F.lit(0), F.col("q"))).alias("more")), "prompt-pairs-met")
        return none.join(more, [key, "h"], "left").select(key, "h", (F.col("fix") + F.coalesce("more", F.lit(0.0))).alias("fix"))

    def ifd(self, samples: DataFrame, key: str = "sample_id") -> DataFrame:
        """(key, given, alone, ifd); without the prompt the mixture is the bigram model."""
        given = self.scored(samples, key).groupBy(key).agg(F.avg(-F.log("p")).alias("given"))
        alone = self.base.ifd(samples, key).select(key, "alone")
        return given.join(alone, key).select(key, "given", "alone", (F.col("given") / F.col("alone")).alias("ifd"))

    def min_k(self, samples: DataFrame, frac: float = 0.2, key: str = "sample_id") -> DataFrame:
        return least_likely(self.scored(samples, key), frac, key)

    def generate(self, samples: DataFrame, length: int = 20, key: str = "sample_id") -> DataFrame:
        """(key, generated): greedy, one token a round, as every choice depends on the prompt; rounds are tables of the shared folder.

        The likeliest token is the bigram's own best or one of the prompt's, so only those are compared. A choice is a
        function of the prompt and the token before, so a sample is done as soon as a token comes back: the rest repeats.
        """
        cache, b = self.prompts(samples, key)
        b.sides()
        p = (F.col("n") + b.smoothing) / (F.col("total") + b.smoothing * b.v)
        likely = durable(self.base.likeliest().join(side(b.contexts.select("h", "total"), b._sizes[0]), "h").select("h", F.col("last").alias("w"), p.alias("p")), "likely")
        now = durable(samples.select(key, F.array(last_token()).alias("path")), "said")
        done = []
        for _ in range(length):
            left = now.count()
            if not left:
                break
            at = now.select(key, F.element_at("path", -1).alias("h"))
            words = durable((F.broadcast(at) if left <= BROADCAST_ROWS else at).join(cache, key), "asked")
            m = (1 - self.beta) * F.col("p") + self.beta * F.col("q")
            said = b.scored(words, words.count()).groupBy(key).agg(F.max(F.struct(F.round(m, 12).alias("m"), "w")).alias("said"))
            own = asked(likely, b._sizes[0], at, left, ["h"]).select("h", F.struct(F.round((1 - self.beta) * F.col("p"), 12).alias("m"), "w").alias("own"))
            path = now.withColumn("h", F.element_at("path", -1)).join(own, "h", "left").join(said, key, "left").select(key, "path", F.greatest("own", "said")["w"].alias("w"))
            t, back = F.size("path"), F.array_position("path", F.col("w")).cast("int") - 1
            again = F.transform(F.sequence(F.lit(1), F.lit(length)), lambda i: F.element_at("path", F.when(i < t, i + 1).otherwise(back + F.pmod(i - t, t - back) + 1)))
            out = F.when(F.col("w").isNull(), F.slice("path", 2, length)).when(back >= 0, again)
            step = durable(path.select(key, F.concat("path", F.array("w")).alias("longer"), out.alias("out")), "said")
            done.append(step.where("out IS NOT NULL").select(key, "out"))
            now = step.where("out IS NULL").select(key, F.col("longer").alias("path"))
        done.append(now.select(key, F.slice("path", 2, length).alias("out")))
        return reduce(DataFrame.unionByName, done).select(key, F.array_join("out", " ").alias("generated"))


class PrecomputedTarget:
    """Metrics of a real model from a table: token log-probabilities (lps), token entropies (ents), its answer (generated), its parameter shift (shift)."""

    def __init__(self, table: DataFrame):
        self.table = table
        if "generated" in table.columns:
            self.generate = lambda samples, key="sample_id": samples.select(key).join(table, key).select(key, "generated")
        if "shift" in table.columns:
            self.shift = lambda samples, lr=0.0, key="sample_id": samples.select(key).join(table, key).select(key, F.col("shift").alias("mean_diff"))

    def metrics(self, samples: DataFrame, key: str = "sample_id") -> DataFrame:
        mean = lambda c: F.when(F.size(c) > 0, F.aggregate(c, F.lit(0.0), lambda a, x: a + x) / F.size(c))
        return samples.select(key).join(self.table, key).select(key, (-mean("lps")).alias("loss"), mean("ents").alias("entropy"))


class ArrowBatchTarget:
    """A callable from a pandas frame of samples to one of metrics, loaded once per worker."""

    def __init__(self, make, schema: str):
        self.make, self.schema = make, schema

    def metrics(self, samples: DataFrame, key: str = "sample_id") -> DataFrame:
        make = self.make

        def run(batches):
            score = make()
            for b in batches:
                yield score(b)

        return samples.mapInPandas(run, self.schema)
