"""Secrets in documents: rules find candidates, a random forest removes false findings.

A candidate is a value in a white-space separated token that looks like a credential: a run of 16 or more key
characters, or a value of any length assigned to a name such as password or token, in the same token or in the
one after `=` or `:`. Every different value of a token is a candidate of its own. The forest sees the value's
length, its character transitions, the share of it that dictionary words cover, path signs in the token and
the words beside it. Transitions are changes between lower case, upper case, digits and signs, and the mean
log odds of the value's character pairs: how much likelier each next character is among labelled secrets than
among false findings, from two first-order tables with 41 signs a side. Forest and tables are trained on
labelled findings; where the caller has none, on a seeded table of made-up findings of both kinds
(`made_up_findings`), whose length is a parameter.

Everything is DataFrame functions and JVM trees: one narrow pass over whole texts, no shuffle.

Defined cases: null and empty texts have no candidates; repeated rows repeat their findings; ties in the
forest's vote count as no secret; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.ml.classification import RandomForestClassificationModel, RandomForestClassifier
from pyspark.ml.feature import VectorAssembler
from pyspark.ml.functions import vector_to_array
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from poolcurator.llm.store import pick, write_table

# Names that secrets are assigned to, words that fill placeholders and code, words that announce harmless digests.
NAMES = "password|passwd|passphrase|pwd|secret|token|apikey|api_key|api-key|access_key|auth|bearer|credential|private_key"
DICTIONARY = (
    "password|example|sample|secret|token|changeme|default|test|user|admin|demo|dummy|your|here|key|value|none|null|true|false|"
    "function|class|object|string|number|config|service|server|client|handler|request|response|version|release|build|index|"
    "image|page|file|path|http|https|www|html|data|name|type|list|item|model|table|column|query|the|and|for|with|this|that|"
    "tion|ing|ment|ness|able|lich|keit|heit|ung|schaft|ment|eux|eau|elle|aire|mente|ción|ado|oso"
)
DIGEST_WORDS = "commit|sha1|sha256|md5|checksum|digest|etag|revision|uuid|hash|id"

NAMED = rf"(?i)({NAMES})[\"']?\s*[=:]"
RUN = r"[A-Za-z0-9+/_\-]{16,}"
#: A value may hold the next assignment: the look-ahead lets matches overlap, and the second form ends at the signs that part assignments.
ASSIGNED = rf"(?i)(?:{NAMES})[\"']?[=:](?=[\"']?([^\s\"',;]+))"
ASSIGNED_PART = rf"(?i)(?:{NAMES})[\"']?[=:](?=[\"']?([^\s\"',;&|?#}}]+))"
FEATURES = ("odds", "n", "digits", "upper", "lower", "signs", "kinds", "changes", "vowels", "hex", "distinct", "covered", "slashes", "dots", "named", "named_before", "digest_before", "quoted", "prefixed")


def candidates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, word, token, before, before2, after, value, at) of every candidate.

    word counts white-space separated tokens from 0; at is the value's first place in its token, from 1.
    """
    tokens = F.split(F.coalesce(F.col(text_col), F.lit("")), r"[\x20\x09-\x0D]+")
    rows = pick(docs, id_col, text_col).select(F.col(id_col).alias("id"), tokens.alias("t"))

    def near(i, k: int) -> F.Column:
        return F.when(i > k, F.try_element_at("t", F.greatest(i - k, F.lit(1)))).otherwise("")

    def looks(i) -> F.Column:
        x, last = F.try_element_at("t", i), near(i, 1)
        apart = (F.endswith(last, F.lit("=")) | F.endswith(last, F.lit(":"))) & F.concat_ws(" ", near(i, 2), last).rlike(NAMED + "$")
        return (F.length(x) > 0) & (((F.length(x) >= 16) & x.rlike(RUN)) | x.rlike(ASSIGNED) | apart)

    places = F.filter(F.sequence(F.lit(1), F.size("t")), looks)
    found = F.transform(
        places,
        lambda i: F.struct((i - 1).alias("word"), F.try_element_at("t", i).alias("token"), near(i, 1).alias("before"), near(i, 2).alias("before2"), F.coalesce(F.try_element_at("t", i + 1), F.lit("")).alias("after")),
    )
    out = rows.select("id", F.explode(found).alias("c")).select("id", "c.*")
    every = [F.regexp_extract_all("token", F.lit(x), F.lit(1)) for x in (ASSIGNED, ASSIGNED_PART, rf"({RUN}={{0,2}})")]
    # Of a token after a name, what its opening quote holds, or all of it.
    own = F.when(F.col("token").rlike("^[\"']"), F.regexp_extract("token", "^([\"'])(.*?)(?:\\1|$)", 2)).otherwise(F.regexp_replace("token", "[\"',;]", ""))
    apart = F.when(F.concat_ws(" ", "before2", "before").rlike(NAMED + "$"), F.array(own)).otherwise(F.array().cast("array<string>"))
    values = F.array_distinct(F.filter(F.concat(*every, apart), lambda v: v != ""))
    return out.withColumn("value", F.explode(values)).withColumn("at", F.expr("greatest(locate(value, token), 1)"))


#: Signs of the transition tables: letters (capitals are marked apart), digits, marks of keys; all else is one sign.
SIGNS = "abcdefghijklmnopqrstuvwxyz0123456789^+/_-"


def character_pairs(value) -> F.Column:
    """The pairs of neighbouring signs of a value: every capital is ^ and its letter, every other character outside SIGNS is a dash."""
    marked = F.regexp_replace(value, "([A-Z])", "^$1")
    plain = F.regexp_replace(F.lower(marked), r"[^a-z0-9^+/_\-]", "-")
    # Bound to a variable, so that the replacements run once and not per pair.
    cut = F.transform(F.array(plain), lambda p: F.transform(F.sequence(F.lit(1), F.greatest(F.length(p) - 1, F.lit(1))), lambda i: F.substring(p, i, F.lit(2))))
    return F.get(cut, F.lit(0))


def transition_odds(labelled: DataFrame) -> dict[str, float]:
    """Log odds of the second sign of every pair after its first, secrets against false findings, add-one smoothed."""
    pairs = labelled.select("label", F.explode(character_pairs(F.col("value"))).alias("pair")).where(F.length("pair") == 2)
    counts = {(r.pair, r.label): r.n for r in pairs.groupBy("pair", "label").agg(F.count(F.lit(1)).alias("n")).collect()}  # at most two per pair of signs
    total: dict[tuple[str, float], int] = {}
    for (pair, label), n in counts.items():
        total[pair[0], label] = total.get((pair[0], label), 0) + n

    def p(pair: str, label: float) -> float:
        return (counts.get((pair, label), 0) + 1) / (total.get((pair[0], label), 0) + len(SIGNS))

    return {a + b: math.log(p(a + b, 1.0) / p(a + b, 0.0)) for a in SIGNS for b in SIGNS}


@dataclass
class SecretModel:
    """The forest, and the transition table that makes one of its features."""

    forest: RandomForestClassificationModel
    odds: dict[str, float]


def with_features(found: DataFrame, odds: dict[str, float]) -> DataFrame:
    """The findings with one double column per feature."""
    v, low = F.col("value"), F.lower("value")
    table = F.broadcast(found.sparkSession.createDataFrame([(odds,)], "_odds map<string,double>"))  # one row
    found = found.crossJoin(table)
    pairs = character_pairs(v)
    n = F.greatest(F.length(v), F.lit(1)).cast("double")

    def share(pattern: str) -> F.Column:
        return F.regexp_count(v, F.lit(pattern)) / n

    beside = F.concat_ws(" ", "before2", "before")
    flag = lambda c: c.cast("double")
    return found.withColumns(
        {
            "odds": F.aggregate(pairs, F.lit(0.0), lambda a, x: a + F.coalesce(F.try_element_at("_odds", x), F.lit(0.0))) / n,
            "n": n,
            "digits": share("[0-9]"),
            "upper": share("[A-Z]"),
            "lower": share("[a-z]"),
            "signs": share("[^A-Za-z0-9]"),
            "kinds": flag(v.rlike("[0-9]").cast("int") + v.rlike("[A-Z]").cast("int") + v.rlike("[a-z]").cast("int") + v.rlike("[^A-Za-z0-9]").cast("int")),
            "changes": F.regexp_count(v, F.lit("(?<=[a-z])(?=[A-Z0-9])|(?<=[A-Z])(?=[a-z0-9])|(?<=[0-9])(?=[A-Za-z])")) / n,
            "vowels": F.regexp_count(low, F.lit("(?<=[a-z&&[^aeiou]])[aeiou]")) / n,
            "hex": flag(v.rlike("^[0-9a-fA-F-]+$")),
            "distinct": F.size(F.array_distinct(F.split(v, ""))) / n,
            "covered": 1 - F.length(F.regexp_replace(low, DICTIONARY, "")) / n,
            "slashes": F.regexp_count("token", F.lit("[/\\\\]")) / n,
            "dots": F.regexp_count("token", F.lit(r"\.|://|@")) / n,
            "named": flag(F.expr("left(token, locate(value, token) - 1)").rlike(NAMED + "[\"']?$")),
            "named_before": flag(beside.rlike(rf"(?i)({NAMES})")),
            "digest_before": flag(beside.rlike(rf"(?i)\b({DIGEST_WORDS})\b")),
            "quoted": flag(F.col("token").rlike("[\"']")),
            "prefixed": flag(v.rlike("^(AKIA|ASIA|ghp_|gho_|glpat-|xox[abp]-|sk_live_|sk-|AIza|eyJ|npm_)")),
        }
    )


def made_up_findings(spark: SparkSession, rows: int = 4_000, seed: int = 42) -> DataFrame:
    """Labelled findings (token, before, before2, after, value, label) of ten true and ten false kinds, from seeded hashes."""
    # One partition: the trees' sampling depends on the order of rows.
    base = spark.range(0, rows, 1, 1)
    h = F.sha2(F.concat_ws(":", F.lit(str(seed)), "id").cast("binary"), 512)
    b64 = F.regexp_replace(F.base64(F.unhex(h)), "[=\n\r]", "")
    up = F.upper(F.translate(F.conv(F.substring(h, 1, 15), 16, 36), "o", "q"))
    long_up = F.concat(up, F.upper(F.conv(F.substring(h, 20, 15), 16, 36)), F.upper(F.conv(F.substring(h, 40, 15), 16, 36)))
    size = F.pmod(F.xxhash64("id", F.lit(1)), F.lit(24)).cast("int")
    parts = F.split(F.lit("con ver ta re mo li ca dis pre su per tion ing ment ne sa der un auf ent lo que ra mi"), " ")
    word = F.array_join(F.transform(F.sequence(F.lit(1), F.lit(4) + size % 5), lambda i: F.element_at(parts, (F.pmod(F.xxhash64("id", i), F.lit(24)) + 1).cast("int"))), "")
    num = F.conv(F.substring(h, 1, 12), 16, 10)
    plain = F.element_at(F.split(F.lit("the of and in it is was see at from"), " "), (F.pmod(F.xxhash64("id", F.lit(3)), F.lit(10)) + 1).cast("int"))
    hexes = F.substring(h, F.lit(1), F.lit(16) + size)
    kinds = [
        (F.concat(F.lit("AKIA"), F.substring(long_up, 1, 16)), "", "", 1),
        (F.concat(F.lit("ghp_"), F.substring(b64, 1, 36)), "", "", 1),
        (F.concat(F.lit("sk_live_"), F.substring(b64, 5, 24)), "", "", 1),
        (hexes, "password=", "", 1),
        (hexes, "", "=", 1),
        (F.substring(b64, F.lit(1), F.lit(20) + size), "", "=", 1),
        (F.substring(b64, F.lit(1), F.lit(16) + size), "secret:", "", 1),
        (F.substring(h, F.lit(1), F.lit(32)), "api_key=", "", 1),
        (F.concat(F.lit("xoxb-"), F.substring(h, 1, 24)), "", "", 1),
        (F.substring(b64, F.lit(2), F.lit(12) + size % 8), "token:", "", 1),
        (F.concat(word, F.lit("-"), word, size), "", "", 0),
        (F.concat(F.lit("/"), word, F.lit("/"), word, F.lit("/"), word, size), "", "", 0),
        (F.substring(h, 1, 40), "", "commit", 0),
        (F.concat_ws("-", F.substring(h, 1, 8), F.substring(h, 9, 4), F.substring(h, 13, 4), F.substring(h, 17, 4), F.substring(h, 21, 12)), "", "id", 0),
        (F.concat(F.lit("your_"), word, F.lit("_password1")), "password=", "", 0),
        (F.concat(F.lit("changeme"), size), "password=", "", 0),
        (F.concat(num, num), "", "", 0),
        (F.concat(F.lit("2024-01-"), size, F.lit("T10-00-00-"), word), "", "", 0),
        (F.concat(F.initcap(word), F.lit("Handler"), size, F.initcap(word)), "", "", 0),
        (F.concat(F.lit("xxxxxxxxxxxxxxxx"), size), "token=", "", 0),
    ]
    kind = F.pmod("id", F.lit(len(kinds)))

    def choose(values) -> F.Column:
        out = F.lit(None)
        for i, x in enumerate(values):
            out = F.when(kind == i, x).otherwise(out)
        return out

    value = choose([k[0] for k in kinds])
    lead = choose([F.lit(k[1]) for k in kinds])
    near = choose([F.lit(k[2]) for k in kinds])
    return base.select(
        value.alias("value"),
        F.concat(lead, F.when(near == "=", F.concat(F.lit('"'), value, F.lit('"'))).otherwise(value)).alias("token"),
        F.when(near == "", plain).otherwise(near).alias("before"),
        F.when(near == "=", F.element_at(F.split(F.lit("token secret password apikey"), " "), (F.pmod(F.xxhash64("id", F.lit(5)), F.lit(4)) + 1).cast("int"))).otherwise(plain).alias("before2"),
        plain.alias("after"),
        choose([F.lit(k[3]) for k in kinds]).cast("double").alias("label"),
    )


def train_forest(labelled: DataFrame, trees: int = 30, depth: int = 7, seed: int = 42) -> SecretModel:
    """A model from findings with a column label of 0 or 1.

    Half of the findings, by hash, teach the transitions and the other half the forest, which so sees odds of values
    that the table has not counted.
    """
    half = F.pmod(F.xxhash64("value", "token"), F.lit(2)) == 0
    odds = transition_odds(labelled.where(half))
    seen, _ = write_table(with_features(labelled.where(~half), odds).select("label", *FEATURES), "findings")  # trees pass over it many times
    rows = VectorAssembler(inputCols=list(FEATURES), outputCol="features").transform(seen.coalesce(1))
    return SecretModel(RandomForestClassifier(numTrees=trees, maxDepth=depth, seed=seed, maxMemoryInMB=128).fit(rows), odds)


def held_out_rates(model: SecretModel, labelled: DataFrame, at: float = 0.5) -> tuple[float, float]:
    """(precision, recall) of the model on labelled findings."""
    rows = VectorAssembler(inputCols=list(FEATURES), outputCol="features").transform(with_features(labelled, model.odds))
    said = model.forest.transform(rows).select("label", (F.get(vector_to_array("probability"), F.lit(1)) > at).alias("said"))
    tp, fp, fn = said.agg(F.count_if(F.col("said") & (F.col("label") == 1)), F.count_if(F.col("said") & (F.col("label") == 0)), F.count_if(~F.col("said") & (F.col("label") == 1))).first()
    return tp / max(1, tp + fp), tp / max(1, tp + fn)


def scan_secrets(docs: DataFrame, model: SecretModel, id_col: str = "doc_id", text_col: str = "text", at: float = 0.5) -> DataFrame:
    """(id, word, kind, value_sha256, score, secret) of every candidate; secret where the score is above `at`."""
    found = with_features(candidates(docs, id_col, text_col), model.odds)
    rows = VectorAssembler(inputCols=list(FEATURES), outputCol="features", handleInvalid="keep").transform(found)
    scored = model.forest.transform(rows)
    kind = F.when(F.col("prefixed") > 0, F.lit("provider")).when(F.col("named") + F.col("named_before") > 0, F.lit("assigned")).otherwise(F.lit("generic"))
    score = F.round(F.get(vector_to_array("probability"), F.lit(1)), 6)
    return scored.select(F.col("id").alias(id_col), F.col("word").cast("long").alias("word"), kind.alias("kind"), F.sha2("value", 256).alias("value_sha256"), score.alias("score"), (score > at).alias("secret"))
