"""Read-only looks at a pool for the configuration prompts."""

from __future__ import annotations

import re

from pyspark.errors import PySparkException
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from poolcurator.backbone.core import Backbone, CostLedger, ask
from poolcurator.config import SelectionRequest
from poolcurator.functions import text as X
from poolcurator.operators.topk import random_k


def stats(df: DataFrame) -> DataFrame:
    """One row: size, null counts, length quantiles and means, character shares; a single fused aggregate."""
    x, y, t = F.length("instruction"), F.length("output"), F.length("text")
    return df.agg(
        F.count(F.lit(1)).alias("n"),
        F.count_if(F.coalesce(y, F.lit(0)) == 0).alias("empty_output"),
        F.round(F.avg(x), 6).alias("mean_x"),
        F.round(F.avg(y), 6).alias("mean_y"),
        F.min(t).alias("min_t"),
        F.max(t).alias("max_t"),
        F.round(F.avg(X.share_of("text", X.noise_class())), 6).alias("noise"),
        F.round(F.avg(X.latin_share("text")), 6).alias("latin"),
    )


def nulls(df: DataFrame) -> DataFrame:
    fields = ("instruction", "input", "output", "text", "lang", "source")
    return df.agg(*[F.count_if(F.col(c).isNull() | (F.col(c) == "")).alias(c) for c in fields])


def lengths(df: DataFrame, exact: bool = False) -> DataFrame:
    """Quantiles of the text's length and of the output/instruction ratio; sketches unless exact."""
    t, ratio = F.length("text").cast("double"), F.length("output") / F.nullif(F.length("instruction"), F.lit(0))
    q = F.percentile if exact else (lambda c, p: F.percentile_approx(c, p, F.lit(10_000)))
    out = [F.round(q(t, F.lit(p)), 6).alias(f"t_{int(p * 100)}") for p in (0.1, 0.5, 0.9)]
    out += [F.round(q(ratio, F.lit(p)), 6).alias(f"r_{int(p * 100)}") for p in (0.1, 0.5, 0.9)]
    return df.agg(*out, F.round(F.stddev_samp(t), 6).alias("t_sd"))


def charset(df: DataFrame) -> DataFrame:
    shares = {"noise": X.noise_class(), "latin": "[A-Za-z]", "digit": "[0-9]", "upper": "[A-Z]"}
    return df.agg(*[F.round(F.avg(X.share_of("text", p)), 6).alias(n) for n, p in shares.items()])


def value_counts(df: DataFrame, column: str) -> DataFrame:
    return df.groupBy(column).agg(F.count(F.lit(1)).alias("n"))


def duplicates(df: DataFrame) -> DataFrame:
    """Exact duplicate groups by digest; the digests are added up in the tasks first."""
    return df.groupBy(F.md5("text").alias("digest")).agg(F.count(F.lit(1)).alias("n")).where("n > 1")


def vocabulary(df: DataFrame, n: int = 20) -> DataFrame:
    rows = X.explode_rows(df, [], X.tokens("text"), "token").groupBy("token").agg(F.count(F.lit(1)).alias("n"))
    return rows.orderBy(F.desc("n"), "token").limit(n)


def histogram(df: DataFrame, value, lo: float, hi: float, bins: int) -> DataFrame:
    return df.select(F.width_bucket(value.cast("double"), F.lit(lo), F.lit(hi), F.lit(bins)).alias("bucket")).groupBy("bucket").agg(F.count(F.lit(1)).alias("n"))


def preview(df: DataFrame, n: int = 5, seed: int = 42, chars: int = 200) -> DataFrame:
    return random_k(df, n, seed).select("sample_id", F.substring("instruction", 1, chars).alias("instruction"), F.substring("output", 1, chars).alias("output"))


class UnsafeQuery(ValueError):
    """A query that is not a plain SELECT over the pool."""


_FORBIDDEN = re.compile(r"\b(insert|update|delete|merge|drop|create|alter|truncate|set|reset|add|cache|uncache|refresh|msck|load|grant|revoke|use|call|execute|describe|explain|show|reflect|java_method|try_reflect)\b", re.IGNORECASE)


def guarded_select(df: DataFrame, query: str, limit: int = 100) -> DataFrame:
    """A model-written SELECT over the single view `pool`, at most `limit` rows.

    Commands, writes, other relations, files and functions that reach outside are refused; analysis
    scripts are not run at all.
    """
    body = query.strip().rstrip(";")
    bare = re.sub(r"'(?:[^']|'')*'", "''", body)
    if ";" in bare or "`" in bare or not re.match(r"(?is)^\s*select\b", bare) or _FORBIDDEN.search(bare):
        raise UnsafeQuery("one SELECT statement only")
    relations = re.findall(r"(?is)\b(?:from|join)\s+([^\s,()]+)", bare)
    if any(r.lower() != "pool" for r in relations) or re.search(r"(?is)\bfrom\s+pool\s*,|range\s*\(|read_files|\btable\s*\(", bare):
        raise UnsafeQuery("pool is the only relation")
    return df.sparkSession.sql(f"SELECT * FROM ({body.replace('{', '{{').replace('}', '}}')}) LIMIT {int(limit)}".replace("FROM pool", "FROM {pool}").replace("from pool", "from {pool}"), pool=df)


#: Probes that a model may ask for, each a bounded number of rows.
PROBES = {
    "nulls": nulls,
    "lengths": lengths,
    "charset": charset,
    "languages": lambda df: value_counts(df, "lang").orderBy(F.desc("n"), "lang").limit(20),
    "sources": lambda df: value_counts(df, "source").orderBy(F.desc("n"), "source").limit(20),
    "duplicates": lambda df: duplicates(df).agg(F.count(F.lit(1)).alias("groups"), F.coalesce(F.sum("n"), F.lit(0)).alias("rows")),
    "vocabulary": vocabulary,
}


def inspect_pool(df: DataFrame, stage: int, backbone: Backbone | None = None, request: SelectionRequest | None = None, ledger: CostLedger | None = None) -> dict:
    """Compact facts for a prompt: one fused aggregate and a preview; then the probes and guarded queries that the backbone asks for.

    A query that is refused or fails is answered by the reason, and the run goes on.
    """
    row = stats(df).first().asDict()
    facts = {"stage": stage, "schema": [f"{f.name} {f.dataType.simpleString()}" for f in df.schema.fields], "stats": row, "preview": [r.asDict() for r in preview(df, 3).collect()]}
    if backbone is None or request is None or not getattr(backbone, "inspects", False):
        return facts

    def parse(reply) -> tuple[list[str], list[str]]:
        probes, queries = list(reply["probes"]), list(reply["queries"])
        if not set(probes) <= set(PROBES) or not all(isinstance(q, str) for q in queries):
            raise ValueError("unknown probe")
        return probes, queries

    probes, queries = ask(backbone, "inspect", {"request": request.text, "stage": stage, "observations": facts, "probes": ", ".join(PROBES)}, parse, ledger=ledger, stage=stage)
    facts["probes"] = {p: [r.asDict() for r in PROBES[p](df).collect()] for p in probes}
    facts["queries"] = {}
    for q in queries:
        try:
            facts["queries"][q] = [r.asDict() for r in guarded_select(df, q).collect()]
        except (UnsafeQuery, PySparkException) as e:
            facts["queries"][q] = f"refused: {str(e).splitlines()[0][:200]}"
    return facts


def observations(df: DataFrame, stage: int) -> DataFrame:
    """The fused statistics in the long layout (stage, probe, key, value, ord)."""
    row = stats(df)
    names = row.columns
    pairs = F.explode(F.array(*[F.struct(F.lit(n).alias("key"), F.col(n).cast("string").alias("value"), F.lit(i).alias("ord")) for i, n in enumerate(names)]))
    return row.select(pairs.alias("o")).select(F.lit(stage).alias("stage"), F.lit("stats").alias("probe"), "o.key", "o.value", "o.ord")
