"""Measures over answers and score tables (model, pool, benchmark, method, score)."""

from __future__ import annotations

import re
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

CONTROL = "Full Pool"
SCORES = "model string, pool string, benchmark string, method string, score double"


def normal_answer(c: str) -> Column:
    """Lower case, trimmed, without dollar signs, thousands commas and a final full stop."""
    t = F.lower(F.trim(F.regexp_replace(c, r"[ \t\r\n]+", " ")))
    t = F.regexp_replace(t, r"\$", "")
    t = F.regexp_replace(t, r"([0-9]),([0-9]{3})", "$1$2")
    return F.regexp_replace(t, r"\.$", "")


def as_number(c: Column) -> Column:
    """The value of a decimal or of a fraction of whole numbers; else null."""
    top, bottom = F.regexp_extract(c, r"^(-?[0-9]+)/([0-9]+)$", 1), F.regexp_extract(c, r"^(-?[0-9]+)/([0-9]+)$", 2)
    fraction = F.when(top != "", top.try_cast("double") / F.nullif(bottom.try_cast("double"), F.lit(0.0)))
    return F.coalesce(fraction, F.when(c.rlike(r"^-?[0-9]+(\.[0-9]+)?$"), c.try_cast("double")))


def same_answer(predicted: str = "predicted", gold: str = "gold") -> Column:
    p, g = normal_answer(predicted), normal_answer(gold)
    return F.coalesce((p == g) | (F.abs(as_number(p) - as_number(g)) < 1e-9), F.lit(False))


def answer_accuracy(df: DataFrame) -> DataFrame:
    return df.agg(F.round(100 * F.avg(same_answer().cast("double")), 2).alias("accuracy"))


def chosen_option(c: str) -> Column:
    """The option letter that an answer names last in brackets or after 'answer', else its first letter alone."""
    named = F.regexp_extract(c, r"(?i)answer(?: is)?:? *\(?([a-e])\b", 1)
    return F.upper(F.when(named != "", named).otherwise(F.regexp_extract(c, r"^\(?([A-Ea-e])\b", 1)))


def choice_accuracy(df: DataFrame) -> DataFrame:
    return df.agg(F.round(100 * F.avg((chosen_option("predicted") == F.upper("gold")).cast("double")), 2).alias("accuracy"))


def pass_at_1(results: DataFrame) -> DataFrame:
    """Share of problems whose one completion passes all its tests."""
    return results.groupBy("item_id").agg(F.bool_and("passed").alias("ok")).agg(F.round(100 * F.avg(F.col("ok").cast("double")), 2).alias("pass_at_1"))


def setting_mean(scores: DataFrame) -> DataFrame:
    return scores.groupBy("model", "pool", "method").agg(F.round(F.round(F.avg("score"), 9), 2).alias("score"))


def rank_methods(scores: DataFrame, by: tuple[str, ...] = ("model", "pool"), exclude: tuple[str, ...] = (CONTROL,)) -> DataFrame:
    """scores with place: dense rank by falling score, ties share a place."""
    w = Window.partitionBy(*by).orderBy(F.desc("score"))
    return scores.where(~F.col("method").isin(list(exclude))).withColumn("place", F.dense_rank().over(w))


def against(scores: DataFrame, method: str, others: tuple[str, ...], by: tuple[str, ...]) -> DataFrame:
    """One row per setting: the method's score, the best of the others, and the difference."""
    own = F.max(F.when(F.col("method") == method, F.col("score")))
    best = F.max(F.when(F.col("method").isin(list(others)), F.col("score")))
    return scores.groupBy(*by).agg(own.alias("own"), best.alias("best")).withColumn("gain", F.round(F.col("own") - F.col("best"), 6))


def win_counts(scores: DataFrame, method: str, others: tuple[str, ...], by: tuple[str, ...], margin: float = 0.0, strict: bool = True) -> tuple[int, int]:
    """(wins, settings); shared first places count unless strict."""
    g = against(scores, method, others, by)
    test = F.col("gain") > 0 if strict and not margin else F.col("gain") >= margin - 1e-9
    return tuple(g.agg(F.count_if(test), F.count(F.lit(1))).first())


def gain_range(scores: DataFrame, method: str, others: tuple[str, ...], by: tuple[str, ...]) -> tuple[float, float]:
    return tuple(against(scores, method, others, by).agg(F.round(F.min("gain"), 2), F.round(F.max("gain"), 2)).first())


def margin_count(scores: DataFrame, method: str, other: str, by: tuple[str, ...], margin: float = 1.0) -> int:
    return win_counts(scores, method, (other,), by, margin)[0]


def reduction(n: int, k: int) -> float:
    return n / k


def pick_shared_lr(scores: DataFrame) -> DataFrame:
    """Per setting, the learning rate with the best mean over methods, and every method's score there."""
    mean = scores.groupBy("setting", "lr").agg(F.avg("score").alias("mean"))
    best = mean.groupBy("setting").agg(F.max_by("lr", F.struct(F.round("mean", 9), -F.col("lr"))).alias("lr"))
    return scores.join(best, ["setting", "lr"])


def final_epoch(scores: DataFrame) -> DataFrame:
    return scores.groupBy("setting", "method", "lr", "benchmark").agg(F.max_by("score", "epoch").alias("score"))


#: Chat markers: angle brackets with bars, and bracketed instruction or header marks.
MARKER = r"<\|[A-Za-z0-9_]+\|>|\[/?INST\]|<</?SYS>>|<(?:start|end)_of_turn>"


def strip_template_tokens(c: str) -> Column:
    return F.trim(F.regexp_replace(c, MARKER, ""))


def count_leaks(df: DataFrame, c: str = "text") -> DataFrame:
    return df.agg(F.count_if(F.regexp_count(F.col(c), F.lit(MARKER)) > 0).alias("rows"), F.coalesce(F.sum(F.regexp_count(F.col(c), F.lit(MARKER))), F.lit(0)).alias("markers"))


def scores_from_markdown(spark: SparkSession, path: str, section: int) -> DataFrame:
    """A printed score table as long rows, read by its header; section is the heading's number in the file.

    Files of published numbers are parameters: none is part of the library.
    """
    body = re.split(r"(?m)^## ", Path(path).read_text())[section]
    lines = [[c.strip() for c in x.strip().strip("|").split("|")] for x in body.splitlines() if x.startswith("|")]
    head = lines[0]
    known = {"Line": None, "Target model": "model", "Pool": "pool", "Target": "target", "Benchmark": "benchmark"}
    rows = []
    for x in lines[2:]:
        facts = {known[h]: v for h, v in zip(head, x, strict=True) if known.get(h)}
        for h, v in zip(head, x, strict=True):
            if h not in known:
                rows.append((facts.get("model") or facts.get("target") or "", facts.get("pool") or "", facts.get("benchmark") or "", h, float(v)))
    return spark.createDataFrame(rows, SCORES)
