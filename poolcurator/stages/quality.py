"""Stage 4: a weighted rubric, side-by-side judging in small batches, weighted sum, top k."""

from __future__ import annotations

import json
from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from poolcurator import schema
from poolcurator.backbone.core import Backbone, CostLedger, ask, rough_tokens
from poolcurator.backbone.prompts import render
from poolcurator.config import CascadeConfig, Rubric, SelectionRequest
from poolcurator.functions import text as X
from poolcurator.operators.topk import top_k


def propose_rubric(request: SelectionRequest, observations: dict, backbone: Backbone, max_retries: int = 3, ledger: CostLedger | None = None) -> Rubric:
    return ask(backbone, "rubric", {"request": request.text, "observations": observations}, Rubric.parse, max_retries, ledger)


def assign_batches(df: DataFrame, b: int = 10, seed: int = 42, key: str = "sample_id", ranges: int | None = None) -> DataFrame:
    """df with batch_id: b samples each in seeded order, a function of ids, seed and b alone.

    Small inputs are numbered as a whole. With `ranges`, ids fall into that many ranges of the seeded
    key and each is numbered from where the ranges before it end, so no task sees all rows and batches are the same.
    """
    keyed = df.withColumn("_key", X.seeded_key(key, seed))
    if not ranges:
        rank = F.row_number().over(Window.orderBy("_key", key))
        return keyed.withColumn("batch_id", F.floor((rank - 1) / b).cast("long")).drop("_key")
    # The uniform is the seeded key's beginning, so parts follow each other in the key's order.
    part = F.floor(X.seeded_uniform(key, str(seed)) * ranges).cast("long")
    keyed = keyed.withColumn("_part", part)
    held = keyed.groupBy("_part").agg(F.count(F.lit(1)).alias("_n"))  # `ranges` rows
    before = held.select("_part", (F.sum("_n").over(Window.orderBy("_part")) - F.col("_n")).alias("_before"))
    rank = F.row_number().over(Window.partitionBy("_part").orderBy("_key", key))
    numbered = keyed.withColumn("_rank", rank).join(before, "_part")
    return numbered.withColumn("batch_id", F.floor((F.col("_before") + F.col("_rank") - 1) / b).cast("long")).drop("_key", "_part", "_rank", "_before")


def batch_ranges(n: int, b: int = 10) -> int | None:
    """Ranges of about 100 batches; None while the input is small enough to number as a whole."""
    return None if n <= 100_000 else -(-n // (100 * b))


def render_judge_prompt(rubric: Rubric, batch: list[dict]) -> str:
    lines = "\n".join(f"- {n} ({w:g}): {d}" for n, d, w in rubric.dimensions)
    return render("judge", rubric=lines, samples=json.dumps(batch, ensure_ascii=False))


def score_batches(df: DataFrame, rubric: Rubric, judge: Callable[[str, list[dict]], str], cfg: CascadeConfig = CascadeConfig(), key: str = "sample_id") -> DataFrame:
    """(batch_id, members, raw, tokens_in, tokens_out): the judge's reply to every batch.

    A task works in rounds of `samples_per_round` samples, at most `concurrency` batches at a time. A failed call gives a null reply and is not repeated. Write the result before parsing: a task
    that is run again must not pay again for batches that are already written.
    """
    whole = df.groupBy("batch_id").agg(F.sort_array(F.collect_list(F.struct(F.col(key).alias("sample_id"), "instruction", "input", "output"))).alias("rows"))
    at_once = max(1, min(cfg.concurrency, cfg.samples_per_round // cfg.batch))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        def one(rows) -> tuple[list[int], str | None, int, int]:
            batch = [{k: (int(v) if k == "sample_id" else v) for k, v in r.items()} if isinstance(r, dict) else r.asDict() for r in rows]
            prompt, reply = render_judge_prompt(rubric, batch), None
            try:
                reply = judge(prompt, batch)
            except Exception:  # noqa: BLE001  the round goes on without this batch
                pass
            return [r["sample_id"] for r in batch], reply, rough_tokens(prompt), rough_tokens(reply or "")

        with ThreadPoolExecutor(at_once) as pool:
            for b in batches:
                said = []
                for first in range(0, len(b), at_once):  # one round
                    said += pool.map(one, b["rows"].iloc[first : first + at_once])
                yield pd.DataFrame({"batch_id": b["batch_id"].to_numpy(), **dict(zip(("members", "raw", "tokens_in", "tokens_out"), map(list, zip(*said, strict=True)), strict=True))})

    return whole.mapInPandas(run, "batch_id long, members array<long>, raw string, tokens_in long, tokens_out long")


def bill(raw: DataFrame, ledger: CostLedger) -> None:
    """Adds the judge's calls to the ledger: one a batch, failed ones counted, tokens as sent and received."""
    calls, tokens_in, tokens_out, failed = raw.agg(F.count(F.lit(1)), F.coalesce(F.sum("tokens_in"), F.lit(0)), F.coalesce(F.sum("tokens_out"), F.lit(0)), F.count_if(F.col("raw").isNull())).first()
    ledger.add_many(4, "judge", calls, tokens_in, tokens_out, failures=failed)


def rule_judge(names: list[str]) -> Callable[[str, list[dict]], str]:
    """The offline judge as a callable: replies in JSON with each feature's fifth of the batch, dealt to the dimensions in turn."""

    def judge(prompt: str, batch: list[dict]) -> str:
        texts = [f"{r['instruction'] or ''} {r['output'] or ''}" for r in batch]
        words = [t.lower().split() for t in texts]
        features = [
            [len(set(w)) / len(w) if w else 0.0 for w in words],
            [sum(c.isalnum() or c.isspace() or c in ".,;!?()/" for c in t) / max(1, len(t)) for t in texts],
            [len(t) for t in texts],
        ]
        fifths = []
        for line in features:
            place = {i: p for p, i in enumerate(sorted(range(len(line)), key=lambda i: (line[i], batch[i]["sample_id"])))}
            fifths.append([1 + 5 * place[i] // len(line) for i in range(len(line))])
        return json.dumps([{"sample_id": r["sample_id"], "scores": {n: fifths[j % 3][i] for j, n in enumerate(names)}, "reasoning": "", "flagged": False} for i, r in enumerate(batch)])

    return judge


def parse_verdicts(raw: DataFrame) -> DataFrame:
    """(batch_id, sample_id, dim, q, flagged). A reply has one object per member of its batch, each once; any other gives no rows. Scores that are not 1 to 5 go."""
    v = F.from_json("raw", schema.VERDICT, {"mode": "PERMISSIVE"})
    rows = raw.withColumn("v", v).withColumn("ids", F.col("v.sample_id"))
    whole = (F.size("ids") == F.size("members")) & (F.size(F.array_distinct("ids")) == F.size("ids")) & (F.size(F.array_except("ids", "members")) == 0)
    rows = rows.where(whole).select("batch_id", "members", F.explode("v").alias("v"))
    dims = rows.select("batch_id", "members", F.col("v.sample_id").alias("sample_id"), F.coalesce("v.flagged", F.lit(False)).alias("flagged"), F.explode("v.scores").alias("dim", "q"))
    return dims.where(F.col("q").between(1, 5)).select("batch_id", "sample_id", "dim", "q", "flagged")


def apply_flags(df: DataFrame, drop_flagged: bool = False) -> DataFrame:
    return df.where(~F.col("flagged")) if drop_flagged else df


def quality_score(verdicts: DataFrame, weights: dict[str, float], key: str = "sample_id") -> DataFrame:
    """(key, q): the weighted sum of a sample's dimensions; a sample that lacks one has no score."""
    table = verdicts.sparkSession.createDataFrame(list(weights.items()), "dim string, z double")
    agg = verdicts.join(F.broadcast(table), "dim").groupBy(key).agg(F.sum(F.col("z") * F.col("q")).alias("q"), F.count_distinct("dim").alias("n"))
    return agg.where(F.col("n") == len(weights)).select(key, "q")


#: The offline judge's features; each becomes a fifth of its batch.
RULE_DIMENSIONS = ("d1", "d2", "d3")


def rule_scores(df: DataFrame, key: str = "sample_id") -> DataFrame:
    """(batch_id, key, d1, d2, d3): fifths within the batch of variety, cleanness and length. Scores depend on the batch mates."""
    from poolcurator.functions.text import noise_class, share_of, unique_share

    f = df.select("batch_id", key, F.round(unique_share("text"), 6).alias("variety"), F.round(1 - share_of("text", noise_class()), 6).alias("clean"), F.length("text").alias("length"))
    fifth = lambda c: F.ntile(5).over(Window.partitionBy("batch_id").orderBy(c, key))
    return f.select("batch_id", key, fifth("variety").alias("d1"), fifth("clean").alias("d2"), fifth("length").alias("d3"))


def rule_verdicts(df: DataFrame, rubric_names: list[str], key: str = "sample_id") -> DataFrame:
    """The offline judge's verdicts, its three features dealt to the rubric's dimensions in turn."""
    scores = rule_scores(df, key)
    dims = F.explode(F.array(*[F.struct(F.lit(n).alias("dim"), F.col(RULE_DIMENSIONS[i % 3]).alias("q")) for i, n in enumerate(rubric_names)]))
    return scores.select("batch_id", key, dims.alias("v")).select("batch_id", key, "v.dim", "v.q", F.lit(False).alias("flagged"))


def best_by_quality(scored: DataFrame, k: int, key: str = "sample_id") -> DataFrame:
    """Top k by q; unscored samples last, ties by the stage-3 score, then id."""
    return top_k(scored, "q", k, key, ties=("score",))
