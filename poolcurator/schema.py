"""Declared schemas of samples, configurations and results."""

from __future__ import annotations

from pyspark.sql import types as T

SAMPLE = "sample_id long, pool string, instruction string, input string, output string, text string, lang string, source string, n_chars long"
OBSERVATION = "stage int, probe string, key string, value string, ord int"
POLICY = (
    "min_total_len int, max_total_len int, min_inst_len int, min_out_len int, out_inst_ratio_min double, "
    "refusal_phrases array<string>, noise_regex string, max_noise_ratio double, require_en boolean, min_en_ratio double"
)
WEIGHTS = "loss double, entropy double, drift double, mean_diff double"
RUBRIC = "map<string, struct<description: string, weight: double>>"
VERDICT = "array<struct<sample_id: bigint, scores: map<string, int>, reasoning: string, flagged: boolean>>"
METRIC = "sample_id long, loss double, entropy double, drift double, mean_diff double"
SELECT = "sample_id long, stage int, score double, rank int"
LEDGER = "run_id string, stage int, prompt_kind string, calls long, tokens_in long, tokens_out long, retries long, failures long, usd decimal(18,6)"

REQUIRED = ("instruction", "input", "output", "text")

#: Physical schemas of the given tables, so that reading needs no inference.
TABLES = {
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "conversations": "conv_id long, turn long, role string, text string",
    "labels": "doc_id long, quality int, toxic int",
    "benchmark": "item_id long, text string",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "pages": "page_id long, url string, html string",
}


def struct(ddl: str) -> T.StructType:
    return T.StructType.fromDDL(ddl)
