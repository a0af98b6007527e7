"""Stage 2: a ten-key rule policy as one native filter."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from poolcurator import schema
from poolcurator.backbone.core import Backbone, CostLedger, ask
from poolcurator.config import Policy, SelectionRequest
from poolcurator.functions import text as X

#: Phrases above this number are searched by one pattern.
PHRASES = 8


def refusal_free(c: str, phrases: tuple[str, ...], case_sensitive: bool = True) -> Column:
    t = X.col(c) if case_sensitive else F.lower(c)
    words = phrases if case_sensitive else tuple(p.lower() for p in phrases)
    if not words:
        return F.lit(True)
    if len(words) > PHRASES:
        return ~t.rlike("|".join(r"\Q" + w.replace(r"\E", r"\E\\E\Q") + r"\E" for w in words))
    out = t.contains(words[0])
    for w in words[1:]:
        out = out | t.contains(w)
    return ~out


def rules(policy: Policy, stored_length: bool = False) -> list[tuple[str, Column]]:
    """The rules in order of cost: lengths, then phrases, then character classes."""
    x, y, t = F.length("instruction"), F.length("output"), F.length("text")
    out = [("required", F.col("instruction").isNotNull() & F.col("output").isNotNull() & F.col("text").isNotNull() & F.col("input").isNotNull())]
    total = (t >= policy.min_total_len) & (t <= policy.max_total_len)
    if stored_length:  # lets the scan skip row groups
        total = (F.col("n_chars") >= policy.min_total_len) & (F.col("n_chars") <= policy.max_total_len) & total
    out += [
        ("total_len", total),
        ("inst_len", x >= policy.min_inst_len),
        ("out_len", y >= policy.min_out_len),
        ("ratio", y >= policy.out_inst_ratio_min * x),
        ("refusal", refusal_free("output", policy.refusal_phrases)),
        ("noise", X.share_of("text", X.unicode_words(policy.noise_regex)) <= policy.max_noise_ratio),
    ]
    if policy.require_en:
        out.append(("english", X.latin_share("text") >= policy.min_en_ratio))
    return out


def compile_policy(policy: Policy, stored_length: bool = False) -> Column:
    """The conjunction, cheap rules first, so that later ones are not evaluated for rejected rows; null where a rule is.

    It is left a plain conjunction, so that the scan takes over what it can.
    """
    test = None
    for _, rule in rules(policy, stored_length):
        test = rule if test is None else test & rule
    return test


def match(samples: DataFrame, policy: Policy, stored_length: bool = False) -> DataFrame:
    missing = [c for c in schema.REQUIRED if c not in samples.columns]
    if missing:
        raise ValueError(f"samples lack the fields {missing}")
    return samples.where(compile_policy(policy, stored_length))


def reject_reasons(samples: DataFrame, policy: Policy) -> DataFrame:
    """samples with the first rule that each fails, or 'kept'."""
    reason = F.lit("kept")
    for name, rule in reversed(rules(policy)):
        reason = F.when(~F.coalesce(rule, F.lit(False)), F.lit(name)).otherwise(reason)
    return samples.withColumn("reason", reason)


def propose_policy(request: SelectionRequest, observations: dict, backbone: Backbone, max_retries: int = 3, ledger: CostLedger | None = None) -> Policy:
    return ask(backbone, "policy", {"request": request.text, "observations": observations, "keys": ", ".join(Policy.keys())}, lambda r: Policy.merge(r, strict=True), max_retries, ledger)
