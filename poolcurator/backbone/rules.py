"""A deterministic stand-in for the chat model: cues in the request decide the configuration."""

from __future__ import annotations

import json
import re
from collections import Counter
from collections.abc import Mapping
from typing import Any

from poolcurator.config import Policy

# Language names and codes.
LANGUAGES = {"english": "en", "german": "de", "french": "fr", "spanish": "es"}

#: Words in a request that raise a metric's weight.
WEIGHT_CUES = {
    "loss": ("hard", "rare", "special", "difficult", "challenging", "non-trivial"),
    "entropy": ("weak", "unsure", "uncertain", "gaps", "diverse"),
    "drift": ("step", "structured", "form", "format", "laid out", "style"),
    "mean_diff": ("clean", "reliable", "tidy", "accurate", "junk", "good"),
}
#: Words in a request that bring a rubric dimension, with its description.
RUBRIC_CUES = {
    "correctness": (("accurate", "correct", "reliable", "precise", "term"), "Statements hold and terms are used precisely."),
    "rigour": (("step", "reason", "laid out", "answer"), "The answer follows from steps that are all there."),
    "cleanness": (("clean", "tidy", "junk", "structured"), "The text is free of noise and well laid out."),
    "depth": (("non-trivial", "hard", "challenging"), "The sample teaches something that is not obvious."),
}


class TaxonomyMatcher:
    """Which clusters serve a field: one fitting name is enough, and a sub-field serves its parents."""

    def __init__(self, parents: Mapping[str, str] | None = None):
        self.parents = dict(parents or {})

    def lineage(self, name: str) -> list[str]:
        out = [name]
        while out[-1] in self.parents and self.parents[out[-1]] not in out:
            out.append(self.parents[out[-1]])
        return out

    def match(self, wanted: list[str], clusters: Mapping[int, list[str]]) -> list[int]:
        if not wanted:
            return sorted(clusters)
        return sorted(c for c, names in clusters.items() if any(w in self.lineage(n) for n in names for w in wanted))


class RuleBackbone:
    """Answers every kind of prompt from the request's words and the slots."""

    def __init__(self, parents: Mapping[str, str] | None = None, temperature: float = 0.01):
        self.matcher, self.temperature = TaxonomyMatcher(parents), temperature

    inspects = True

    def _inspect(self, s) -> str:
        """Looks closer where the request's words or the first facts call for it."""
        asked = s["request"].lower()
        probes = ["charset"] if any(c in asked for c in ("junk", "clean", "tidy")) else ["lengths"]
        queries = ["SELECT lang, count(*) AS n FROM pool GROUP BY lang ORDER BY n DESC LIMIT 5"] if int(s["stage"]) == 2 else []
        return json.dumps({"probes": probes, "queries": queries})

    def complete(self, kind: str, prompt: str, slots: Mapping[str, Any]) -> str:
        return getattr(self, f"_{kind}")(slots)

    @staticmethod
    def wanted(request: str) -> list[str]:
        asked = request.lower()
        take = re.search(r"(?:take|only|want|keep) the ([a-z, ]+?) samples", asked)
        scope = take[1] if take else ""
        return [code for name, code in LANGUAGES.items() if name in scope]

    def _mode(self, s) -> str:
        asked = s["request"].lower()
        return "multi" if re.search(r"mixes|mixed|several|multi|generally", asked) else "single"

    def _label(self, s) -> str:
        counts = Counter(x.get("lang") or "unknown" for x in s["samples"])
        name, n = counts.most_common(1)[0] if counts else ("mixed", 0)
        return json.dumps([name] if n >= 0.6 * sum(counts.values()) and n else ["mixed"])

    def _match(self, s) -> str:
        clusters = {int(c): names for c, names in s["clusters"]}
        return json.dumps({"matching_cluster_ids": self.matcher.match(self.wanted(s["request"]), clusters)})

    def _policy(self, s) -> str:
        asked, seen = s["request"].lower(), s.get("observations") or {}
        policy = Policy().to_dict()
        if "junk" in asked or "clean" in asked:
            policy["max_noise_ratio"] = 0.02
            policy["noise_regex"] = policy["noise_regex"].replace("!", "", 1).replace("！", "", 1)
        if any(f" {x}" in asked for x in ("french", "german", "spanish")) or "mix" in asked:
            policy["require_en"] = False
        stats = seen.get("stats") or {}
        if stats.get("latin") is not None and stats["latin"] < policy["min_en_ratio"]:
            policy["require_en"] = False  # the pool is written in another script
        if stats.get("n") and stats.get("empty_output") == stats["n"]:
            policy["min_out_len"], policy["out_inst_ratio_min"] = 0, 0.0  # no sample has an answer to measure
        return json.dumps(policy)

    def _plan(self, s) -> str:
        asked = s["request"].lower()
        tidy = any(c in asked for c in ("clean", "tidy", "junk"))
        return json.dumps({"max_noise": 0.02 if tidy else 0.1, "min_output": 15, "variety": 1.0, "clean": 2.0 if tidy else 1.0, "length": 1.0 if "step" in asked or "non-trivial" in asked else 0.5})

    def _weights(self, s) -> str:
        asked = s["request"].lower()
        raw = {m: 1 + 2 * sum(c in asked for c in cues) for m, cues in WEIGHT_CUES.items()}
        total = sum(raw.values())
        out = {m: round(v / total, 2) for m, v in raw.items()}
        out["mean_diff"] = round(1 - out["loss"] - out["entropy"] - out["drift"], 2)
        return json.dumps(out)

    def _rubric(self, s) -> str:
        asked = s["request"].lower()
        hits = {n: sum(c in asked for c in cues) for n, (cues, _) in RUBRIC_CUES.items()}
        chosen = {n: h for n, h in hits.items() if h} or {"correctness": 1, "cleanness": 1}
        total, out, left = sum(chosen.values()), {}, 1.0
        for i, (n, h) in enumerate(chosen.items()):
            w = round(left, 4) if i == len(chosen) - 1 else round(h / total, 2)
            left -= w
            out[n] = {"description": RUBRIC_CUES[n][1], "weight": w}
        return json.dumps(out)
