"""Prompt texts in our own words; slots are filled by name."""

from __future__ import annotations

PROMPTS = {
    "mode": "A user wants training data: {request}\nDoes the pool hold one field only, or several? Answer with single or multi.",
    "label": "These are up to eight samples from one cluster of a pool:\n{samples}\nName the fields they belong to, as a JSON list of short English names. If they have nothing in common, answer [\"mixed\"].",
    "match": 'A user wants training data: {request}\nClusters and their field names:\n{clusters}\nWhich clusters serve the request? A sub-field of a wanted field counts, and one fitting name is enough. If the request names no field, take all. Answer as JSON: {{"matching_cluster_ids": [..]}}.',
    "inspect": 'A user wants training data: {request}\nStage {stage} is next. What is known of the pool: {observations}\nProbes to choose from: {probes}. Answer as JSON: {{"probes": [".."], "queries": ["SELECT .. FROM pool"]}}; both lists may be empty.',
    "plan": 'A user wants training data: {request}\nYou may look at the pool once. Answer as JSON with max_noise (0 to 1), min_output (characters), and weights of at least 0 for variety, clean and length.',
    "policy": "A user wants training data: {request}\nWhat the pool looks like: {observations}\nWrite the rule filter as one JSON object with exactly these keys: {keys}.",
    "weights": "A user wants training data: {request}\nWhat the pool looks like: {observations}\nShare a total of 1 among loss, entropy, drift and mean_diff, by how much each should count, as one JSON object. Prefer a small share to 0.",
    "rubric": 'A user wants training data: {request}\nWhat the pool looks like: {observations}\nWrite a scoring rubric for it as JSON: {{"name": {{"description": "..", "weight": 0.5}}, ..}}; the weights sum to 1. Prefer dimensions made for the request.',
    "judge": 'Score the samples below against each other, 1 to 5 as whole numbers, on each dimension:\n{rubric}\nSamples:\n{samples}\nAnswer with a JSON list in the same order: {{"sample_id": .., "scores": {{"name": 1}}, "reasoning": "..", "flagged": false}}. Flag harmful samples and score them low.',
}


def render(kind: str, **slots: object) -> str:
    return PROMPTS[kind].format(**slots)
