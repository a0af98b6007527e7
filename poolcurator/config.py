"""Configurations that a chat model may write, with defaults and validators."""

from __future__ import annotations

import re
from collections.abc import Mapping, Sequence
from dataclasses import asdict, dataclass, field, fields, replace

from poolcurator.functions.text import noise_class

# Openings of common refusals.
REFUSALS = ("I'm sorry, but", "I cannot assist", "I can't help with", "As an AI language model", "I am unable to")


class ConfigRejected(ValueError):
    """A configuration that is malformed or out of range."""


@dataclass(frozen=True)
class Policy:
    """The ten keys of the rule filter; lengths are in characters."""

    min_total_len: int = 40
    max_total_len: int = 4096
    min_inst_len: int = 5
    min_out_len: int = 15
    out_inst_ratio_min: float = 0.2
    refusal_phrases: tuple[str, ...] = REFUSALS
    noise_regex: str = field(default_factory=noise_class)
    max_noise_ratio: float = 0.15
    require_en: bool = True
    min_en_ratio: float = 0.30

    @classmethod
    def keys(cls) -> tuple[str, ...]:
        return tuple(f.name for f in fields(cls))

    @classmethod
    def merge(cls, emitted: Mapping[str, object], strict: bool = False) -> Policy:
        """Defaults with the emitted keys in their place; strict asks for exactly the ten keys."""
        unknown, missing = set(emitted) - set(cls.keys()), set(cls.keys()) - set(emitted)
        if unknown or (strict and missing):
            raise ConfigRejected(f"policy keys: unknown {sorted(unknown)}, missing {sorted(missing) if strict else []}")
        values = dict(emitted)
        if "refusal_phrases" in values:
            phrases = values["refusal_phrases"]
            if isinstance(phrases, str) or not isinstance(phrases, Sequence) or not all(isinstance(p, str) for p in phrases):
                raise ConfigRejected("refusal_phrases is a list of strings")
            values["refusal_phrases"] = tuple(phrases)
        out = replace(cls(), **values)
        out.validate()
        return out

    def validate(self) -> None:
        for name in ("min_total_len", "max_total_len", "min_inst_len", "min_out_len"):
            if isinstance(getattr(self, name), bool) or not isinstance(getattr(self, name), int) or getattr(self, name) < 0:
                raise ConfigRejected(f"{name} is a whole number of at least 0")
        if self.min_total_len > self.max_total_len:
            raise ConfigRejected("min_total_len is above max_total_len")
        for name in ("max_noise_ratio", "min_en_ratio"):
            if not 0 <= getattr(self, name) <= 1:
                raise ConfigRejected(f"{name} is outside 0 to 1")
        if self.out_inst_ratio_min < 0 or not isinstance(self.require_en, bool):
            raise ConfigRejected("out_inst_ratio_min is at least 0 and require_en is a boolean")
        try:
            re.compile(re.sub(r"\\p\{[A-Za-z]+\}", "a", self.noise_regex))
        except re.error as e:
            raise ConfigRejected(f"noise_regex: {e}") from e
        if re.search(r"\(\?<?[=!]|\\[1-9]", self.noise_regex):
            raise ConfigRejected("noise_regex may not look around or refer back")

    def to_dict(self) -> dict:
        return asdict(self) | {"refusal_phrases": list(self.refusal_phrases)}


METRICS = ("loss", "entropy", "drift", "mean_diff")


@dataclass(frozen=True)
class Weights:
    loss: float
    entropy: float
    drift: float
    mean_diff: float

    @classmethod
    def parse(cls, emitted: Mapping[str, object]) -> Weights:
        if set(emitted) != set(METRICS):
            raise ConfigRejected(f"weights have the keys {METRICS}")
        try:
            out = cls(**{k: float(v) for k, v in emitted.items()})
        except (TypeError, ValueError) as e:
            raise ConfigRejected("weights are numbers") from e
        out.validate()
        return out

    def validate(self) -> list[str]:
        """Raises on negative weights or a sum other than 1; names the weights that are 0."""
        values = asdict(self)
        if min(values.values()) < 0 or abs(sum(values.values()) - 1) > 1e-6:
            raise ConfigRejected(f"weights are at least 0 and sum to 1: {values}")
        return [k for k, v in values.items() if v == 0]

    def to_dict(self) -> dict[str, float]:
        return asdict(self)


@dataclass(frozen=True)
class Rubric:
    """Named dimensions with a description and a weight."""

    dimensions: tuple[tuple[str, str, float], ...]

    @classmethod
    def parse(cls, emitted: Mapping[str, object], most: int = 12) -> Rubric:
        try:
            dims = tuple((str(n), str(d["description"]), float(d["weight"])) for n, d in emitted.items())
        except (TypeError, KeyError, ValueError) as e:
            raise ConfigRejected("a rubric maps names to description and weight") from e
        if not 1 <= len(dims) <= most:
            raise ConfigRejected(f"a rubric has 1 to {most} dimensions")
        if min(w for _, _, w in dims) < 0 or abs(sum(w for _, _, w in dims) - 1) > 1e-6:
            raise ConfigRejected("rubric weights are at least 0 and sum to 1")
        return cls(dims)

    @property
    def weights(self) -> dict[str, float]:
        return {n: w for n, _, w in self.dimensions}

    def to_dict(self) -> dict:
        return {n: {"description": d, "weight": w} for n, d, w in self.dimensions}


@dataclass(frozen=True)
class SelectionRequest:
    """What is asked for, in plain language."""

    id: str
    text: str


@dataclass(frozen=True)
class CascadeConfig:
    k: int = 100
    keep_ratio: float = 3.0
    seed: int = 42
    n_c: int = 50_000
    min_cluster_size: int = 50
    min_samples: int | None = None
    noise_policy: str = "drop"
    k_c: int = 20
    n_init: int = 3
    max_iter: int = 300
    n_s: int = 8
    trunc_chars: int = 500
    batch: int = 10
    samples_per_round: int = 50
    concurrency: int = 5
    temperature: float = 0.01
    max_retries: int = 3
    lr: float = 1e-5
    drop_flagged: bool = False

    def __post_init__(self):
        if self.keep_ratio <= 1:
            raise ConfigRejected("keep_ratio is above 1")
        if self.noise_policy not in ("drop", "nearest", "own_cluster"):
            raise ConfigRejected("noise_policy is drop, nearest or own_cluster")

    @property
    def k_star(self) -> int:
        return int(self.k * self.keep_ratio)


def budget_for(n: int) -> int:
    """The experiments' budget: a tenth of the pool, 20 at least."""
    return max(20, n // 10)


# Published weight vectors (setting, pool, loss, entropy, drift, mean_diff).
PUBLISHED_WEIGHTS = (
    ("single", "OpenR1-Math", 0.05, 0.20, 0.40, 0.35),
    ("single", "Synthetic-Math", 0.15, 0.15, 0.35, 0.35),
    ("multi", "OpenHermes-2.5 math", 0.25, 0.15, 0.35, 0.25),
    ("multi", "Tulu-3 math", 0.15, 0.15, 0.40, 0.30),
    ("single", "OSS-Instruct", 0.25, 0.20, 0.15, 0.40),
    ("single", "Code-Alpaca", 0.25, 0.20, 0.20, 0.35),
    ("multi", "OpenHermes-2.5 code", 0.30, 0.15, 0.20, 0.35),
    ("multi", "Tulu-3 code", 0.35, 0.10, 0.10, 0.45),
    ("single", "Medical-Reasoning", 0.20, 0.15, 0.35, 0.30),
    ("single", "UltraMedical", 0.15, 0.10, 0.40, 0.35),
    ("multi", "OpenHermes-2.5 science", 0.30, 0.25, 0.25, 0.20),
)
