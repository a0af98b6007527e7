"""ask(): one configuration call with validation and a retry budget; and the cost ledger."""

from __future__ import annotations

import json
from collections.abc import Callable, Mapping
from dataclasses import dataclass, field
from decimal import Decimal
from typing import Any, Protocol

from poolcurator.backbone.prompts import render
from poolcurator.config import ConfigRejected


class Backbone(Protocol):
    """A chat model. kind and slots let offline models answer without reading prose."""

    temperature: float

    def complete(self, kind: str, prompt: str, slots: Mapping[str, Any]) -> str: ...


def rough_tokens(text: str) -> int:
    """Four characters to a token."""
    return -(-len(text) // 4)


@dataclass
class CostLedger:
    """Calls, tokens and dollars by stage and kind of prompt."""

    run_id: str = "run"
    price_in: Decimal = Decimal("0")  # dollars per million tokens
    price_out: Decimal = Decimal("0")
    rows: dict[tuple[int, str], list[int]] = field(default_factory=dict)

    def add(self, stage: int, kind: str, prompt: str, reply: str, failed: bool = False, retry: bool = False) -> None:
        row = self.rows.setdefault((stage, kind), [0, 0, 0, 0, 0])
        for i, v in enumerate((1, rough_tokens(prompt), rough_tokens(reply), int(retry), int(failed))):
            row[i] += v

    def add_many(self, stage: int, kind: str, calls: int, tokens_in: int, tokens_out: int, retries: int = 0, failures: int = 0) -> None:
        row = self.rows.setdefault((stage, kind), [0, 0, 0, 0, 0])
        for i, v in enumerate((calls, tokens_in, tokens_out, retries, failures)):
            row[i] += v

    def table(self) -> list[tuple]:
        return [(self.run_id, s, k, c, i, o, r, f, (self.price_in * i + self.price_out * o) / 1_000_000) for (s, k), (c, i, o, r, f) in sorted(self.rows.items())]

    def summary(self) -> dict[str, Any]:
        t = self.table()
        return {"calls": sum(x[3] for x in t), "tokens_in": sum(x[4] for x in t), "tokens_out": sum(x[5] for x in t), "retries": sum(x[6] for x in t), "failures": sum(x[7] for x in t), "usd": sum((x[8] for x in t), Decimal(0))}


STAGE_OF = {"plan": 0, "inspect": 2, "mode": 1, "label": 1, "match": 1, "policy": 2, "weights": 3, "rubric": 4, "judge": 4}


def ask(backbone: Backbone, kind: str, slots: Mapping[str, Any], parse: Callable[[Any], Any], max_retries: int = 3, ledger: CostLedger | None = None, stage: int | None = None) -> Any:
    """The parsed reply; malformed or out-of-range replies are asked for again until the budget is used up."""
    prompt = render(kind, **{k: v if isinstance(v, str) else json.dumps(v, ensure_ascii=False, default=str) for k, v in slots.items()})
    error: Exception | None = None
    for attempt in range(max_retries + 1):
        reply = backbone.complete(kind, prompt, slots)
        try:
            value = parse(json.loads(reply) if kind != "mode" else reply.strip().lower())
        except (ValueError, TypeError, KeyError, AttributeError) as e:
            error = e
        else:
            if ledger:
                ledger.add(stage or STAGE_OF[kind], kind, prompt, reply, retry=attempt > 0)
            return value
        if ledger:
            ledger.add(stage or STAGE_OF[kind], kind, prompt, reply, failed=True, retry=attempt > 0)
    raise ConfigRejected(f"{kind}: no valid reply in {max_retries + 1} calls: {error}")


class ReplayBackbone:
    """Canned replies by kind, in order; the last one repeats."""

    def __init__(self, replies: Mapping[str, list[str]], temperature: float = 0.01):
        self.replies, self.temperature = {k: list(v) for k, v in replies.items()}, temperature
        self.seen: list[str] = []

    def complete(self, kind: str, prompt: str, slots: Mapping[str, Any]) -> str:
        self.seen.append(kind)
        queue = self.replies[kind]
        return queue.pop(0) if len(queue) > 1 else queue[0]


class HttpBackbone:
    """A chat endpoint that takes JSON {model, messages, temperature} and answers {choices: [{message: {content}}]}."""

    def __init__(self, url: str, model: str, headers: Mapping[str, str] | None = None, temperature: float = 0.01, timeout: float = 120):
        self.url, self.model, self.headers, self.temperature, self.timeout = url, model, dict(headers or {}), temperature, timeout

    def complete(self, kind: str, prompt: str, slots: Mapping[str, Any]) -> str:
        from urllib.request import Request, urlopen

        body = json.dumps({"model": self.model, "temperature": self.temperature, "messages": [{"role": "user", "content": prompt}]}).encode()
        with urlopen(Request(self.url, body, {"Content-Type": "application/json"} | self.headers), timeout=self.timeout) as r:
            return json.load(r)["choices"][0]["message"]["content"]
