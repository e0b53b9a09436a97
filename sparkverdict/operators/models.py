"""Simulated semantic models: a model answers named tests about rows and counts its tokens. All answers are deterministic."""

from __future__ import annotations

import hashlib
from collections import Counter
from dataclasses import dataclass
from typing import Protocol

from sparkverdict.functions.truth import Pred

#: List prices in dollars per million input and output tokens, by tier.
PRICES = {"A": (5.0, 25.0), "B": (3.0, 15.0), "C": (1.0, 5.0), "D": (0.287, 1.147), "E": (0.144, 0.574)}
#: Published map accuracies of the tiers, from which error rates are simulated.
ACCURACY = {"A": 0.96, "B": 0.95, "C": 0.93, "D": 0.92, "E": 0.88}
PROMPT_TOKENS, ANSWER_TOKENS = 60, 8


class SemanticModel(Protocol):
    name: str

    def answer(self, pred: Pred, row: dict) -> bool: ...


def prompt_text(pred: Pred, row: dict) -> str:
    return f"{pred.name}|" + "|".join(str(row.get(c)) for c in pred.columns)


def tokens_in(row: dict, columns: tuple[str, ...]) -> int:
    """A quarter of the characters, and the instructions."""
    return PROMPT_TOKENS + sum(-(-len(str(row.get(c) or "")) // 4) for c in columns)


@dataclass(frozen=True)
class RuleModel:
    name: str = "rule"

    def answer(self, pred: Pred, row: dict) -> bool:
        return pred.answer(row)


@dataclass(frozen=True)
class LabelModel:
    """Answers from a label column that the row carries."""

    column: str
    name: str = "label"

    def answer(self, pred: Pred, row: dict) -> bool:
        return bool(row.get(self.column))


@dataclass(frozen=True)
class NoisyModel:
    """Flips a share of another model's answers, chosen by a hash of model, seed and prompt."""

    base: SemanticModel
    flip: float
    name: str = "noisy"
    seed: int = 0

    def answer(self, pred: Pred, row: dict) -> bool:
        h = hashlib.blake2b(f"{self.name}|{self.seed}|{prompt_text(pred, row)}".encode(), digest_size=8).digest()
        return self.base.answer(pred, row) ^ (int.from_bytes(h) / 2**64 < self.flip)


@dataclass(frozen=True)
class EnsembleModel:
    """The majority of an odd number of models."""

    models: tuple[SemanticModel, ...]
    name: str = "ensemble"

    def answer(self, pred: Pred, row: dict) -> bool:
        return Counter(m.answer(pred, row) for m in self.models).most_common(1)[0][0]


@dataclass(frozen=True)
class HttpModel:
    """Where a served model plugs in: give it a function from prompt text to a boolean."""

    call: object
    name: str = "http"

    def answer(self, pred: Pred, row: dict) -> bool:
        return bool(self.call(prompt_text(pred, row)))  # type: ignore[operator]


def tier(name: str, seed: int = 0) -> NoisyModel:
    return NoisyModel(RuleModel(), 1 - ACCURACY[name], f"tier-{name}", seed)


def dollars(model: str, tokens_in: int, tokens_out: int) -> float:
    a, b = PRICES[model]
    return (tokens_in * a + tokens_out * b) / 1e6
