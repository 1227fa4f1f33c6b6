"""What a language model is asked, and what asking costs.

Models run inside Arrow workers.  Records come as parallel lists of ids and
texts; `hidden` holds the truth, is read by the simulated model only and is empty
for every other.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from typing import Any, Protocol

from jointsem.functions.expressions import tokens_of


@dataclass
class Records:
    ids: list[int]
    texts: list[str]
    hidden: list[str | None] = field(default_factory=list)

    def __len__(self) -> int:
        return len(self.ids)

    def take(self, rows: Any) -> Records:
        rows = list(map(int, rows))
        return Records([self.ids[r] for r in rows], [self.texts[r] for r in rows], [self.hidden[r] for r in rows] if self.hidden else [])


class LanguageModel(Protocol):
    """Answers; each costs one call of the records it is shown.

    A model may also have classify_rows(instruction, labels, records, context), which
    reads many records one by one at once, and answered(df, labels), which adds pred
    and log to a DataFrame with a column text, without Python.
    """

    def classify(self, instruction: str, labels: list[str], record: Records, context: str = "", key: str = "") -> tuple[str, float]:
        """Label of one record, and the log-probability of the answer."""

    def classify_many(self, instruction: str, labels: list[str], records: Records, key: str = "") -> list[str]: ...

    def group_pairs(self, instruction: str, records: Records, key: str = "") -> list[tuple[int, int]]:
        """Pairs of ids that are of one class."""

    def group_clusters(self, instruction: str, records: Records, key: str = "") -> list[list[int]]: ...

    def same(self, instruction: str, a: Records, b: Records, context: Records | None = None, key: str = "") -> bool: ...

    def score_labels(self, instruction: str, labels: list[str], records: Records, examples: dict[str, Records] | None = None, key: str = "") -> list[float]:
        """Log-probability of each label for a cluster as a whole."""

    def compare(self, instruction: str, a: Records, b: Records, key: str = "") -> bool:
        """Whether a is to be scored lower than b."""

    def summarize(self, instruction: str, records: Records, key: str = "") -> str: ...

    def extract(self, instruction: str, fields: dict[str, str], records: Records, key: str = "") -> dict[str, str]:
        """Values of named fields for the first record, the others being its context."""

    def rubric(self, instruction: str, labels: list[str], records: Records, key: str = "") -> str: ...

    def keyphrases(self, instruction: str, record: Records, key: str = "") -> list[str]: ...

    def propose_labels(self, instruction: str, records: Records, key: str = "") -> list[str]: ...

    def merge_labels(self, instruction: str, names: list[str], k: int, key: str = "") -> list[str]: ...


@dataclass(frozen=True)
class Tier:
    """A model with prices per million tokens."""

    name: str
    model: Any
    price_in: float
    price_out: float


@dataclass(frozen=True)
class Pool:
    """The expensive and the cheap model."""

    strong: Tier
    light: Tier

    def tier(self, name: str) -> Tier:
        return {"strong": self.strong, "light": self.light}[name]


@dataclass
class Usage:
    calls: int = 0
    tokens_in: int = 0
    tokens_out: int = 0

    def add(self, tokens_in: int, tokens_out: int, calls: int = 1) -> None:
        self.calls += calls
        self.tokens_in += tokens_in
        self.tokens_out += tokens_out

    def cost(self, tier: Tier) -> float:
        return (self.tokens_in * tier.price_in + self.tokens_out * tier.price_out) / 1e6


class Metered:
    """A tier whose calls are counted; it has the model's methods."""

    def __init__(self, tier: Tier):
        self.tier, self.usage = tier, Usage()

    def _shown(self, instruction: str, *parts: Any) -> int:
        total = tokens_of(instruction)
        for p in parts:
            if isinstance(p, Records):
                total += sum(tokens_of(t) + 2 for t in p.texts)
            elif isinstance(p, str):
                total += tokens_of(p)
            elif isinstance(p, dict):
                total += sum(self._shown("", v) for v in p.values())
            elif p:
                total += sum(tokens_of(str(x)) for x in p)
        return total

    def classify(self, instruction, labels, record, context="", key=""):
        answer = self.tier.model.classify(instruction, labels, record, context, key)
        self.usage.add(self._shown(instruction, labels, record, context), tokens_of(answer[0]))
        return answer

    def classify_rows(self, instruction, labels, records, context=""):
        """Answers to each record by itself, and the tokens of each."""
        model = self.tier.model
        if hasattr(model, "classify_rows"):
            answers = model.classify_rows(instruction, labels, records, context)
        else:
            answers = [model.classify(instruction, labels, records.take([r]), context) for r in range(len(records))]
        fixed = self._shown(instruction, labels, context)
        tokens = [(fixed + tokens_of(t) + 2, tokens_of(a[0])) for t, a in zip(records.texts, answers, strict=True)]
        for t in tokens:
            self.usage.add(*t)
        return answers, tokens

    def classify_many(self, instruction, labels, records, key=""):
        answer = self.tier.model.classify_many(instruction, labels, records, key)
        self.usage.add(self._shown(instruction, labels, records), sum(tokens_of(a) for a in answer))
        return answer

    def group_pairs(self, instruction, records, key=""):
        answer = self.tier.model.group_pairs(instruction, records, key)
        self.usage.add(self._shown(instruction, records), 2 * len(answer))
        return answer

    def group_clusters(self, instruction, records, key=""):
        answer = self.tier.model.group_clusters(instruction, records, key)
        self.usage.add(self._shown(instruction, records), len(records))
        return answer

    def same(self, instruction, a, b, context=None, key=""):
        answer = self.tier.model.same(instruction, a, b, context, key)
        self.usage.add(self._shown(instruction, a, b, context), 1)
        return answer

    def score_labels(self, instruction, labels, records, examples=None, key=""):
        answer = self.tier.model.score_labels(instruction, labels, records, examples, key)
        self.usage.add(self._shown(instruction, labels, records, examples), len(labels))
        return answer

    def compare(self, instruction, a, b, key=""):
        answer = self.tier.model.compare(instruction, a, b, key)
        self.usage.add(self._shown(instruction, a, b), 1)
        return answer

    def summarize(self, instruction, records, key=""):
        answer = self.tier.model.summarize(instruction, records, key)
        self.usage.add(self._shown(instruction, records), tokens_of(answer))
        return answer

    def extract(self, instruction, fields, records, key=""):
        answer = self.tier.model.extract(instruction, fields, records, key)
        self.usage.add(self._shown(instruction, list(fields), list(fields.values()), records), sum(map(tokens_of, answer.values())))
        return answer

    def rubric(self, instruction, labels, records, key=""):
        answer = self.tier.model.rubric(instruction, labels, records, key)
        self.usage.add(self._shown(instruction, labels, records), tokens_of(answer))
        return answer

    def keyphrases(self, instruction, record, key=""):
        answer = self.tier.model.keyphrases(instruction, record, key)
        self.usage.add(self._shown(instruction, record), sum(map(tokens_of, answer)))
        return answer

    def propose_labels(self, instruction, records, key=""):
        answer = self.tier.model.propose_labels(instruction, records, key)
        self.usage.add(self._shown(instruction, records), sum(map(tokens_of, answer)))
        return answer

    def merge_labels(self, instruction, names, k, key=""):
        answer = self.tier.model.merge_labels(instruction, names, k, key)
        self.usage.add(self._shown(instruction, names), sum(map(tokens_of, answer)))
        return answer
