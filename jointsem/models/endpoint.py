"""A model behind a user's function: questions become prompts, replies are read back, failed calls are retried.

The function takes a prompt and returns its reply, or the reply and the
log-probability of it.  It is called inside workers, with at most `max_inflight`
calls at a time in each, and must be picklable.  A reply that cannot be read
counts as no answer: no pair, the first label, an even share.
"""

from __future__ import annotations

import math
import re
import time
from collections.abc import Callable, Iterable
from concurrent.futures import ThreadPoolExecutor
from concurrent.futures import TimeoutError as Late
from dataclasses import dataclass

from jointsem.models.base import Records

Reply = str | tuple[str, float]


class CallFailed(RuntimeError):
    """A call failed as often as it may."""


@dataclass
class CallableModel:
    fn: Callable[[str], Reply]
    max_retries: int = 3
    timeout_s: float = 60.0
    max_inflight: int = 8
    backoff_s: float = 0.5

    def _ask(self, prompt: str) -> tuple[str, float]:
        for attempt in range(self.max_retries + 1):
            pool = ThreadPoolExecutor(1)
            try:
                reply = pool.submit(self.fn, prompt).result(self.timeout_s)
                return reply if isinstance(reply, tuple) else (reply, 0.0)
            except (Late, OSError, RuntimeError) as error:  # what a service may throw in passing; others are the caller's mistakes
                last = error
                if attempt < self.max_retries:
                    time.sleep(self.backoff_s * 2**attempt)
            finally:
                pool.shutdown(wait=False)
        raise CallFailed(f"gave up after {self.max_retries + 1} calls") from last

    def _ask_all(self, prompts: Iterable[str]) -> list[tuple[str, float]]:
        with ThreadPoolExecutor(self.max_inflight) as pool:
            return list(pool.map(self._ask, prompts))

    @staticmethod
    def _shown(records: Records) -> str:
        return "\n".join(f"[{i}] {t}" for i, t in zip(records.ids, records.texts, strict=True))

    @staticmethod
    def _label(reply: str, labels: list[str]) -> str:
        """The label that the reply is, or else the first one it names, longer ones first."""
        said = reply.strip().strip("\"'.").lower()
        for n in labels:
            if said == n.lower():
                return n
        found = [(said.find(n.lower()), -len(n), n) for n in labels if n.lower() in said]
        return min(found)[2] if found else labels[0]

    def _row(self, instruction: str, labels: list[str], text: str, context: str) -> str:
        return f"{context}\n{instruction}\nAnswer with one of: {', '.join(labels)}.\n\n{text}".strip()

    def classify(self, instruction: str, labels: list[str], record: Records, context: str = "", key: str = "") -> tuple[str, float]:
        reply, log = self._ask(self._row(instruction, labels, record.texts[0], context))
        return self._label(reply, labels), log

    def classify_rows(self, instruction: str, labels: list[str], records: Records, context: str = "") -> list[tuple[str, float]]:
        """Each record by itself, several calls at a time."""
        replies = self._ask_all([self._row(instruction, labels, t, context) for t in records.texts])
        return [(self._label(reply, labels), log) for reply, log in replies]

    def classify_many(self, instruction: str, labels: list[str], records: Records, key: str = "") -> list[str]:
        reply, _ = self._ask(f"{instruction}\nFor every item write its number, a colon, and one of: {', '.join(labels)}.\n\n{self._shown(records)}")
        said = {int(i): x for i, x in re.findall(r"\[?(\d+)\]?\s*:\s*(.+)", reply)}
        return [self._label(said.get(i, ""), labels) for i in records.ids]

    def group_pairs(self, instruction: str, records: Records, key: str = "") -> list[tuple[int, int]]:
        reply, _ = self._ask(f"{instruction}\nWrite pairs of numbers of items with the same answer, one pair a line, as 1-2. Every item is to be linked to another one of its kind.\n\n{self._shown(records)}")
        return [(int(a), int(b)) for a, b in re.findall(r"(\d+)\s*[-,]\s*(\d+)", reply)]

    def group_clusters(self, instruction: str, records: Records, key: str = "") -> list[list[int]]:
        reply, _ = self._ask(f"{instruction}\nGroup the items by their answer. Write one group a line, as numbers separated by commas.\n\n{self._shown(records)}")
        left, out = set(records.ids), []
        for line in reply.splitlines():
            group = [int(i) for i in dict.fromkeys(re.findall(r"\d+", line)) if int(i) in left]
            left -= set(group)
            out += [group] if group else []
        return [*out, *([i] for i in records.ids if i in left)]

    def same(self, instruction: str, a: Records, b: Records, context: Records | None = None, key: str = "") -> bool:
        around = f"\n\nOther items:\n{self._shown(context)}" if context else ""
        reply, _ = self._ask(f"{instruction}\nWould both items get the same answer? Say yes or no.\n\n{a.texts[0]}\n---\n{b.texts[0]}{around}")
        return reply.strip().lower().startswith("y")

    def score_labels(self, instruction: str, labels: list[str], records: Records, examples: dict[str, Records] | None = None, key: str = "") -> list[float]:
        """The reply's label has its log-probability; the rest is shared evenly by the others."""
        if not len(records):
            return [-math.log(len(labels))] * len(labels)
        others = "".join(f"\n\nItems of another group:\n{self._shown(x)}" for x in (examples or {}).values())
        reply, log = self._ask(f"{instruction}\nAll items have the same answer. Say which of: {', '.join(labels)}.\n\n{self._shown(records)}{others}")
        p = min(0.999, max(math.exp(min(0.0, log)), 1 / len(labels)))
        chosen = self._label(reply, labels)
        return [math.log(p) if n == chosen else math.log((1 - p) / max(1, len(labels) - 1)) if len(labels) > 1 else 0.0 for n in labels]

    def compare(self, instruction: str, a: Records, b: Records, key: str = "") -> bool:
        reply, _ = self._ask(f"{instruction}\nWhich item scores lower? Say A or B.\n\nA: {a.texts[0]}\n\nB: {b.texts[0]}")
        return reply.strip().lower().startswith("a")

    def summarize(self, instruction: str, records: Records, key: str = "") -> str:
        return self._ask(f"{instruction}\nName what these items have in common, in a few words.\n\n{self._shown(records)}")[0].strip()

    def extract(self, instruction: str, fields: dict[str, str], records: Records, key: str = "") -> dict[str, str]:
        """Values of the fields for the first record; the others are context."""
        asked = "\n".join(f"{n}: {meaning}" for n, meaning in fields.items())
        reply, _ = self._ask(f"{instruction}\nFor the first item write each field, a colon and its value.\n{asked}\n\n{self._shown(records)}")
        said = {n.strip().lower(): v.strip() for n, v in re.findall(r"^\s*([^:\n]+):(.*)$", reply, re.M)}
        return {n: said.get(n.lower(), "") for n in fields}

    def rubric(self, instruction: str, labels: list[str], records: Records, key: str = "") -> str:
        return self._ask(f"{instruction}\nWrite short guidelines for telling apart: {', '.join(labels)}.\n\n{self._shown(records)}")[0].strip()

    def keyphrases(self, instruction: str, record: Records, key: str = "") -> list[str]:
        return self._lines(f"{instruction}\nWrite key phrases of the item for this purpose, one a line.\n\n{record.texts[0]}")

    def propose_labels(self, instruction: str, records: Records, key: str = "") -> list[str]:
        return self._lines(f"{instruction}\nWrite the answers that occur among the items, one a line.\n\n{self._shown(records)}")

    def merge_labels(self, instruction: str, names: list[str], k: int, key: str = "") -> list[str]:
        return self._lines(f"{instruction}\nMerge these names into {k}, one a line.\n\n" + "\n".join(names))[:k]

    def _lines(self, prompt: str) -> list[str]:
        return [x for x in (line.strip(" -*\t") for line in self._ask(prompt)[0].splitlines()) if x]
