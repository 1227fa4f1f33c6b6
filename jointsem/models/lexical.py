"""A model that sees words only: classes are patterns, and answers follow from counts of their matches."""

from __future__ import annotations

import math
import re
from collections import Counter
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from jointsem.models.base import Records


@dataclass
class LexicalModel:
    """spec: a pattern per class, over lower-cased text.  order: rank of words for comparisons; otherwise the first number decides."""

    spec: dict[str, str]
    order: dict[str, int] = field(default_factory=dict)
    sharpness: float = 6.0

    def _counts(self, text: str, names: list[str]) -> list[int]:
        low = (text or "").lower()
        return [len(re.findall(self.spec.get(n, re.escape(n.lower())), low)) for n in names]

    def _log_shares(self, counts: list[float]) -> list[float]:
        total = sum(counts)
        scaled = [self.sharpness * c / total if total else 0.0 for c in counts]
        top = max(scaled)
        norm = top + math.log(sum(math.exp(s - top) for s in scaled))
        return [s - norm for s in scaled]

    def _best(self, text: str, names: list[str]) -> int:
        counts = self._counts(text, names)
        return counts.index(max(counts))

    def classify(self, instruction: str, labels: list[str], record: Records, context: str = "", key: str = "") -> tuple[str, float]:
        logs = self._log_shares(self._counts(record.texts[0], labels))
        best = logs.index(max(logs))
        return labels[best], logs[best]

    def classify_many(self, instruction: str, labels: list[str], records: Records, key: str = "") -> list[str]:
        return [labels[self._best(t, labels)] for t in records.texts]

    def _groups(self, records: Records) -> dict[str, list[int]]:
        names = list(self.spec)
        out: dict[str, list[int]] = {}
        for i, t in zip(records.ids, records.texts, strict=True):
            out.setdefault(names[self._best(t, names)], []).append(i)
        return out

    def group_pairs(self, instruction: str, records: Records, key: str = "") -> list[tuple[int, int]]:
        return [p for g in self._groups(records).values() for p in zip(g[:-1], g[1:], strict=True)]

    def group_clusters(self, instruction: str, records: Records, key: str = "") -> list[list[int]]:
        return list(self._groups(records).values())

    def same(self, instruction: str, a: Records, b: Records, context: Records | None = None, key: str = "") -> bool:
        names = list(self.spec)
        return self._best(a.texts[0], names) == self._best(b.texts[0], names)

    def score_labels(self, instruction: str, labels: list[str], records: Records, examples: dict[str, Records] | None = None, key: str = "") -> list[float]:
        if not len(records):
            return [-math.log(len(labels))] * len(labels)
        sums = [0.0] * len(labels)
        for t in records.texts:
            sums[self._best(t, labels)] += 1
        return self._log_shares(sums)

    def _rank(self, text: str) -> float:
        low = (text or "").lower()
        for word, rank in self.order.items():
            if word in low:
                return rank
        m = re.search(r"-?\d+(?:\.\d+)?", low)
        return float(m[0]) if m else 0.0

    def compare(self, instruction: str, a: Records, b: Records, key: str = "") -> bool:
        return self._rank(a.texts[0]) < self._rank(b.texts[0])

    def summarize(self, instruction: str, records: Records, key: str = "") -> str:
        names = list(self.spec)
        return Counter(names[self._best(t, names)] for t in records.texts).most_common(1)[0][0] if len(records) else "empty"

    def extract(self, instruction: str, fields: dict[str, str], records: Records, key: str = "") -> dict[str, str]:
        """The first match of each field's pattern."""
        found = {n: re.search(p, records.texts[0] or "") for n, p in fields.items()}
        return {n: m[0] if m else "" for n, m in found.items()}

    def answered(self, df: DataFrame, labels: list[str]) -> DataFrame:
        """classify() of df's column text, without Python: df with pred and log.  The patterns must mean the same to Java; each is matched once."""
        low = F.lower(F.coalesce("text", F.lit("")))
        df = df.withColumn("_counts", F.array(*[F.regexp_count(low, F.lit(self.spec.get(n, re.escape(n.lower())))) for n in labels]))
        df = df.withColumn("_total", F.expr("aggregate(_counts, 0, (s, x) -> s + x)"))
        df = df.withColumn("_scaled", F.transform("_counts", lambda c: F.when(F.col("_total") > 0, self.sharpness * c / F.col("_total")).otherwise(F.lit(0.0))))
        df = df.withColumn("_top", F.array_max("_scaled"))
        best = F.element_at(F.array(*map(F.lit, labels)), F.array_position("_scaled", F.col("_top")).cast("int"))
        return df.withColumns({"pred": best, "log": -F.log(F.expr("aggregate(_scaled, 0D, (s, x) -> s + exp(x - _top))"))}).drop("_counts", "_total", "_scaled", "_top")

    def rubric(self, instruction: str, labels: list[str], records: Records, key: str = "") -> str:
        return "; ".join(f"{n}: like {self.spec.get(n, n)}" for n in labels)

    def keyphrases(self, instruction: str, record: Records, key: str = "") -> list[str]:
        names = list(self.spec)
        return [names[self._best(record.texts[0], names)]]

    def propose_labels(self, instruction: str, records: Records, key: str = "") -> list[str]:
        return sorted(self._groups(records))

    def merge_labels(self, instruction: str, names: list[str], k: int, key: str = "") -> list[str]:
        seen = Counter(names)
        return sorted(seen, key=lambda n: (-seen[n], n))[:k]
