"""A model that knows the truth and errs by declared rates.

Accuracies obtained with it depend on its profile; they show how the methods
behave, not how any real model does.  Every draw is a portable uniform of the
seed, the kind of question and the records, so repeated questions get repeated
answers and SQL can recompute them.
"""

from __future__ import annotations

import math
from collections import Counter
from dataclasses import dataclass, field

from jointsem.functions.hashing import uniform
from jointsem.models.base import Records


@dataclass(frozen=True)
class Profile:
    """Error rates.  ambiguous: share of records a lone reader takes for a neighbouring class; long: error growth per 100 records shown beyond `room`.

    A perceived group is answered as links from each record to the `reach` before it, each lost with probability drop.
    """

    row: float = 0.0
    ambiguous: float = 0.0
    group: float = 0.0
    long: float = 0.0
    room: int = 80
    drop: float = 0.0
    reach: int = 1
    clusters: float = 0.0
    pair: float = 0.0
    compare: float = 0.0
    label: float = 0.0


#: The profile of the experiments: a reader of single records misjudges many, small groups are judged well, large ones badly.
STUDY = Profile(row=0.08, ambiguous=0.22, group=0.06, long=0.25, drop=0.1, reach=3, clusters=0.35, pair=0.18, compare=0.12, label=0.5)
STUDY_LIGHT = Profile(row=0.16, ambiguous=0.26, group=0.1, long=0.35, drop=0.15, reach=3, clusters=0.45, pair=0.25, compare=0.2, label=0.6)


@dataclass
class SimulatedModel:
    labels: list[str]
    profile: Profile = field(default_factory=Profile)
    seed: str = "sim"
    tag: str = ""

    def _u(self, *parts: object) -> float:
        return uniform(self.seed + self.tag, *parts)

    def _other(self, truth: str, u: float) -> str:
        """The class after the truth, or with a small chance another one."""
        if truth not in self.labels or len(self.labels) < 2:
            return truth
        i = self.labels.index(truth)
        step = 1 if u < 0.8 else 1 + int((u - 0.8) * 5 * (len(self.labels) - 1))
        return self.labels[(i + step) % len(self.labels)]

    def _alone(self, i: int, truth: str | None) -> tuple[str, bool]:
        """What a reader of this record alone takes it for, and whether that is a slip."""
        truth = truth or ""
        if uniform(self.seed, "ambiguous", i) < self.profile.ambiguous:
            return self._other(truth, 0.0), True
        if self._u("row", i) < self.profile.row:
            return self._other(truth, self._u("other", i)), True
        return truth, False

    def classify(self, instruction: str, labels: list[str], record: Records, context: str = "", key: str = "") -> tuple[str, float]:
        i = record.ids[0]
        answer, slip = self._alone(i, record.hidden[0])
        u = self._u("confidence", i)
        if answer not in labels:
            answer = labels[int(self._u("outside", i) * len(labels)) % len(labels)]
        return answer, math.log((0.2 + 0.6 * u) if slip else (0.6 + 0.4 * u))

    def classify_many(self, instruction: str, labels: list[str], records: Records, key: str = "") -> list[str]:
        out = []
        for i, h in zip(records.ids, records.hidden, strict=True):
            answer, _ = self._alone(i, h)
            if self._u("many", key, i) < self.profile.long * len(records) / 400:
                answer = self._other(answer, self._u("manyother", key, i))
            out.append(answer if answer in labels else labels[0])
        return out

    def _perceived(self, kind: str, rate: float, records: Records, key: str) -> list[str]:
        """What each record of a sample is taken for: a slip leads to a neighbouring class, and what a long prompt blurs to any."""
        blur = self.profile.long * max(0, len(records) - self.profile.room) / 100
        out = []
        for i, h in zip(records.ids, records.hidden, strict=True):
            u = self._u(kind, key, i)
            if u < rate:
                out.append(self._other(h or "", self._u(kind, "other", key, i)))
            elif u < rate + blur:
                out.append(self.labels[int(self._u(kind, "blur", key, i) * len(self.labels))])
            else:
                out.append(h or "")
        return out

    def group_pairs(self, instruction: str, records: Records, key: str = "") -> list[tuple[int, int]]:
        seen = self._perceived("group", self.profile.group, records, key)
        last: dict[str, list[int]] = {}
        out = []
        for i, c in sorted(zip(records.ids, seen, strict=True)):
            before = last.setdefault(c, [])
            out += [(a, i) for a in before[-self.profile.reach :] if self._u("drop", key, a, i) >= self.profile.drop]
            before.append(i)
        return out

    def group_clusters(self, instruction: str, records: Records, key: str = "") -> list[list[int]]:
        seen = self._perceived("clusters", self.profile.clusters, records, key)
        out: dict[str, list[int]] = {}
        for i, c in zip(records.ids, seen, strict=True):
            out.setdefault(c, []).append(i)
        return list(out.values())

    def same(self, instruction: str, a: Records, b: Records, context: Records | None = None, key: str = "") -> bool:
        i, j = sorted((a.ids[0], b.ids[0]))
        if context is None:  # each is read alone, so what is ambiguous alone misleads every question about it
            alike = self._alone(a.ids[0], a.hidden[0])[0] == self._alone(b.ids[0], b.hidden[0])[0]
            return alike != (self._u("pair", key, i, j) < self.profile.pair)
        return (a.hidden[0] == b.hidden[0]) != (self._u("pair", key, i, j) < self.profile.pair / 2)

    def score_labels(self, instruction: str, labels: list[str], records: Records, examples: dict[str, Records] | None = None, key: str = "") -> list[float]:
        if not len(records):
            return [-math.log(len(labels))] * len(labels)
        share = Counter(records.hidden)
        noise = self.profile.label * (1.5 if examples else 1.0)
        raw = []
        for n in labels:
            own = share[n] + 0.6 * share[labels[(labels.index(n) - 1) % len(labels)]]
            raw.append(6 * own / len(records) + 4 * noise * (self._u("label", key, n) - 0.5) * 2)
        top = max(raw)
        norm = top + math.log(sum(math.exp(r - top) for r in raw))
        return [r - norm for r in raw]

    def compare(self, instruction: str, a: Records, b: Records, key: str = "") -> bool:
        rank = {n: r for r, n in enumerate(self.labels)}
        lower = rank.get(a.hidden[0] or "", 0) < rank.get(b.hidden[0] or "", 0)
        return lower != (self._u("compare", key, a.ids[0], b.ids[0]) < self.profile.compare)

    def summarize(self, instruction: str, records: Records, key: str = "") -> str:
        n = Counter(h or "" for h in records.hidden)
        return min(n, key=lambda c: (-n[c], c)) if n else "empty"

    def extract(self, instruction: str, fields: dict[str, str], records: Records, key: str = "") -> dict[str, str]:
        return dict.fromkeys(fields, self._alone(records.ids[0], records.hidden[0])[0] if len(records) == 1 else records.hidden[0] or "")

    def rubric(self, instruction: str, labels: list[str], records: Records, key: str = "") -> str:
        return "guidelines for " + ", ".join(labels)

    def keyphrases(self, instruction: str, record: Records, key: str = "") -> list[str]:
        return [f"topic_{self._alone(record.ids[0], record.hidden[0])[0]}".replace(" ", "_")]

    def propose_labels(self, instruction: str, records: Records, key: str = "") -> list[str]:
        return sorted(set(self._perceived("propose", self.profile.group, records, key)))

    def merge_labels(self, instruction: str, names: list[str], k: int, key: str = "") -> list[str]:
        n = Counter(names)
        return sorted(n, key=lambda c: (-n[c], c))[:k]
