"""From clusters to classes: by perfect matching, and the ways it is compared with."""

from __future__ import annotations

from typing import TYPE_CHECKING

import numpy as np

from jointsem.functions.hashing import uniforms
from jointsem.models.base import Metered, Records

if TYPE_CHECKING:
    from jointsem.plans.params import Params

FLOOR = np.log(1e-9)


def hungarian(gain: np.ndarray) -> np.ndarray:
    """Column of each row in the one-to-one assignment of greatest total gain; the matrix is padded to a square with zeros."""
    rows, columns = gain.shape
    n = max(rows, columns)
    cost = np.zeros((n, n))
    cost[:rows, :columns] = -gain
    # shortest augmenting paths: row r joins one at a time, prices keep reduced costs non-negative
    u, v = np.zeros(n), np.zeros(n)
    holder = np.full(n, -1)
    for r in range(n):
        dist, came, done = np.full(n, np.inf), np.full(n, -1), np.zeros(n, bool)
        at, column, base = r, -1, 0.0
        while True:
            through = base + cost[at] - u[at] - v
            shorter = ~done & (through < dist)
            dist[shorter], came[shorter] = through[shorter], column
            column = int(np.where(done, np.inf, dist).argmin())
            base = dist[column]
            done[column] = True
            if holder[column] < 0:
                break
            at = holder[column]
        u[r] += base
        for c in np.flatnonzero(done):
            if c != column:
                u[holder[c]] += base - dist[c]
            v[c] -= base - dist[c]
        while column >= 0:
            before = came[column]
            holder[column] = holder[before] if before >= 0 else r
            column = before
    out = np.empty(n, np.int64)
    out[holder] = np.arange(n)
    return out[:rows]


def match_weights(records: Records, ids: np.ndarray, k: int, instruction: str, labels: list[str], model: Metered, weight: str = "logprob", examples: bool = False, n_examples: int = 3, key: str = "") -> np.ndarray:
    """[cluster, class]: the cluster's size times the model's log-probability (or probability) of the class."""
    out = np.zeros((k, len(labels)))
    members = [np.flatnonzero(ids == c) for c in range(k)]
    for c in range(k):
        if len(members[c]):
            others = {str(o): records.take(_pick(records, members[o], n_examples)) for o in range(k) if o != c and len(members[o])} if examples else None
            logs = np.maximum(np.array(model.score_labels(instruction, labels, records.take(members[c]), others, f"{key}|{c}")), FLOOR)
            out[c] = len(members[c]) * (logs if weight == "logprob" else np.exp(logs))
    return out


def _pick(records: Records, rows: np.ndarray, n: int) -> np.ndarray:
    return rows[np.argsort(uniforms(("examples",), [records.ids[r] for r in rows]), kind="stable")[:n]]


def assign_classes(records: Records, ids: np.ndarray, instruction: str, labels: list[str], model: Metered, params: Params, mode: str | None = None, key: str = "") -> np.ndarray:
    """Class of each cluster."""
    mode, k = mode or params.assign, len(labels)
    if mode == "majority":
        out = np.zeros(k, np.int64)
        for c in range(k):
            rows = np.flatnonzero(ids == c)
            votes = np.zeros(k, np.int64)
            for r in rows:
                votes[labels.index(model.classify(instruction, labels, records.take([r]), key=key)[0])] += 1
            out[c] = votes.argmax()
        return out
    w = match_weights(records, ids, k, instruction, labels, model, params.weight, mode == "with_examples", params.n_examples, key)
    return hungarian(w) if mode == "matching" else w.argmax(axis=1)
