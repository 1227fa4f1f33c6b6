"""From clusters to scores: sampled comparisons, and the total order that breaks fewest of them."""

from __future__ import annotations

import itertools

import numpy as np

from jointsem.functions.hashing import uniform
from jointsem.models.base import Metered, Records

EXACT = 16


def precedence(records: Records, ids: np.ndarray, k: int, instruction: str, model: Metered, m_sort: int, seed: str, key: str = "") -> np.ndarray:
    """[i, j]: share of sampled record pairs in which the one of cluster i is judged lower; 0.5 where a cluster is empty."""
    out = np.full((k, k), 0.5)
    members = [np.flatnonzero(ids == c) for c in range(k)]
    for i, j in itertools.permutations(range(k), 2):
        if len(members[i]) and len(members[j]):
            low = 0
            for t in range(m_sort):
                a = members[i][int(uniform(seed, "a", key, i, j, t) * len(members[i]))]
                b = members[j][int(uniform(seed, "b", key, i, j, t) * len(members[j]))]
                low += model.compare(instruction, records.take([a]), records.take([b]), f"{key}|{i}|{j}|{t}")
            out[i, j] = low / m_sort
    return out


def ordering_objective(w: np.ndarray, order: list[int]) -> float:
    """Sum over pairs placed i below j of the share that judges j lower."""
    return float(sum(w[order[b], order[a]] for a in range(len(order)) for b in range(a + 1, len(order))))


def order_clusters(w: np.ndarray) -> list[int]:
    """Clusters from lowest to highest with least violation: exact by subsets up to EXACT clusters, else insertion until stable."""
    k = len(w)
    if k <= 1:
        return list(range(k))
    if k > EXACT:
        return _insertion(w)
    # best[s]: least violation of any order of the set s, with s below everything else
    size = 1 << k
    above = np.zeros((k, size))
    for i in range(k):
        above[:, 1 << i : 2 << i] = above[:, : 1 << i] + w[:, i][:, None]
    best, last = np.full(size, np.inf), np.zeros(size, np.int64)
    best[0] = 0
    for s in range(1, size):
        for j in range(k):
            if s >> j & 1:
                value = best[s ^ 1 << j] + above[j, s ^ 1 << j]
                if value < best[s] - 1e-12:
                    best[s], last[s] = value, j
    out, s = [], size - 1
    while s:
        out.append(int(last[s]))
        s ^= 1 << last[s]
    return out[::-1]


def _insertion(w: np.ndarray) -> list[int]:
    order = np.argsort(w.sum(axis=0) - w.sum(axis=1), kind="stable").tolist()
    improved = True
    while improved:
        improved = False
        for j in list(order):
            rest = [x for x in order if x != j]
            costs = [ordering_objective(w, rest[:p] + [j] + rest[p:]) for p in range(len(order))]
            p = int(np.argmin(costs))
            if costs[p] < ordering_objective(w, order) - 1e-12:
                order, improved = rest[:p] + [j] + rest[p:], True
    return order


def to_scores(order: list[int], logs: np.ndarray | None, k: int) -> dict[int, int]:
    """Score 1..k of each cluster in order; with fewer clusters than scores, the increasing choice of highest total log-probability."""
    if len(order) == k or logs is None:
        return {c: p + 1 for p, c in enumerate(order)}
    m = len(order)
    best, came = np.full((m + 1, k + 1), -np.inf), np.zeros((m + 1, k + 1), bool)
    best[0] = 0
    for p in range(1, m + 1):
        for s in range(p, k + 1):
            take, skip = best[p - 1, s - 1] + logs[order[p - 1], s - 1], best[p, s - 1]
            came[p, s] = take >= skip
            best[p, s] = max(take, skip)
    out, p, s = {}, m, k
    while p:
        if came[p, s]:
            out[order[p - 1]] = s
            p -= 1
        s -= 1
    return out
