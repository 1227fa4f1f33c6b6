"""Clustering one batch by repeated small questions, until its grouping is settled."""

from __future__ import annotations

from dataclasses import dataclass, field
from typing import TYPE_CHECKING

import numpy as np

from jointsem.models.base import Metered, Records
from jointsem.operators.correlation import correlation_cluster, disagreement, objective
from jointsem.operators.edges import Votes, answered_rows, draw_sample, positive_matrix
from jointsem.operators.stopping import should_stop, uncertain_bound

if TYPE_CHECKING:
    from jointsem.plans.params import Params


@dataclass
class Clustering:
    ids: np.ndarray
    weights: np.ndarray
    rounds: int
    malformed: int = 0
    trace: list[tuple[int, float, float, int]] = field(default_factory=list)


def _pairwise(records: Records, instruction: str, model: Metered, params: Params, context: bool) -> np.ndarray:
    """Every pair asked by itself, with or without a sample as context; answers of several rounds are averaged."""
    n = len(records)
    w = np.zeros((n, n))
    rounds = params.pair_rounds if context else 1
    ids = np.array(records.ids)
    for r in range(rounds):
        around = records.take(draw_sample(ids, params.sample, params.seed, 0, r)) if context else None
        for a in range(n):
            for b in range(a + 1, n):
                w[a, b] += not model.same(instruction, records.take([a]), records.take([b]), around, f"{r}")
    w /= rounds
    return w + w.T


def in_order(ids: np.ndarray, k: int) -> np.ndarray:
    """Clusters numbered by their first record, so that equal groupings have equal numbers."""
    seen, first = np.unique(ids, return_index=True)
    number = np.zeros(k, np.int64)
    number[seen[np.argsort(first)]] = np.arange(len(seen))
    return number[ids]


def ask_round(records: Records, ids: np.ndarray, instruction: str, model: Metered, params: Params, batch: int, number: int, votes: Votes, w: np.ndarray) -> int:
    """One question about a sample of the batch: its answers are counted in votes and w; returns how many were malformed."""
    rows = draw_sample(ids, params.sample, params.seed, batch, number)
    part = records.take(rows)
    if params.edge_mode == "cluster_labels":
        groups = model.group_clusters(instruction, part, f"{batch}|{number}")
        answer = [p for g in groups for p in zip(g[:-1], g[1:], strict=True)]
        transitive = True
    else:
        answer, transitive = model.group_pairs(instruction, part, f"{batch}|{number}"), params.transitive
    pairs, bad = answered_rows(answer, ids[rows])
    votes.add(rows, positive_matrix(len(rows), pairs, transitive))
    votes.refresh(w, rows)
    return bad


def cluster_batch(records: Records, instruction: str, k: int, model: Metered, params: Params, batch: int = 0) -> Clustering:
    """Clusters 0..k-1, numbered by their first records.  The trace holds (round, bound, objective, records moved).

    With a warm start, random starts are tried in the first round and where the
    questions would end; a better grouping found there puts the end off.
    """
    n = len(records)
    ids = np.array(records.ids, np.int64)
    search = {"k": k, "record_ids": ids, "seed": params.seed, "restarts": params.restarts}
    if n <= 1 or k <= 1:
        return Clustering(np.zeros(n, np.int64), np.zeros((n, n)), 0)
    if params.edge_mode in ("pairwise", "pairwise_context"):
        w = _pairwise(records, instruction, model, params, params.edge_mode == "pairwise_context")
        return Clustering(in_order(correlation_cluster(w, **search), k), w, 1)
    votes, out = Votes(n, params.unseen_weight), Clustering(np.zeros(n, np.int64), np.zeros((n, n)), 0)
    w = votes.weights()
    for r in range(1, params.max_rounds + 1):
        bad = ask_round(records, ids, instruction, model, params, batch, r, votes, w)
        warm = params.start == "warm" and r > 1
        new = in_order(correlation_cluster(w, start=out.ids, **(search | {"restarts": 0})) if warm else correlation_cluster(w, **search), k)
        seen = votes.per_pair() if params.rounds_seen == "pair_mean" else r
        bound = uncertain_bound(disagreement(w, new, k), new, seen)
        done = should_stop(bound, n, params.stop_share)
        if warm and (done or r == params.max_rounds):
            new = in_order(correlation_cluster(w, start=new, **search), k)
            bound = uncertain_bound(disagreement(w, new, k), new, seen)
            done = should_stop(bound, n, params.stop_share)
        out.trace.append((r, bound, objective(w, new, k), int((new != out.ids).sum())))
        out.ids, out.weights, out.rounds, out.malformed = new, w, r, out.malformed + bad
        if done:
            break
    return out
