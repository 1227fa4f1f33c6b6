"""Grouping a batch so that total disagreement with its pairwise weights is least."""

from __future__ import annotations

import functools
import itertools

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from jointsem.functions.hashing import uniform_table

#: From so many starts on they are settled together.  Batches of more records are compared start by start, to hold one matrix at a time.
_TOGETHER = 8
_WIDE = 64


def disagreement(w: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """[record, cluster]: weight kept inside plus similarity cut, were the record in that cluster."""
    n = len(w)
    hot = np.zeros((n, k))
    hot[np.arange(n), ids] = 1
    alike = 1 - w
    np.fill_diagonal(alike, 0)
    gain = 2 * w - 1
    np.fill_diagonal(gain, 0)
    return alike.sum(axis=1)[:, None] + gain @ hot


def objective(w: np.ndarray, ids: np.ndarray, k: int) -> float:
    return float(disagreement(w, ids, k)[np.arange(len(w)), ids].sum())


def _settle(gain: np.ndarray, ids: np.ndarray, k: int, order: np.ndarray, sweeps: int) -> np.ndarray:
    """Move records to their best cluster, in order, until none improves."""
    n = len(gain)
    ids = ids.copy()
    hot = np.zeros((n, k))
    hot[np.arange(n), ids] = 1
    total = gain @ hot
    for _ in range(sweeps):
        # only records that some cluster would improve are visited
        todo = order[total.min(axis=1)[order] < total[order, ids[order]] - 1e-9]
        if not len(todo):
            break
        for a in todo.tolist():
            best = int(total[a].argmin())
            if total[a, best] < total[a, ids[a]] - 1e-9:
                total[:, ids[a]] -= gain[:, a]
                total[:, best] += gain[:, a]
                ids[a] = best
    return ids


def _settle_all(gain: np.ndarray, ids: np.ndarray, k: int, order: np.ndarray, sweeps: int) -> np.ndarray:
    """_settle for many starts at once, one a row of ids and order: each goes its own way, and all take a step together."""
    ids, every, column = ids.copy(), np.arange(len(ids)), np.arange(len(gain))
    total = gain @ (ids[:, :, None] == np.arange(k)).astype(float)
    for _ in range(sweeps):
        todo = total.min(axis=2) < total[every[:, None], column, ids] - 1e-9
        if not todo.any():
            break
        asked = todo[every[:, None], order]
        for p in np.flatnonzero(asked.any(axis=0)).tolist():
            row = np.flatnonzero(asked[:, p])
            a = order[row, p]
            held, mine = ids[row, a], total[row, a]
            best, n = mine.argmin(axis=1), every[: len(row)]
            move = mine[n, best] < mine[n, held] - 1e-9
            row, a, held, best = row[move], a[move], held[move], best[move]
            step = gain.T[a]
            total[row, :, held] -= step
            total[row, :, best] += step
            ids[row, a] = best
    return ids


@functools.lru_cache(maxsize=4)
def _drawn(seed: str, ids: tuple[int, ...]) -> list[np.ndarray]:
    """What _draws() drew for these records so far."""
    return [np.zeros((0, len(ids))), np.zeros((0, len(ids)), np.int64)]


def _draws(seed: str, starts: int, ids: tuple[int, ...]) -> tuple[np.ndarray, np.ndarray]:
    """Draws of each start, and the order in which it visits records; every round of a batch uses them again."""
    known = _drawn(seed, ids)
    if len(known[0]) < starts:
        u = uniform_table([(seed, "start", r) for r in range(len(known[0]), starts)], ids)
        known[:] = np.concatenate([known[0], u]), np.concatenate([known[1], np.argsort(u, axis=1, kind="stable")])
    return known[0][:starts], known[1][:starts]


def correlation_cluster(w: np.ndarray, k: int, record_ids: np.ndarray, seed: str = "joint", restarts: int = 2, start: np.ndarray | None = None, sweeps: int = 50) -> np.ndarray:
    """Clusters 0..k-1 of a local optimum: the best of a warm start, if given, and random starts."""
    n = len(w)
    if k <= 1 or n <= 1:
        return np.zeros(n, np.int64)
    gain = 2 * w - 1
    np.fill_diagonal(gain, 0)
    u, order = _draws(seed, restarts + 1 if start is not None else max(1, restarts), tuple(record_ids.tolist()))
    first = np.minimum((u * k).astype(np.int64), k - 1)
    if start is not None:
        first[0] = start
    if len(first) >= _TOGETHER:
        settled = _settle_all(gain, first, k, order, sweeps)
    else:
        settled = np.array([_settle(gain, f, k, o, sweeps) for f, o in zip(first, order, strict=True)])
    owns = [gain[ids[:, None] == ids[None, :]].sum() for ids in settled] if n > _WIDE else ((settled[:, :, None] == settled[:, None, :]) * gain).sum(axis=(1, 2)).tolist()
    best, value = None, np.inf
    for ids, own in zip(settled, owns, strict=True):
        if own < value - 1e-9:
            best, value = ids, own
    return best


def exact_correlation(w: np.ndarray, k: int) -> tuple[np.ndarray, float]:
    """The optimum by enumeration, for small tests."""
    every = (np.array(x) for x in itertools.product(range(k), repeat=len(w)))
    best = min(every, key=lambda ids: (round(objective(w, ids, k), 9), tuple(ids)))
    return best, objective(w, best, k)


def disagreement_df(edges: DataFrame, clusters: DataFrame) -> DataFrame:
    """edges (batch_id, a, b, weight), clusters (batch_id, id, cluster_id) -> (batch_id, id, cluster_id, d) for every cluster."""
    both = edges.select("batch_id", F.col("a").alias("id"), F.col("b").alias("other"), "weight").unionByName(edges.select("batch_id", F.col("b").alias("id"), F.col("a").alias("other"), "weight"))
    near = both.join(clusters.select("batch_id", F.col("id").alias("other"), F.col("cluster_id").alias("held")), ["batch_id", "other"])
    every = clusters.select("batch_id", "cluster_id").distinct()
    inside = near.groupBy("batch_id", "id", F.col("held").alias("cluster_id")).agg(F.sum(2 * F.col("weight") - 1).alias("inside"))
    outside = near.groupBy("batch_id", "id").agg(F.sum(1 - F.col("weight")).alias("outside"))
    return outside.join(every, "batch_id").join(inside, ["batch_id", "id", "cluster_id"], "left").select("batch_id", "id", "cluster_id", (F.col("outside") + F.coalesce("inside", F.lit(0.0))).alias("d"))


def objective_df(distances: DataFrame, clusters: DataFrame) -> DataFrame:
    """Sum of each record's disagreement with its own cluster, per batch."""
    return distances.join(clusters, ["batch_id", "id", "cluster_id"]).groupBy("batch_id").agg(F.sum("d").alias("objective"))
