"""When a clustering is settled: a bound on how many records may still be misplaced."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def margins(d: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """Half of how much closer a record is to its own cluster than to the next best; never below 0."""
    own = d[np.arange(len(d)), ids]
    if d.shape[1] < 2:
        return np.full(len(d), np.inf)
    other = d.copy()
    other[np.arange(len(d)), ids] = np.inf
    return np.maximum(0, (other.min(axis=1) - own) / 2)


def uncertain_bound(d: np.ndarray, ids: np.ndarray, seen: float) -> float:
    """Upper bound on the expected number of uncertain records after `seen` annotations per pair."""
    if d.shape[1] < 2:
        return 0.0
    size = np.bincount(ids, minlength=d.shape[1])
    spread = (1 / size[size > 0].astype(float) ** 2).sum()
    return float(np.exp(-2 * seen * margins(d, ids) ** 2 * spread).sum())


def should_stop(bound: float, n: int, share: float) -> bool:
    return bound < share * n


def uncertain_bound_df(distances: DataFrame, clusters: DataFrame, seen: float) -> DataFrame:
    """uncertain_bound over disagreement_df() output: (batch_id, bound)."""
    own = distances.join(clusters, ["batch_id", "id", "cluster_id"]).select("batch_id", "id", F.col("d").alias("own"), F.col("cluster_id").alias("held"))
    gap = distances.join(own, ["batch_id", "id"]).where("cluster_id <> held").groupBy("batch_id", "id", "own").agg(F.min("d").alias("other"))
    margin = gap.select("batch_id", F.greatest(F.lit(0.0), (F.col("other") - F.col("own")) / 2).alias("margin"))
    size = clusters.groupBy("batch_id", "cluster_id").count().groupBy("batch_id").agg(F.sum(1 / F.pow("count", F.lit(2))).alias("spread"))
    return margin.join(size, "batch_id").groupBy("batch_id").agg(F.sum(F.exp(-2 * seen * F.col("margin") * F.col("margin") * F.col("spread"))).alias("bound"))
