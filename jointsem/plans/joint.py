"""Clustering and labelling of batches as one grouped map: a batch is a task's work, independent of all others."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from jointsem.models.base import Metered, Pool, Records
from jointsem.operators.assignment import assign_classes, match_weights
from jointsem.operators.clustering import Clustering, cluster_batch
from jointsem.operators.ordering import order_clusters, precedence, to_scores
from jointsem.plans.params import Params

_USAGE = ["strong_calls", "strong_in", "strong_out", "light_calls", "light_in", "light_out"]
SCHEMA = "id long, pred string, confidence double, batch_id long, cluster_id int, rounds int, bound double, malformed int, " + ", ".join(f"{c} long" for c in _USAGE)

_ARROW = pa.schema([(n, {"long": pa.int64(), "int": pa.int32(), "double": pa.float64(), "string": pa.string()}[t]) for n, t in map(str.split, SCHEMA.split(", "))])


def _records(pdf: pd.DataFrame) -> Records:
    pdf = pdf.sort_values("id")
    return Records(pdf["id"].astype(int).tolist(), pdf["text"].fillna("").tolist(), [None if pd.isna(h) else h for h in pdf["hidden"]] if "hidden" in pdf else [])


def rows_of(table: pa.Table) -> Records:
    """_records of an Arrow table, which small batches are read from much faster."""
    ids = table["id"].to_pylist()
    order = sorted(range(len(ids)), key=ids.__getitem__)
    texts, hidden = table["text"].to_pylist(), table["hidden"].to_pylist() if "hidden" in table.column_names else None
    return Records([int(ids[r]) for r in order], [texts[r] or "" for r in order], [hidden[r] for r in order] if hidden else [])


def label_records(records: Records, task: str, instruction: str, labels: list[str], k: int, pool: Pool, params: Params, batch: int) -> dict[str, list]:
    """Columns of predictions of one batch; usage and clustering figures stand in its first row."""
    asker = Metered(pool.tier(params.cluster_tier))
    found = cluster_batch(records, instruction, k, asker, params, batch)
    return _labelled(records, found, asker, task, instruction, labels, k, pool, params, batch)


def _labelled(records: Records, found: Clustering, asker: Metered, task: str, instruction: str, labels: list[str], k: int, pool: Pool, params: Params, batch: int) -> dict[str, list]:
    labeller, ids, key = Metered(pool.tier(params.assign_tier)), found.ids, str(batch)
    if task == "cluster" and not labels:
        names: list[str] = []
        for c in range(k):
            name = labeller.summarize(instruction, records.take(np.flatnonzero(ids == c)), key) if (ids == c).any() else f"empty {c + 1}"
            names.append(name if name not in names else f"{name} #{c + 1}")
        pred = [names[c] for c in ids]
    elif task == "score" and params.score_assign == "order":
        w = precedence(records, ids, k, instruction, labeller, params.m_sort, params.seed, key)
        used = [c for c in range(k) if (ids == c).any()]
        order = [used[i] for i in order_clusters(w[np.ix_(used, used)])]
        logs = match_weights(records, ids, k, instruction, labels, labeller, key=key) if len(used) < k else None
        score = to_scores(order, logs, k)
        pred = [labels[score[c] - 1] for c in ids]
    else:
        mode = params.score_assign if task == "score" else params.assign
        chosen = assign_classes(records, ids, instruction, labels, labeller, params, mode, key)
        pred = [labels[chosen[c]] for c in ids]
    n = len(records)
    once = dict.fromkeys(["malformed", *_USAGE], 0) | {"malformed": found.malformed}
    for tier, meter in ((params.cluster_tier, asker), (params.assign_tier, labeller)):
        for c, v in (("calls", meter.usage.calls), ("in", meter.usage.tokens_in), ("out", meter.usage.tokens_out)):
            once[f"{tier}_{c}"] += v
    return {
        "id": records.ids, "pred": pred, "confidence": [1.0] * n, "batch_id": [batch] * n, "cluster_id": ids + 1, "rounds": [found.rounds] * n,
        "bound": [found.trace[-1][1] if found.trace else 0.0] * n, **{c: [v, *[0] * (n - 1)][:n] for c, v in once.items()},
    }


def label_batches(batches: DataFrame, task: str, instruction: str, labels: list[str], k: int, pool: Pool, params: Params) -> DataFrame:
    """(batch_id, id, text[, hidden]) -> SCHEMA."""

    def work(table: pa.Table) -> pa.Table:
        return pa.table(label_records(rows_of(table), task, instruction, labels, k, pool, params, table["batch_id"][0].as_py()), schema=_ARROW)

    return batches.groupBy("batch_id").applyInArrow(work, SCHEMA)


def label_clusters(clustered: DataFrame, task: str, instruction: str, labels: list[str], k: int, pool: Pool, params: Params) -> DataFrame:
    """(batch_id, id, cluster_id, text[, hidden]) -> SCHEMA: the given clusters are labelled, and nothing is clustered anew."""

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("id")
        found = Clustering(pdf["cluster_id"].to_numpy(np.int64) - 1, np.zeros((0, 0)), 0)
        return pd.DataFrame(_labelled(_records(pdf), found, Metered(pool.tier(params.cluster_tier)), task, instruction, labels, k, pool, params, int(pdf["batch_id"].iloc[0])))

    return clustered.groupBy("batch_id").applyInPandas(work, SCHEMA)


def cluster_batches(batches: DataFrame, instruction: str, k: int, pool: Pool, params: Params) -> DataFrame:
    """(batch_id, id, cluster_id) with clusters 1..k per batch, without labels."""

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        records, batch = _records(pdf), int(pdf["batch_id"].iloc[0])
        found = cluster_batch(records, instruction, k, Metered(pool.tier(params.cluster_tier)), params, batch)
        return pd.DataFrame({"batch_id": batch, "id": records.ids, "cluster_id": (found.ids + 1).astype("int32")})

    return batches.groupBy("batch_id").applyInPandas(work, "batch_id long, id long, cluster_id int")


def trace_batches(batches: DataFrame, instruction: str, k: int, pool: Pool, params: Params) -> DataFrame:
    """(batch_id, round, bound, objective, moved): how each batch's clustering settled."""

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        batch = int(pdf["batch_id"].iloc[0])
        found = cluster_batch(_records(pdf), instruction, k, Metered(pool.tier(params.cluster_tier)), params, batch)
        return pd.DataFrame([(batch, *t) for t in found.trace], columns=["batch_id", "round", "bound", "objective", "moved"])

    return batches.groupBy("batch_id").applyInPandas(work, "batch_id long, round int, bound double, objective double, moved int")


def usage_rows(labelled: DataFrame, stage_name: str, pool: Pool) -> list[tuple]:
    """Ledger rows (stage, tier, calls, tokens_in, tokens_out, cost) of label_batches() output."""
    total = labelled.agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in _USAGE]).first()
    out = []
    for tier in (pool.strong, pool.light):
        kind = "strong" if tier is pool.strong else "light"
        calls, tin, tout = (int(total[f"{kind}_{c}"]) for c in ("calls", "in", "out"))
        if calls:
            out.append((stage_name, kind, calls, tin, tout, (tin * tier.price_in + tout * tier.price_out) / 1e6))
    return out
