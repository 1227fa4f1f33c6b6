"""Ways to score records cheaply before the joint method sees the unsure ones."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from jointsem.models.base import Metered, Pool, Records
from jointsem.operators.sampling import assign_batches, sample_batch
from jointsem.plans.cascade import ROWS, route, row_wise
from jointsem.plans.params import Params
from jointsem.sources.stages import stage


def _paid(scored: DataFrame, name: str, tier_name: str, pool: Pool, calls: int | None = None) -> tuple:
    tier = pool.tier(tier_name)
    n, tin, tout = (int(x or 0) for x in scored.agg(F.count("*"), F.sum("tokens_in"), F.sum("tokens_out")).first())
    return (name, tier_name, n if calls is None else calls, tin, tout, (tin * tier.price_in + tout * tier.price_out) / 1e6)


def proxy_scores(rest: DataFrame, instruction: str, labels: list[str], pool: Pool, tier: str, params: Params) -> tuple[DataFrame, list[tuple]]:
    """(id, pred, confidence, tokens_in, tokens_out) of every record, and ledger rows; how is params.proxy."""
    ways = {"rows": _rows, "ladder": _ladder, "batch": _batch, "rubric": _rubric}
    if params.proxy not in ways:
        raise ValueError(f"no such proxy: {params.proxy}")
    return ways[params.proxy](rest, instruction, labels, pool, tier, params)


def _rows(rest: DataFrame, instruction: str, labels: list[str], pool: Pool, tier: str, params: Params) -> tuple[DataFrame, list[tuple]]:
    scored = stage(row_wise(rest, instruction, labels, pool.tier(tier)), "scores")
    return scored, [_paid(scored, "proxy", tier, pool)]


def _ladder(rest: DataFrame, instruction: str, labels: list[str], pool: Pool, tier: str, params: Params) -> tuple[DataFrame, list[tuple]]:
    """The light model reads all, the strong one what the light one is unsure of; what both are unsure of is left to the joint method."""
    light = stage(row_wise(rest, instruction, labels, pool.light), "light")
    sure, unsure = route(light, params.ladder_tau)
    strong = stage(row_wise(rest.join(unsure.select("id"), "id", "left_semi"), instruction, labels, pool.strong), "strong")
    return sure.unionByName(strong), [_paid(light, "proxy", "light", pool), _paid(strong, "proxy", "strong", pool)]


def _rubric(rest: DataFrame, instruction: str, labels: list[str], pool: Pool, tier: str, params: Params) -> tuple[DataFrame, list[tuple]]:
    """Guidelines written from a sample go with every record."""
    meter = Metered(pool.tier(tier))
    rows = sample_batch(rest, params.call_batch, params.seed).orderBy("id").collect()
    guide = meter.rubric(instruction, labels, Records([r.id for r in rows], [r.text for r in rows], [r.hidden for r in rows] if "hidden" in rest.columns else []))
    scored = stage(row_wise(rest, instruction, labels, pool.tier(tier), guide), "scores")
    u = meter.usage
    return scored, [("proxy rubric", tier, u.calls, u.tokens_in, u.tokens_out, u.cost(meter.tier)), _paid(scored, "proxy", tier, pool)]


def _batch(rest: DataFrame, instruction: str, labels: list[str], pool: Pool, tier: str, params: Params) -> tuple[DataFrame, list[tuple]]:
    """Every record is labelled in two batches of different company; it is sure (1) if both agree, else half sure."""
    one = pool.tier(tier)

    def asked(turn: str) -> DataFrame:
        def work(pdf: pd.DataFrame) -> pd.DataFrame:
            meter, pdf = Metered(one), pdf.sort_values("id")
            every = Records(pdf["id"].astype(int).tolist(), pdf["text"].fillna("").tolist(), [None if pd.isna(h) else h for h in pdf["hidden"]] if "hidden" in pdf else [])
            out = pd.DataFrame({"id": every.ids, "pred": meter.classify_many(instruction, labels, every, f"{turn}{pdf['batch_id'].iloc[0]}"), "confidence": 1.0, "tokens_in": 0, "tokens_out": 0})
            out.loc[out.index[:1], ["tokens_in", "tokens_out"]] = [meter.usage.tokens_in, meter.usage.tokens_out]
            return out

        return assign_batches(rest, params.call_batch, f"{params.seed}{turn}").groupBy("batch_id").applyInPandas(work, ROWS)

    a, b = (asked(turn) for turn in ("a", "b"))
    other = b.select("id", F.col("pred").alias("p2"), F.col("tokens_in").alias("in2"), F.col("tokens_out").alias("out2"))
    agree = F.when(F.col("pred") == F.col("p2"), 1.0).otherwise(0.5)
    scored = stage(a.join(other, "id").select("id", "pred", agree.alias("confidence"), (F.col("tokens_in") + F.col("in2")).alias("tokens_in"), (F.col("tokens_out") + F.col("out2")).alias("tokens_out")), "scores")
    calls = 2 * -(-scored.count() // params.call_batch)
    return scored, [_paid(scored, "proxy", tier, pool, calls)]
