"""Sending sure records through a row-wise proxy and the rest to the joint method, within a budget."""

from __future__ import annotations

import math
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from jointsem.functions.expressions import render, token_count, tokens_of
from jointsem.models.base import Metered, Records, Tier
from jointsem.sources.stages import spread, stage
from jointsem.sources.tables import ResponseCache

ROWS = "id long, pred string, confidence double, tokens_in long, tokens_out long"
BINS = 4096


def row_wise(records: DataFrame, instruction: str, labels: list[str], tier: Tier, context: str = "", cache: ResponseCache | None = None) -> DataFrame:
    """Each record by itself: column expressions where the model has them, else a narrow map with one model client per partition.

    With a cache, texts that the tier was asked about before are looked up and cost nothing, and new answers are stored before they are used.
    """
    if cache:
        return _cached(records, instruction, labels, tier, context, cache)
    if hasattr(tier.model, "answered"):
        fixed = tokens_of(instruction) + sum(map(tokens_of, labels)) + tokens_of(context) + 2
        answered = tier.model.answered(spread(records).select("id", "text", (token_count(F.col("text")) + fixed).alias("tokens_in")), labels)
        return answered.select("id", "pred", F.exp("log").alias("confidence"), "tokens_in", token_count(F.col("pred")).alias("tokens_out"))

    def work(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        meter = Metered(tier)
        for pdf in parts:
            hidden = pdf["hidden"].where(pdf["hidden"].notna(), None).tolist() if "hidden" in pdf else []
            every = Records(pdf["id"].tolist(), [t or "" for t in pdf["text"]], hidden)
            answers, tokens = meter.classify_rows(instruction, labels, every, context)
            yield pd.DataFrame({"id": every.ids, "pred": [a for a, _ in answers], "confidence": [math.exp(x) for _, x in answers], "tokens_in": [t for t, _ in tokens], "tokens_out": [t for _, t in tokens]}, columns=["id", "pred", "confidence", "tokens_in", "tokens_out"])

    return spread(records).mapInPandas(work, ROWS)


def _cached(records: DataFrame, instruction: str, labels: list[str], tier: Tier, context: str, cache: ResponseCache) -> DataFrame:
    asked = render("{context}\n{instruction}\n{labels}\n```\n{text}\n```", {"context": F.lit(context), "instruction": F.lit(instruction), "labels": F.lit(", ".join(labels)), "text": F.col("text")})
    keyed = stage(cache.keyed(records.withColumn("prompt", asked), tier.name).drop("prompt"), "asked")
    # which record stands for an open text is decided once: chosen anew for each use, answers would be dropped where the choices differ
    open_ = stage(cache.lookup(keyed)[1], "open")
    new = stage(row_wise(open_.drop("key"), instruction, labels, tier, context), "answers")
    cache.store(open_.select("id", "key").join(new, "id").select("key", "pred", "confidence"))
    known, _ = cache.lookup(keyed)
    paid = new.select(F.col("id").alias("_paid"), "tokens_in", "tokens_out")
    spent = lambda c: F.coalesce(c, F.lit(0)).cast("long").alias(c)
    return known.join(paid, F.col("id") == F.col("_paid"), "left").select("id", "pred", "confidence", spent("tokens_in"), spent("tokens_out"))


def predicted_cost(records: DataFrame, instruction: str, labels: list[str], tiers: list[Tier], context: str = "") -> list[float]:
    """Cost of a row-wise pass with each tier, from token counts and prices alone."""
    fixed = tokens_of(instruction) + sum(map(tokens_of, labels)) + tokens_of(context) + 2
    answer = max(map(tokens_of, labels))
    total = records.agg(F.coalesce(F.sum(token_count(F.col("text")) + fixed), F.lit(0)).alias("tin"), F.count("*").alias("n")).first()
    return [(total.tin * t.price_in + answer * total.n * t.price_out) / 1e6 for t in tiers]


def full_joint_feasible(c0: float, n: int, batch: int, budget: float) -> bool:
    return c0 * math.ceil(n / batch) <= budget


def choose_proxy(c0: float, strong_cost: float, budget: float) -> str:
    """The strong model if it could read all the rest within the budget, else the light one."""
    return "strong" if c0 + strong_cost <= budget else "light"


def cost_of_threshold(n_joint: int, batch: int, c0: float, c_proxy: float) -> float:
    return c_proxy + c0 * (1 + math.ceil(n_joint / batch))


def allowed_joint(batch: int, c0: float, c_proxy: float, budget: float) -> float:
    """How many records may go to the joint method; negative if nothing fits."""
    if c0 <= 0:
        return math.inf
    batches = math.floor((budget - c_proxy) / c0 - 1 + 1e-9)
    return batches * batch if batches >= 0 else -1


def choose_threshold(scores: DataFrame, batch: int, c0: float, c_proxy: float, budget: float, column: str = "confidence") -> float | None:
    """The largest score (or 1) with at most the allowed number of records strictly below it; None if no threshold fits.

    Scores are counted in bins, and only the bin where the allowance runs out is
    refined, so the driver sees a bounded number of rows whatever n is.
    """
    allowed = allowed_joint(batch, c0, c_proxy, budget)
    if allowed < 0:
        return None
    if math.isinf(allowed):
        return 1.0
    rows = scores.select(F.least(F.greatest(F.col(column), F.lit(0.0)), F.lit(1.0)).alias("s"))
    if rows.where("s < 1").count() <= allowed:
        return 1.0
    lo, hi, below = 0.0, 1.0, 0
    while True:
        bin_ = F.least(F.floor((F.col("s") - lo) / ((hi - lo) / BINS)), F.lit(BINS - 1))
        bins = rows.where((F.col("s") >= lo) & (F.col("s") <= hi)).groupBy(bin_.alias("b")).agg(F.count("*").alias("n"), F.min("s").alias("least"), F.max("s").alias("most")).orderBy("b").collect()
        # the last bin whose least score is still feasible holds the answer
        chosen = None
        for r in bins:
            if below > allowed:
                break
            chosen, before = r, below
            below += r.n
        if chosen.least == chosen.most:
            return float(chosen.least)
        lo, hi, below = float(chosen.least), float(chosen.most), before


def score_histogram(scores: DataFrame, bins: int, column: str = "confidence") -> DataFrame:
    """(bin, n, below): counts per bin, and how many records lie in lower bins."""
    from pyspark.sql import Window

    counts = scores.groupBy(F.least(F.floor(F.col(column) * bins), F.lit(bins - 1)).cast("int").alias("bin")).agg(F.count("*").alias("n"))
    return counts.withColumn("below", F.coalesce(F.sum("n").over(Window.orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))


def route(scores: DataFrame, tau: float, column: str = "confidence") -> tuple[DataFrame, DataFrame]:
    """Sure records, and those left for the joint method; a score of exactly tau is sure."""
    return scores.where(F.col(column) >= tau), scores.where(F.col(column) < tau)
