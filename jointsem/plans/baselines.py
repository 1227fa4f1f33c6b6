"""The methods the joint one is compared with."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from jointsem.models.base import Metered, Pool, Records
from jointsem.operators.sampling import assign_batches, sample_batch
from jointsem.plans.cascade import route, row_wise
from jointsem.plans.tasks import Result
from jointsem.sources.stages import stage


def _result(rows: DataFrame, route_name: str, ledger: list[tuple], report: dict | None = None) -> Result:
    missing = {"confidence": "double", "batch_id": "long", "cluster_id": "int"}
    out = rows.select("id", "pred", F.lit(route_name).alias("route"), *[(F.col(c) if c in rows.columns else F.lit(None)).cast(t).alias(c) for c, t in missing.items()])
    cost = sum(r[5] for r in ledger)
    return Result(out, ledger, {"cost": cost, **(report or {})})


def _spent(scored: DataFrame, name: str, tier_name: str, pool: Pool) -> tuple:
    tier = pool.tier(tier_name)
    n, tin, tout = scored.agg(F.count("*"), F.coalesce(F.sum("tokens_in"), F.lit(0)), F.coalesce(F.sum("tokens_out"), F.lit(0))).first()
    return (name, tier_name, int(n), int(tin), int(tout), (tin * tier.price_in + tout * tier.price_out) / 1e6)


def _asked(meter: Metered, name: str, tier_name: str) -> tuple:
    u = meter.usage
    return (name, tier_name, u.calls, u.tokens_in, u.tokens_out, u.cost(meter.tier))


def _collected(df: DataFrame) -> Records:
    rows = df.orderBy("id").collect()
    return Records([r.id for r in rows], [r.text for r in rows], [r.hidden for r in rows] if "hidden" in df.columns else [])


def row_by_row(records: DataFrame, instruction: str, labels: list[str], pool: Pool, tier: str = "strong", context: str = "") -> Result:
    scored = stage(row_wise(records, instruction, labels, pool.tier(tier), context), "rows")
    return _result(scored, f"row_{tier}", [_spent(scored, "rows", tier, pool)])


def batch_prompt(records: DataFrame, instruction: str, labels: list[str], pool: Pool, size: int = 50, tier: str = "strong", seed: str = "batch") -> Result:
    """One call labels all records of a batch."""
    one = pool.tier(tier)

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        meter, pdf = Metered(one), pdf.sort_values("id")
        every = Records(pdf["id"].astype(int).tolist(), pdf["text"].fillna("").tolist(), [None if pd.isna(h) else h for h in pdf["hidden"]] if "hidden" in pdf else [])
        batch = int(pdf["batch_id"].iloc[0])
        out = pd.DataFrame({"id": every.ids, "pred": meter.classify_many(instruction, labels, every, str(batch)), "batch_id": batch, "calls": 0, "tokens_in": 0, "tokens_out": 0})
        out.loc[out.index[:1], ["calls", "tokens_in", "tokens_out"]] = [meter.usage.calls, meter.usage.tokens_in, meter.usage.tokens_out]
        return out

    batches = assign_batches(records, size, seed)
    done = stage(batches.groupBy("batch_id").applyInPandas(work, "id long, pred string, batch_id long, calls long, tokens_in long, tokens_out long"), "batches")
    calls, tin, tout = (int(x or 0) for x in done.agg(F.sum("calls"), F.sum("tokens_in"), F.sum("tokens_out")).first())
    return _result(done, "batch", [("batches", tier, calls, tin, tout, (tin * one.price_in + tout * one.price_out) / 1e6)])


def rubric_then_rows(records: DataFrame, instruction: str, labels: list[str], pool: Pool, sample: int = 50, tier: str = "strong", seed: str = "rubric") -> Result:
    """Guidelines are written from a sample; each record is then read with them."""
    meter = Metered(pool.tier(tier))
    guide = meter.rubric(instruction, labels, _collected(sample_batch(records, sample, seed)))
    scored = stage(row_wise(records, instruction, labels, pool.tier(tier), guide), "rubric")
    return _result(scored, "rubric", [_asked(meter, "rubric", tier), _spent(scored, "rows", tier, pool)], {"rubric": guide})


def plain_cascade(records: DataFrame, instruction: str, labels: list[str], pool: Pool, tau: float) -> Result:
    """Records of which the light model is less sure than tau go to the strong one."""
    light = stage(row_wise(records, instruction, labels, pool.light), "light")
    sure, unsure = route(light, tau)
    strong = stage(row_wise(records.join(unsure.select("id"), "id", "left_semi"), instruction, labels, pool.strong), "strong")
    found = _result(sure.unionByName(strong), "cascade", [_spent(light, "light", "light", pool), _spent(strong, "strong", "strong", pool)], {"tau": tau})
    return found


def most_losses(n: int, target: float, delta: float = 0.1) -> int:
    """The most of n sampled records that may be lost for the share of all that are lost to be at most 1 - target, with probability 1 - delta; -1 if none may be.

    The exact binomial bound: so few losses would have a chance of at most delta if the share were larger.
    """
    lost, chance, found = 1 - target, 0.0, -1
    for k in range(n):
        chance += math.comb(n, k) * lost**k * target ** (n - k)
        if chance > delta:
            break
        found = k
    return found


def target_threshold(confidence: np.ndarray, agree: np.ndarray, target: float, delta: float = 0.1) -> float:
    """The least sampled confidence at which agreement with the strong model is at least target with probability 1 - delta; 0 if any will do, above 1 if none does.

    A record is lost if the light model is sure of it and disagrees.  Thresholds
    are tested from the highest down until one fails, so delta holds for all of
    them together: losses only grow on the way.
    """
    allowed = most_losses(len(agree), target, delta)
    lost = np.sort(confidence[~agree])[::-1]
    if allowed < 0:
        return 1.000001
    if len(lost) <= allowed:
        return 0.0
    above = confidence[confidence > lost[allowed]]
    return float(above.min()) if len(above) else 1.000001


def target_cascade(records: DataFrame, instruction: str, labels: list[str], pool: Pool, target: float = 0.9, sample: int = 200, delta: float = 0.1, seed: str = "target") -> Result:
    """A cascade whose threshold is learnt on a sample that both models read."""
    light = stage(row_wise(records, instruction, labels, pool.light), "light")
    drawn = sample_batch(records, sample, seed)
    both = stage(row_wise(drawn, instruction, labels, pool.strong), "sample")
    pairs = both.select("id", F.col("pred").alias("strong")).join(light, "id").select("confidence", (F.col("strong") == F.col("pred")).alias("agree")).toPandas()
    tau = target_threshold(pairs["confidence"].to_numpy(), pairs["agree"].to_numpy(bool), target, delta)
    sure, unsure = route(light, tau)
    asked = records.join(unsure.select("id"), "id", "left_semi").join(both.select("id"), "id", "left_anti")
    strong = stage(row_wise(asked, instruction, labels, pool.strong), "strong")
    known = both.join(unsure.select("id"), "id", "left_semi")
    ledger = [_spent(light, "light", "light", pool), _spent(both, "sample", "strong", pool), _spent(strong, "strong", "strong", pool)]
    n, left = light.count(), unsure.count()
    return _result(sure.unionByName(strong).unionByName(known), "target_cascade", ledger, {"tau": tau, "light_share": (n - left) / n if n else 1.0})


def text_vectors(records: DataFrame, size: int = 512, extra: str | None = None) -> DataFrame:
    """(id, features): hashed words weighted by rarity, of unit length."""
    from pyspark.ml import Pipeline
    from pyspark.ml.feature import IDF, HashingTF, Normalizer

    text = F.concat_ws(" ", F.lower("text"), *([F.lower(extra)] if extra else []))
    words = records.select("id", F.split(text, r"[^\p{L}\p{N}_]+").alias("words"))
    model = Pipeline(stages=[HashingTF(inputCol="words", outputCol="counts", numFeatures=size), IDF(inputCol="counts", outputCol="weighted"), Normalizer(inputCol="weighted", outputCol="features")]).fit(words)
    return model.transform(words).select("id", "features")


def vector_rows(vectors: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    from pyspark.ml.functions import array_to_vector

    return vectors.select(F.col(id_col).cast("long").alias("id"), array_to_vector(F.col(vector_col).cast("array<double>")).alias("features"))


def kmeans(features: DataFrame, k: int, seed: int = 7, steps: int = 20) -> Result:
    """Clusters of vectors; the instruction plays no part."""
    from pyspark.ml.clustering import KMeans

    model = KMeans(k=k, seed=seed, maxIter=steps).fit(features)
    out = model.transform(features).select("id", F.concat(F.lit("cluster "), F.col("prediction") + 1).alias("pred"), (F.col("prediction") + 1).alias("cluster_id"))
    return _result(out, "kmeans", [], {"inertia": model.summary.trainingCost})


def embedding_kmeans(records: DataFrame, k: int, seed: int = 7) -> Result:
    return kmeans(text_vectors(records), k, seed)


def keyphrase_kmeans(records: DataFrame, instruction: str, k: int, pool: Pool, tier: str = "light", seed: int = 7) -> Result:
    """The model adds phrases that the instruction calls for; then K-means."""
    one = pool.tier(tier)

    def work(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        meter = Metered(one)
        for pdf in parts:
            rows = []
            for n, (i, t) in enumerate(zip(pdf["id"], pdf["text"], strict=True)):
                tin, tout = meter.usage.tokens_in, meter.usage.tokens_out
                words = meter.keyphrases(instruction, Records([int(i)], [t or ""], [pdf["hidden"].iloc[n]] if "hidden" in pdf else []))
                rows.append((i, t, " ".join(words * 4), meter.usage.tokens_in - tin, meter.usage.tokens_out - tout))
            yield pd.DataFrame(rows, columns=["id", "text", "phrases", "tokens_in", "tokens_out"])

    asked = stage(records.mapInPandas(work, "id long, text string, phrases string, tokens_in long, tokens_out long"), "phrases")
    found = kmeans(text_vectors(asked, extra="phrases"), k, seed)
    return Result(found.predictions, [_spent(asked, "phrases", tier, pool)], found.report)


def label_then_assign(records: DataFrame, instruction: str, k: int, pool: Pool, size: int = 50, tier: str = "strong", seed: str = "labels") -> Result:
    """Candidate names per batch are merged into k; each record then gets one of them."""
    one = pool.tier(tier)

    def propose(pdf: pd.DataFrame) -> pd.DataFrame:
        meter, pdf = Metered(one), pdf.sort_values("id")
        every = Records(pdf["id"].astype(int).tolist(), pdf["text"].fillna("").tolist(), [None if pd.isna(h) else h for h in pdf["hidden"]] if "hidden" in pdf else [])
        names = meter.propose_labels(instruction, every, str(pdf["batch_id"].iloc[0]))
        return pd.DataFrame({"name": names or [""], "tokens_in": [meter.usage.tokens_in] + [0] * (max(1, len(names)) - 1), "tokens_out": [meter.usage.tokens_out] + [0] * (max(1, len(names)) - 1)})

    proposed = stage(assign_batches(records, size, seed).groupBy("batch_id").applyInPandas(propose, "name string, tokens_in long, tokens_out long"), "names")
    merger = Metered(one)
    labels = _merged(proposed.where("name <> ''").groupBy("name").agg(F.count("*").alias("n")), instruction, k, merger)
    labels += [f"other {i}" for i in range(len(labels) + 1, k + 1)]
    found = row_by_row(records, instruction, labels, pool, tier)
    spent = proposed.agg(F.sum(F.when(F.col("tokens_in") > 0, 1)), F.sum("tokens_in"), F.sum("tokens_out")).first()
    first = ("proposals", tier, int(spent[0] or 0), int(spent[1] or 0), int(spent[2] or 0), ((spent[1] or 0) * one.price_in + (spent[2] or 0) * one.price_out) / 1e6)
    ledger = [first, _asked(merger, "merging", tier), *found.ledger_rows]
    return Result(found.predictions.withColumn("route", F.lit("label_then_assign")), ledger, {"cost": sum(r[5] for r in ledger), "labels": labels})


def _merged(counts: DataFrame, instruction: str, k: int, merger: Metered, page: int = 1000) -> list[str]:
    """k names from all that were proposed, the most frequent first: pages of names are merged into k each, and these again, so no prompt holds more than a page."""
    names: list[str] = []
    held: list[str] = []
    for r in counts.orderBy(F.desc("n"), "name").toLocalIterator():
        held += [r.name] * min(int(r.n), max(1, page // 20))
        if len(held) >= page:
            names += merger.merge_labels(instruction, held, k)
            held = []
    if not names:
        return merger.merge_labels(instruction, held, k)
    return merger.merge_labels(instruction, names + (merger.merge_labels(instruction, held, k) if held else []), k)


def semantic_group_by(records: DataFrame, instruction: str, k: int, pool: Pool, sample: int = 200, tier: str = "strong", seed: str = "groups", steps: int = 10) -> Result:
    """Groups that the model predicts on a sample give K-means its first centres."""
    from pyspark.ml.functions import vector_to_array

    one = Metered(pool.tier(tier))
    drawn = sample_batch(records, sample, seed)
    part = _collected(drawn)
    names = one.merge_labels(instruction, one.propose_labels(instruction, part), k)
    guessed = stage(row_wise(drawn, instruction, names, pool.tier(tier)), "guessed")
    features = stage(text_vectors(records).select("id", vector_to_array("features").alias("v")), "vectors")
    held = guessed.select("id", "pred").join(features, "id")
    centres = _centres(held.withColumnRenamed("pred", "c"))
    spare = features.join(guessed.select("id"), "id", "left_anti").orderBy("id").limit(max(0, k - len(centres))).collect()
    centres += [np.array(r.v) for r in spare]
    for _ in range(steps):
        table = np.stack(centres)

        def nearest(parts: Iterator[pd.DataFrame], table: np.ndarray = table) -> Iterator[pd.DataFrame]:
            for pdf in parts:
                v = np.stack(pdf["v"].to_numpy()) if len(pdf) else np.zeros((0, table.shape[1]))
                d = (v * v).sum(1)[:, None] - 2 * v @ table.T + (table * table).sum(1)[None, :]
                yield pd.DataFrame({"id": pdf["id"], "v": pdf["v"], "c": d.argmin(1) if len(pdf) else []})

        placed = features.mapInPandas(nearest, "id long, v array<double>, c int")
        new = _centres(placed, len(centres), table)
        if np.allclose(np.stack(new), table):
            break
        centres = new
    out = placed.select("id", F.concat(F.lit("cluster "), F.col("c") + 1).alias("pred"), (F.col("c") + 1).alias("cluster_id"))
    ledger = [_asked(one, "groups", tier), _spent(guessed, "sample", tier, pool)]
    return _result(out, "semantic_group_by", ledger, {"labels": names})


def _centres(placed: DataFrame, k: int | None = None, old: np.ndarray | None = None) -> list[np.ndarray]:
    """Mean vector of each group, in order of the group; k rows of fixed width."""
    each = placed.select("c", F.posexplode("v").alias("d", "x")).groupBy("c", "d").agg(F.avg("x").alias("x"))
    rows = {r.c: np.array([x.x for x in r.xs]) for r in each.groupBy("c").agg(F.array_sort(F.collect_list(F.struct("d", "x"))).alias("xs")).collect()}
    if k is None:
        return [rows[c] for c in sorted(rows)]
    return [rows.get(c, old[c]) for c in range(k)]


def direct_cluster(records: DataFrame, instruction: str, pool: Pool, size: int, tier: str = "strong", seed: str = "direct") -> Result:
    """One question about one large sample, answered with whole clusters."""
    meter = Metered(pool.tier(tier))
    drawn = sample_batch(records, size, seed)
    groups = meter.group_clusters(instruction, _collected(drawn), f"direct{size}")
    rows = [(int(i), f"cluster {c + 1}", c + 1) for c, g in enumerate(groups) for i in g]
    return _result(records.sparkSession.createDataFrame(rows, "id long, pred string, cluster_id int"), "direct", [_asked(meter, "direct", tier)])
