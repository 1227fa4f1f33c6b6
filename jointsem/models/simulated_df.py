"""The simulated model's draws as column expressions: the same answers set-wise, for inspection and for oracles."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from jointsem.functions.hashing import portable_uniform
from jointsem.models.simulated import Profile


def other_class(label: Column, u: Column | float, labels: list[str]) -> Column:
    """The class a slip leads to: mostly the next one."""
    k, u = len(labels), u if isinstance(u, Column) else F.lit(u)
    names = F.array(*map(F.lit, labels))
    step = F.when(u < 0.8, 1).otherwise(1 + F.floor((u - 0.8) * 5 * (k - 1)).cast("int"))
    return F.get(names, F.pmod(F.array_position(names, label) - 1 + step, F.lit(k)).cast("int"))


def simulated_rows(records: DataFrame, labels: list[str], profile: Profile, seed: str = "sim", tag: str = "") -> DataFrame:
    """(id, hidden) -> (id, pred, confidence), as SimulatedModel.classify answers."""
    own = seed + tag
    ambiguous = portable_uniform(seed, "ambiguous", F.col("id")) < profile.ambiguous
    wrong = portable_uniform(own, "row", F.col("id")) < profile.row
    u = portable_uniform(own, "confidence", F.col("id"))
    pred = F.when(ambiguous, other_class(F.col("hidden"), 0.0, labels)).when(wrong, other_class(F.col("hidden"), portable_uniform(own, "other", F.col("id")), labels)).otherwise(F.col("hidden"))
    return records.select("id", pred.alias("pred"), F.when(ambiguous | wrong, 0.2 + 0.6 * u).otherwise(0.6 + 0.4 * u).alias("confidence"))


def simulated_pairs(samples: DataFrame, truth: DataFrame, labels: list[str], profile: Profile, seed: str = "sim") -> DataFrame:
    """Answers of SimulatedModel.group_pairs, for a reach of 1 and samples within the profile's room, for every sample (batch_id, round, id): (batch_id, round, a, b)."""
    key = F.concat_ws("|", F.col("batch_id").cast("string"), F.col("round").cast("string"))
    held = samples.join(truth.select("id", F.col("truth").alias("c")), "id")
    slip = portable_uniform(seed, "group", key, F.col("id")) < profile.group
    seen = held.withColumn("seen", F.when(slip, other_class(F.col("c"), portable_uniform(seed, "group", "other", key, F.col("id")), labels)).otherwise(F.col("c")))
    before = F.lag("id").over(Window.partitionBy("batch_id", "round", "seen").orderBy("id"))
    linked = seen.withColumn("a", before).where("a is not null").withColumn("u", portable_uniform(seed, "drop", key, F.col("a"), F.col("id")))
    return linked.where(F.col("u") >= profile.drop).select("batch_id", "round", "a", F.col("id").alias("b"))


def simulated_clusters(samples: DataFrame, truth: DataFrame, labels: list[str], profile: Profile, seed: str = "sim") -> DataFrame:
    """Pairs inside the clusters that SimulatedModel.group_clusters answers."""
    key = F.concat_ws("|", F.col("batch_id").cast("string"), F.col("round").cast("string"))
    held = samples.join(truth.select("id", F.col("truth").alias("c")), "id")
    slip = portable_uniform(seed, "clusters", key, F.col("id")) < profile.clusters
    seen = held.select("batch_id", "round", "id", F.when(slip, other_class(F.col("c"), portable_uniform(seed, "clusters", "other", key, F.col("id")), labels)).otherwise(F.col("c")).alias("seen"))
    other = seen.select("batch_id", "round", "seen", F.col("id").alias("b"))
    return seen.withColumnRenamed("id", "a").join(other, ["batch_id", "round", "seen"]).where("a < b").select("batch_id", "round", "a", "b")


def simulated_same(records: DataFrame, profile: Profile, seed: str = "sim", key: str = "0") -> DataFrame:
    """(batch_id, id, truth) -> (batch_id, a, b, weight): each pair asked by itself, 1 if judged different."""
    other = records.select("batch_id", F.col("id").alias("b"), F.col("truth").alias("t2"))
    pairs = records.withColumnRenamed("id", "a").join(other, "batch_id").where("a < b")
    flip = portable_uniform(seed, "pair", key, F.col("a"), F.col("b")) < profile.pair
    return pairs.select("batch_id", "a", "b", ((F.col("truth") != F.col("t2")) != flip).cast("int").alias("weight"))
