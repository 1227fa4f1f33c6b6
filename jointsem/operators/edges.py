"""Pairwise dissimilarities of a batch from answers about small samples.

The array form runs inside a worker; the DataFrame forms (same names, ending in
_df) do the same set-wise for inspection and for SQL.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from jointsem.functions.hashing import portable_uniform, uniforms


def draw_sample(ids: np.ndarray, size: int, seed: str, batch: int, number: int) -> np.ndarray:
    """Rows of a uniform sample without replacement: those with the least draws."""
    if size >= len(ids):
        return np.arange(len(ids))
    return np.sort(np.lexsort((ids, uniforms((seed, batch, number), ids.tolist())))[:size])


def components(n: int, pairs: np.ndarray) -> np.ndarray:
    """Least member of each element's component, by repeated minimum and pointer jumping."""
    label = np.arange(n)
    while len(pairs):
        a, b = label[pairs[:, 0]], label[pairs[:, 1]]
        differ = a != b
        if not differ.any():
            break
        np.minimum.at(label, np.maximum(a, b)[differ], np.minimum(a, b)[differ])
        while not np.array_equal(label[label], label):
            label = label[label]
    return label


def answered_rows(answer: list[tuple[int, int]], ids: np.ndarray) -> tuple[np.ndarray, int]:
    """Answered id pairs as rows of ids; pairs with strangers or of one record are dropped and counted."""
    row = {int(i): r for r, i in enumerate(ids)}
    good = [(row[a], row[b]) for a, b in answer if a != b and a in row and b in row]
    return np.array(good, np.int64).reshape(-1, 2), len(answer) - len(good)


def positive_matrix(size: int, pairs: np.ndarray, transitive: bool = True) -> np.ndarray:
    """Which pairs of a sample count as one class: all implied ones, or only those answered."""
    if transitive:
        label = components(size, pairs)
        same = label[:, None] == label[None, :]
    else:
        same = np.zeros((size, size), bool)
        same[pairs[:, 0], pairs[:, 1]] = same[pairs[:, 1], pairs[:, 0]] = True
    np.fill_diagonal(same, False)
    return same


class Votes:
    """Counts of positive and negative annotations of all pairs of a batch."""

    def __init__(self, n: int, unseen: float = 0.5):
        self.positive, self.negative, self.unseen = np.zeros((n, n), np.int32), np.zeros((n, n), np.int32), unseen

    def add(self, rows: np.ndarray, same: np.ndarray) -> None:
        at = np.ix_(rows, rows)
        other = ~same
        np.fill_diagonal(other, False)
        self.positive[at] += same
        self.negative[at] += other

    def weights(self) -> np.ndarray:
        """Share of negative annotations; the unseen weight where there is none."""
        seen = self.positive + self.negative
        out = np.full(seen.shape, self.unseen)
        np.divide(self.negative, seen, out=out, where=seen > 0)
        np.fill_diagonal(out, 0)
        return out

    def refresh(self, w: np.ndarray, rows: np.ndarray) -> None:
        """Bring the weights of all pairs of these rows up to date in w."""
        at = np.ix_(rows, rows)
        negative, seen = self.negative[at], self.positive[at] + self.negative[at]
        w[at] = np.where(seen > 0, negative / np.maximum(seen, 1), self.unseen)
        w[rows, rows] = 0

    def per_pair(self) -> float:
        n = len(self.positive)
        return float((self.positive + self.negative).sum()) / (n * (n - 1)) if n > 1 else 0.0


def weights_from_truth(truth: list) -> np.ndarray:
    codes = np.unique(np.array(truth), return_inverse=True)[1].ravel()
    return (codes[:, None] != codes[None, :]).astype(float)


def zero_weight_components(w: np.ndarray) -> np.ndarray:
    return components(len(w), np.argwhere(np.triu(w == 0, 1)))


def round_samples_df(batch: DataFrame, size: int, rounds: int, seed: str) -> DataFrame:
    """(batch_id, id) -> (batch_id, round, id): the sample of each round."""
    from pyspark.sql import Window

    each = batch.select("batch_id", "id", F.explode(F.sequence(F.lit(1), F.lit(rounds))).alias("round"))
    order = Window.partitionBy("batch_id", "round").orderBy(portable_uniform(seed, F.col("batch_id"), F.col("round"), F.col("id")), "id")
    return each.withColumn("place", F.row_number().over(order)).where(F.col("place") <= size).drop("place")


def sample_pairs_df(samples: DataFrame) -> DataFrame:
    """All unordered pairs of each sample: (batch_id, round, a, b) with a < b."""
    other = samples.select("batch_id", "round", F.col("id").alias("b"))
    return samples.withColumnRenamed("id", "a").join(other, ["batch_id", "round"]).where("a < b")


def closed_labels_df(samples: DataFrame, answers: DataFrame) -> DataFrame:
    """(batch_id, round, id, label): the least id that answered pairs connect a record with, inside its sample.

    A sample is as small as a question, so its records and pairs are one row,
    and each pair in turn gives the records of its two labels the lesser one.
    Pairs with a record outside the sample join nothing.
    """
    keys = ["batch_id", "round"]
    held = samples.groupBy(*keys).agg(F.collect_list("id").alias("ids"))
    asked = answers.groupBy(*keys).agg(F.collect_list(F.struct("a", "b")).alias("pairs"))
    merged = """aggregate(coalesce(pairs, array()), transform(ids, i -> struct(i AS id, i AS label)), (known, p) ->
      transform(array(struct(get(filter(known, x -> x.id = p.a), 0).label AS l, get(filter(known, x -> x.id = p.b), 0).label AS r)), o ->
        transform(known, x -> struct(x.id AS id, if(x.label = o.l OR x.label = o.r, least(o.l, o.r), x.label) AS label)))[0])"""
    return held.join(asked, keys, "left").select(*keys, F.inline(F.expr(merged)))


def pair_closure_df(samples: DataFrame, answers: DataFrame) -> DataFrame:
    """Answered pairs and all pairs they imply: (batch_id, round, a, b)."""
    labels = closed_labels_df(samples, answers)
    other = labels.select("batch_id", "round", "label", F.col("id").alias("b"))
    return labels.withColumnRenamed("id", "a").join(other, ["batch_id", "round", "label"]).where("a < b").drop("label")


def pair_complement_df(samples: DataFrame, positives: DataFrame) -> DataFrame:
    """The sample's pairs that are not positive."""
    return sample_pairs_df(samples).join(positives, ["batch_id", "round", "a", "b"], "left_anti")


def edge_weights_df(samples: DataFrame, positives: DataFrame) -> DataFrame:
    """(batch_id, a, b, pos, neg, weight) over the pairs that any sample held."""
    marked = sample_pairs_df(samples).join(positives.withColumn("hit", F.lit(1)), ["batch_id", "round", "a", "b"], "left")
    return (
        marked.groupBy("batch_id", "a", "b")
        .agg(F.count("hit").cast("int").alias("pos"), F.count(F.when(F.col("hit").isNull(), 1)).cast("int").alias("neg"))
        .withColumn("weight", F.col("neg") / (F.col("pos") + F.col("neg")))
    )


def edge_weights_truth_df(records: DataFrame) -> DataFrame:
    """(batch_id, id, truth) -> (batch_id, a, b, weight): 0 inside a class and 1 across."""
    other = records.select("batch_id", F.col("id").alias("b"), F.col("truth").alias("other"))
    return records.withColumnRenamed("id", "a").join(other, "batch_id").where("a < b").select("batch_id", "a", "b", (F.col("truth") != F.col("other")).cast("int").alias("weight"))
