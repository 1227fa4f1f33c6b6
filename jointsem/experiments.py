"""The experiments, on samples of the workloads, under the study profiles of the simulated model.

Numbers from these runs depend on the profiles and are no reproduction of
published accuracies; they show which method wins and how cost and accuracy move.
"""

from __future__ import annotations

import math
from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from jointsem.functions import measures
from jointsem.models.base import Pool, Tier
from jointsem.models.simulated import STUDY, STUDY_LIGHT, SimulatedModel
from jointsem.operators.sampling import evaluation_sample
from jointsem.plans import baselines, tasks
from jointsem.plans.params import Params
from jointsem.sources.stages import stage
from jointsem.workloads import Workload, workload

REPORT = "workload string, method string, budget double, accuracy double, pairwise_accuracy double, clustering_accuracy double, cost_per_1000 double, rounds double, joint_fraction double"
CLASSES = [f"W{i}" for i in range(1, 11)]
SCORES = [f"S{i}" for i in range(1, 6)]
BUDGETED = ["W1", "W3", "W6", "W8", "W9", "W10"]
SAMPLE = 2000


def study_pool(labels: list[str]) -> Pool:
    return Pool(Tier("strong", SimulatedModel(labels, STUDY), 2.5, 10.0), Tier("light", SimulatedModel(labels, STUDY_LIGHT, tag="light"), 0.15, 0.6))


def prepared(spark: SparkSession, sf_dir: str, name: str, size: int = SAMPLE) -> tuple[Workload, DataFrame]:
    """A workload, and its evaluation sample as (id, text, hidden)."""
    w = workload(spark, sf_dir, name)
    w.records = stage(evaluation_sample(w.records, size), f"{name}")
    return w, w.records.withColumnRenamed("truth", "hidden")


def measured(w: Workload, method: str, found: tasks.Result, clusters: bool = False, budget: float | None = None) -> tuple:
    """One report row."""
    n = w.records.count()
    value = lambda df: float(df.first()[0] or 0.0)
    accuracy = None if clusters else value(measures.accuracy(found.predictions, w.records))
    pairwise = value(measures.pairwise_accuracy(found.predictions, w.records)) if w.kind == "score" and not clusters else None
    purity = value(measures.clustering_accuracy(found.predictions, w.records))
    r = found.report
    return (w.name, method, budget, accuracy, pairwise, purity, 1000 * found.cost / max(1, n), r.get("rounds"), r.get("joint_fraction"))


def _joint(w: Workload, records: DataFrame, params: Params | None = None, budget: float = math.inf, task: str | None = None, **options) -> tasks.Result:
    task = task or ("score" if w.kind == "score" else "classify")
    return tasks.run_task(task, records, "id", ["text"], w.instruction, study_pool(w.labels), k=w.k, labels=None if task == "cluster" else w.labels, params=params, budget=budget, hidden="hidden", **options)


def _report(spark: SparkSession, rows: Iterable[tuple]) -> DataFrame:
    return spark.createDataFrame(list(rows), REPORT)


def exp_classification(spark: SparkSession, sf_dir: str, names: list[str] | None = None, size: int = SAMPLE) -> DataFrame:
    """Row-by-row, batch, rubric and joint, without a budget."""
    rows = []
    for name in names or CLASSES:
        w, records = prepared(spark, sf_dir, name, size)
        pool = study_pool(w.labels)
        rows += [
            measured(w, "row_by_row", baselines.row_by_row(records, w.instruction, w.labels, pool)),
            measured(w, "batch", baselines.batch_prompt(records, w.instruction, w.labels, pool)),
            measured(w, "rubric", baselines.rubric_then_rows(records, w.instruction, w.labels, pool)),
            measured(w, "joint", _joint(w, records)),
        ]
    return _report(spark, rows)


def exp_scoring(spark: SparkSession, sf_dir: str, names: list[str] | None = None, size: int = SAMPLE) -> DataFrame:
    return exp_classification(spark, sf_dir, names or SCORES, size)


def exp_overview(spark: SparkSession, sf_dir: str, size: int = SAMPLE) -> DataFrame:
    """Average accuracy of each method over the class and the score workloads."""
    both = exp_classification(spark, sf_dir, None, size).withColumn("task", F.lit("classification")).unionByName(exp_scoring(spark, sf_dir, None, size).withColumn("task", F.lit("scoring")))
    return both.groupBy("task", "method").agg(F.avg("accuracy").alias("accuracy"), F.avg("cost_per_1000").alias("cost_per_1000"))


def exp_budget(spark: SparkSession, sf_dir: str, names: list[str] | None = None, size: int = SAMPLE, targets: tuple = (0.1, 0.3, 0.5, 0.7, 0.9), shares: tuple = (0.25, 0.5, 1.0, 2.0)) -> DataFrame:
    """Cost and accuracy of both tiers row by row, target cascades, and the joint method at budgets relative to the strong row-by-row cost."""
    rows = []
    for name in names or BUDGETED:
        w, records = prepared(spark, sf_dir, name, size)
        pool = study_pool(w.labels)
        strong = baselines.row_by_row(records, w.instruction, w.labels, pool)
        rows += [measured(w, "row_strong", strong), measured(w, "row_light", baselines.row_by_row(records, w.instruction, w.labels, pool, "light")), measured(w, "batch", baselines.batch_prompt(records, w.instruction, w.labels, pool))]
        rows += [measured(w, f"target_{t}", baselines.target_cascade(records, w.instruction, w.labels, pool, t)) for t in targets]
        rows += [measured(w, f"joint_{s}", _joint(w, records, budget=s * strong.cost), budget=s * strong.cost) for s in shares]
    report = stage(_report(spark, rows), "report")
    best = measures.frontier(report).select("workload", "method", F.lit(True).alias("on_frontier"))
    return report.join(best, ["workload", "method"], "left").fillna({"on_frontier": False})


def exp_scoring_budget(spark: SparkSession, sf_dir: str, size: int = SAMPLE) -> DataFrame:
    return exp_budget(spark, sf_dir, ["S3", "S4", "S5"], size)


def exp_clustering(spark: SparkSession, sf_dir: str, names: list[str] | None = None, size: int = SAMPLE) -> DataFrame:
    """K-means on embeddings, label-then-assign, semantic group-by, keyphrases and the joint method, labels withheld."""
    rows = []
    for name in names or CLASSES:
        w, records = prepared(spark, sf_dir, name, size)
        pool = study_pool(w.labels)
        rows += [
            measured(w, "kmeans", baselines.embedding_kmeans(records, w.k), True),
            measured(w, "label_then_assign", baselines.label_then_assign(records, w.instruction, w.k, pool), True),
            measured(w, "semantic_group_by", baselines.semantic_group_by(records, w.instruction, w.k, pool), True),
            measured(w, "keyphrase_kmeans", baselines.keyphrase_kmeans(records, w.instruction, w.k, pool), True),
            measured(w, "joint", _joint(w, records, task="cluster"), True),
        ]
    return _report(spark, rows)


def exp_edge_weights(spark: SparkSession, sf_dir: str, names: tuple = ("W1", "W9", "W3"), size: int = SAMPLE) -> DataFrame:
    """Four ways to get pairwise weights.  Single pair questions grow with the square of a batch, of constant size."""
    ways = {"pairs": Params(), "no_transitivity": Params(transitive=False), "cluster_labels": Params(edge_mode="cluster_labels", max_rounds=60), "pairwise": Params(edge_mode="pairwise")}
    rows = []
    for name in names:
        w, records = prepared(spark, sf_dir, name, size)
        rows += [measured(w, how, _joint(w, records, p)) for how, p in ways.items()]
    return _report(spark, rows)


def exp_assignment(spark: SparkSession, sf_dir: str, size: int = SAMPLE) -> DataFrame:
    """Four ways from clusters to classes, three to scores."""
    rows = []
    for name in ("W1", "W9", "W8"):
        w, records = prepared(spark, sf_dir, name, size)
        rows += [measured(w, how, _joint(w, records, Params(assign=how))) for how in ("independent", "with_examples", "majority", "matching")]
    for name in ("S5", "S3", "S4"):
        w, records = prepared(spark, sf_dir, name, size)
        rows += [measured(w, how, _joint(w, records, Params(score_assign=how))) for how in ("independent", "matching", "order")]
    return _report(spark, rows)


def exp_sensitivity(spark: SparkSession, sf_dir: str, names: tuple = ("W1", "W4"), size: int = SAMPLE) -> DataFrame:
    """One parameter moved at a time."""
    sweeps = [("max_rounds", (50, 200, 800)), ("sample", (20, 40, 80, 160)), ("batch", (100, 200, 400))]
    rows = []
    for name in names:
        w, records = prepared(spark, sf_dir, name, size)
        rows += [measured(w, f"{p}={v}", _joint(w, records, Params(**{p: v}))) for p, values in sweeps for v in values]
    return _report(spark, rows)


def exp_paradox(spark: SparkSession, sf_dir: str, sizes: tuple = (20, 50, 100, 200, 400)) -> DataFrame:
    """One prompt with ever more records to cluster, against many small questions about the largest set."""
    w, records = prepared(spark, sf_dir, "W1", max(sizes))
    truth = w.records
    rows = []
    for s in sizes:
        found = baselines.direct_cluster(records, w.instruction, study_pool(w.labels), s)
        w.records = truth.join(found.predictions.select("id"), "id", "left_semi")
        rows.append(measured(w, f"direct_{s}", found, True))
    w.records = truth
    rows.append(measured(w, "joint", _joint(w, records, Params(batch=max(sizes)), task="cluster"), True))
    return _report(spark, rows)


def exp_controls(spark: SparkSession, sf_dir: str, size: int = SAMPLE) -> DataFrame:
    """K-means where the labels carry no signal stays near chance."""
    from jointsem.sources.tables import read_table

    rows = []
    w, records = prepared(spark, sf_dir, "W14", size)
    rows.append(measured(w, "kmeans", baselines.embedding_kmeans(records, w.k), True))
    w, _ = prepared(spark, sf_dir, "W15", size)
    vectors = baselines.vector_rows(read_table(spark, sf_dir, "embeddings", "vec_id", "embedding"), "vec_id", "embedding")
    rows.append(measured(w, "kmeans", baselines.kmeans(vectors.join(w.records.select("id"), "id", "left_semi"), w.k), True))
    return _report(spark, rows)


def exp_context_flip(spark: SparkSession) -> DataFrame:
    """One record in two datasets: alone it gets one label, with its neighbours as context it gets two."""

    minor = [(i, f"severity {s} note") for i, s in enumerate([1, 1, 2, 2, 1, 2, 1, 2])]
    major = [(i, f"severity {s} note") for i, s in enumerate([9, 8, 9, 8, 9, 8, 9, 9])]
    shared = (100, "severity 5 note")
    pool = Pool(Tier("strong", SplitModel(), 2.5, 10.0), Tier("light", SplitModel(), 0.15, 0.6))
    rows = []
    for name, data in (("minor", minor), ("major", major)):
        df = spark.createDataFrame([*data, shared], "id long, text string")
        alone = baselines.row_by_row(df, "How urgent?", ["not urgent", "urgent"], pool).predictions.where("id = 100").first().pred
        both = tasks.classify(df, "id", ["text"], "How urgent?", ["not urgent", "urgent"], pool).predictions.where("id = 100").first().pred
        rows.append((name, alone, both))
    return spark.createDataFrame(rows, "dataset string, alone string, joint string")


class SplitModel:
    """Reads the number in a text; groups a sample by its widest gap, and calls a lone record urgent from 5 on."""

    @staticmethod
    def _value(text: str) -> int:
        return int("".join(c for c in text if c.isdigit()) or 0)

    def classify(self, instruction, labels, record, context="", key=""):
        return labels[int(self._value(record.texts[0]) >= 5)], -0.1

    def group_pairs(self, instruction, records, key=""):
        ranked = sorted(zip(map(self._value, records.texts), records.ids, strict=True))
        gaps = [b[0] - a[0] for a, b in zip(ranked[:-1], ranked[1:], strict=True)]
        if not gaps or max(gaps) == 0:
            return [(a[1], b[1]) for a, b in zip(ranked[:-1], ranked[1:], strict=True)]
        cut = gaps.index(max(gaps))
        return [(a[1], b[1]) for i, (a, b) in enumerate(zip(ranked[:-1], ranked[1:], strict=True)) if i != cut]

    def score_labels(self, instruction, labels, records, examples=None, key=""):
        mean = sum(map(self._value, records.texts)) / max(1, len(records))
        p = min(0.99, max(0.01, mean / 10))
        return [math.log(1 - p), math.log(p)]
