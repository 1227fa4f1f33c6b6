"""Accuracy and cost measures over predictions (id, pred), truth (id, truth), ledgers and reports."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def contingency(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """(truth, pred, n); a record without a prediction has a null one."""
    return truth.select("id", "truth").join(pred.select("id", "pred"), "id", "left").groupBy("truth", "pred").agg(F.count("*").alias("n"))


def accuracy(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: accuracy; a missing prediction is wrong."""
    cells = contingency(pred, truth)
    hit = F.coalesce(F.col("pred").cast("string") == F.col("truth").cast("string"), F.lit(False))
    return cells.agg((F.sum(F.when(hit, F.col("n")).otherwise(0)) / F.sum("n")).alias("accuracy"))


def pairwise_accuracy(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: the share of record pairs ordered alike by prediction and truth, ties included; computed from cells, not pairs."""
    cells = contingency(pred, truth).where("pred is not null").select(F.col("truth").cast("double").alias("t"), F.col("pred").cast("double").alias("p"), "n")
    other = cells.select(F.col("t").alias("t2"), F.col("p").alias("p2"), F.col("n").alias("n2"))
    alike = F.signum(F.col("t") - F.col("t2")) == F.signum(F.col("p") - F.col("p2"))
    itself = (F.col("t") == F.col("t2")) & (F.col("p") == F.col("p2"))
    # ordered pairs of records, without those of a record with itself
    pairs = F.when(itself, F.col("n") * (F.col("n") - 1)).when(alike, F.col("n") * F.col("n2")).otherwise(0)
    total = truth.agg(F.count("*").alias("all"))
    return cells.join(F.broadcast(other)).agg(F.sum(pairs).alias("hits")).join(F.broadcast(total)).select((F.col("hits") / (F.col("all") * (F.col("all") - 1))).alias("pairwise_accuracy"))


def clustering_accuracy(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: each predicted cluster's largest overlap with a true one, summed, over all records."""
    cells = contingency(pred, truth)
    best = cells.where("pred is not null").groupBy("pred").agg(F.max("n").alias("best"))
    return best.agg(F.sum("best").alias("hits")).join(F.broadcast(cells.agg(F.sum("n").alias("all")))).select((F.coalesce("hits", F.lit(0)) / F.col("all")).alias("clustering_accuracy"))


def cost_per_1000(ledger: DataFrame, n: int) -> DataFrame:
    return ledger.agg((1000 * F.coalesce(F.sum("cost"), F.lit(0)) / n).alias("cost_per_1000"))


def frontier(report: DataFrame, by: str = "workload", cost: str = "cost_per_1000", quality: str = "accuracy") -> DataFrame:
    """Rows that no cheaper (or equally cheap) row of their workload reaches or exceeds in quality."""
    before = Window.partitionBy(by).orderBy(F.col(cost), F.desc(quality)).rowsBetween(Window.unboundedPreceding, -1)
    return report.withColumn("_best", F.max(quality).over(before)).where(F.col("_best").isNull() | (F.col(quality) > F.col("_best"))).drop("_best")


def improvement(report: DataFrame, base: str = "row_by_row", quality: str = "accuracy") -> DataFrame:
    """(workload, method, gain) over the base method of the same workload."""
    ground = report.where(F.col("method") == base).select("workload", F.col(quality).alias("_base"))
    return report.where(F.col("method") != base).join(ground, "workload").select("workload", "method", (F.col(quality) - F.col("_base")).alias("gain"))


def suite_average(report: DataFrame, quality: str = "accuracy") -> DataFrame:
    """(method, workload, average) with subtotals: a null workload is the average over all of them."""
    return report.rollup("method", "workload").agg(F.avg(quality).alias("average")).where("method is not null")


def cost_bound(record_tokens: Column | float, label_tokens: Column | float, n, k, m, r, cluster_price: float, assign_price: float, proxy_price: float):
    """Growth of the joint method's cost: record tokens are read by the proxy, m times in the clustered share r and once when labelled; label tokens by the proxy and once per cluster."""
    return record_tokens * (proxy_price + m * r * cluster_price + r * assign_price) + n * label_tokens * (proxy_price + r * k * assign_price)


def weight_separation(edges: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: mean weight of pairs of different classes minus that of pairs of one class."""
    a, b = truth.select(F.col("id").alias("a"), F.col("truth").alias("ta")), truth.select(F.col("id").alias("b"), F.col("truth").alias("tb"))
    both = edges.join(a, "a").join(b, "b")
    same = F.col("ta") == F.col("tb")
    return both.agg((F.avg(F.when(~same, F.col("weight"))) - F.avg(F.when(same, F.col("weight")))).alias("separation"))


def budget_report(report: dict, budget: float) -> dict:
    """Whether a run kept its budget, and how far its plan was off."""
    planned = report.get("planned_cost")
    return {"budget": budget, "cost": report["cost"], "within": report["cost"] <= budget, "planned": planned, "error": None if planned is None else report["cost"] - planned}


def ledger_rollup(ledger: DataFrame) -> DataFrame:
    """Calls, tokens and cost by stage and tier, with subtotals."""
    return ledger.rollup("stage", "tier").agg(F.sum("calls").alias("calls"), F.sum("tokens_in").alias("tokens_in"), F.sum("tokens_out").alias("tokens_out"), F.sum("cost").alias("cost"))


def confusion_cube(pred: DataFrame, truth: DataFrame) -> DataFrame:
    both = truth.select("id", "truth").join(pred.select("id", "pred"), "id", "left")
    return both.cube("truth", "pred").agg(F.count("*").alias("n"), F.grouping_id().cast("int").alias("level"))


def majority(df: DataFrame, cluster: str, label: str) -> DataFrame:
    """(cluster, label): the most frequent label of each cluster; of equals the least."""
    counts = df.groupBy(cluster, label).agg(F.count("*").alias("n"))
    top = Window.partitionBy(cluster).orderBy(F.desc("n"), label)
    return counts.withColumn("_r", F.row_number().over(top)).where("_r = 1").select(cluster, label)
