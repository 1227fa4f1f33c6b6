"""Samples and batches by hash order: equal results under any partitioning, and no global sort."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from jointsem.functions.hashing import portable_uniform

_PER_BUCKET = 200_000
#: Offsets of the ranges are broadcast, so there are at most so many; beyond, ranges grow.
_MOST_BUCKETS = 1 << 20
#: Batches that a task takes one after the other where there are many, and the most tasks.  With _BUSY tasks a partition, tiny batches share tasks by their records.
_PER_TASK = 8
_TASK_ROWS = 1600
_BUSY = 16
_MOST_TASKS = 100_000


def hash_sample(df: DataFrame, id_col: str, share: float, seed: str) -> DataFrame:
    """Rows whose draw is below share: a filter on the scan."""
    return df.where(portable_uniform(seed, F.col(id_col)) < share)


def sample_batch(df: DataFrame, size: int, seed: str, id_col: str = "id", n: int | None = None) -> DataFrame:
    """A uniform sample: the rows with the least (draw, id).  With the row count n, a filter on the draw keeps all but a few rows from the sort."""
    u = portable_uniform(seed, F.col(id_col))
    rows = df.withColumn("_u", u)
    if n and n > 64 * size:
        near = rows.where(F.col("_u") < min(1.0, (4 * size + 64) / n))
        if near.count() >= size:
            rows = near
    return rows.orderBy("_u", id_col).limit(size).drop("_u")


def evaluation_sample(df: DataFrame, size: int = 2000, seed: str = "evaluation", id_col: str = "id") -> DataFrame:
    return sample_batch(df, size, seed, id_col)


def batch_tasks(batches: int, partitions: int, size: int = _TASK_ROWS // _PER_TASK) -> int:
    """Tasks to spread batches of some size over.  A batch is a few kilobytes but many calls, so bytes are no guide to its work; yet a few tiny ones cost less than the start of a task."""
    shared = max(_BUSY * partitions, batches // max(_PER_TASK, _TASK_ROWS // size))
    return max(1, min(batches, _MOST_TASKS, max(4 * partitions, min(batches // _PER_TASK, shared))))


def assign_batches(df: DataFrame, size: int, seed: str, id_col: str = "id", n: int | None = None, bucket_rows: int = _PER_BUCKET) -> DataFrame:
    """df with batch_id: ceil(n / size) random batches whose sizes differ by one at most.

    Rows are numbered in hash order inside ranges of the hash; the counts of the
    ranges (one small row each) give their offsets.  The result is partitioned
    by batch_id, with a number of partitions that follows the batches; adaptive
    execution would otherwise put hundreds of small batches into one task.
    """
    n = df.count() if n is None else n
    batches = max(1, math.ceil(n / size))
    buckets = min(_MOST_BUCKETS, max(1, math.ceil(n / bucket_rows)))
    rows = df.withColumn("_u", portable_uniform(seed, F.col(id_col))).withColumn("_bucket", F.floor(F.col("_u") * buckets).cast("int"))
    place = F.row_number().over(Window.partitionBy("_bucket").orderBy("_u", id_col)) - 1
    if buckets > 1:
        counts = rows.groupBy("_bucket").count()
        before = F.coalesce(F.sum("count").over(Window.orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        offsets = counts.select("_bucket", before.alias("_before"))
        rows = rows.withColumn("_place", place).join(F.broadcast(offsets), "_bucket")
    else:
        rows = rows.withColumn("_place", place).withColumn("_before", F.lit(0))
    # place * batches / n in whole numbers; beyond what a long holds, in decimals
    kind = "bigint" if n * batches < 2**62 else "decimal(19,0)"
    number = F.expr(f"cast((cast(_place + _before as {kind}) * cast({batches} as {kind})) div cast({max(1, n)} as {kind}) as bigint)")
    tasks = batch_tasks(batches, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), size)
    return rows.withColumn("batch_id", number).drop("_u", "_bucket", "_place", "_before").repartition(tasks, "batch_id")
