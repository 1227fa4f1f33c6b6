"""The methods on streams: windows of predicted classes, a frozen row-wise pass, and joint batches as unsure records gather."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from jointsem.models.base import Pool
from jointsem.operators.sampling import assign_batches
from jointsem.plans.cascade import row_wise
from jointsem.plans.joint import label_batches
from jointsem.plans.params import Params
from jointsem.sources.tables import read_or_empty, read_table


def stream_table(spark: SparkSession, sf_dir: str, name: str, files_per_trigger: int = 1) -> DataFrame:
    """A given table as a file stream; ts becomes a timestamp, since watermarks need one."""
    schema = read_table(spark, sf_dir, name).schema
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).option("pathGlobFilter", f"{name}*.parquet").parquet(sf_dir)
    return rows.withColumn("ts", F.col("ts").cast("timestamp")) if "ts" in rows.columns else rows


def with_lateness(rows: DataFrame, column: str = "ts", delay: str = "1 hour") -> DataFrame:
    return rows.withWatermark(column, delay)


def windowed_counts(rows: DataFrame, column: str, by: str, size: str | None = None, slide: str | None = None, gap: str | None = None) -> DataFrame:
    """(start, end, by, n) over tumbling, sliding or session windows."""
    window = F.session_window(column, gap) if gap else F.window(column, size, slide) if slide else F.window(column, size)
    return rows.groupBy(window.alias("w"), by).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), by, "n")


def deduplicated(rows: DataFrame, key: str) -> DataFrame:
    """The first of rows with one key, within the watermark."""
    return rows.dropDuplicatesWithinWatermark([key])


def stream_row_by_row(records: DataFrame, instruction: str, labels: list[str], pool: Pool, tier: str = "light") -> DataFrame:
    """(id, text[, hidden]) on a stream -> predictions, each record by itself."""
    return row_wise(records, instruction, labels, pool.tier(tier))


def with_customers(events: DataFrame, customers: DataFrame) -> DataFrame:
    """A stream joined with a static table on the user; Spark broadcasts the table if it is small."""
    return events.join(customers, events.user_id == customers.c_custkey, "left")


def late_truth(predictions: DataFrame, truth: DataFrame, within: str = "2 hours") -> DataFrame:
    """Predictions (id, pred, ts) joined with truth (id, truth, seen) that arrives within a time; both streams need watermarks."""
    p, t = predictions.alias("p"), truth.alias("t")
    near = (F.col("p.id") == F.col("t.id")) & (F.col("t.seen") >= F.col("p.ts")) & (F.col("t.seen") <= F.col("p.ts") + F.expr(f"INTERVAL {within}"))
    return p.join(t, near).select(F.col("p.id").alias("id"), "pred", "truth", F.col("p.ts").alias("ts"))


class JointSink:
    """foreachBatch target: sure records are predicted at once, unsure ones wait until a batch is full.

    The threshold and labels are frozen from a bootstrap run.  Everything is
    written under the epoch it came from, so an epoch that is delivered twice
    overwrites itself.  When the budget is spent, every record goes to the proxy.
    What flush() labels stands apart from the epochs, under the last one it took
    records of, so neither a later epoch nor a second flush can overwrite it.
    """

    def __init__(self, folder: str, instruction: str, labels: list[str], pool: Pool, tau: float, params: Params | None = None, budget: float = math.inf, proxy: str = "light"):
        self.folder, self.instruction, self.labels, self.pool = folder.rstrip("/"), instruction, labels, pool
        self.tau, self.params, self.budget, self.proxy = tau, params or Params(), budget, proxy

    def _read(self, spark: SparkSession, name: str, schema: str) -> DataFrame:
        return read_or_empty(spark, f"{self.folder}/{name}", schema)

    def _both(self, spark: SparkSession, name: str, schema: str) -> DataFrame:
        """What epochs and flushes wrote; flushed tells them apart."""
        of = [self._read(spark, f"{at}{name}", schema).withColumn("flushed", F.lit(bool(at))) for at in ("", "flushed_")]
        return of[0].unionByName(of[1])

    def spent(self, spark: SparkSession, epoch: int | None = None) -> float:
        """Money spent, in all or before an epoch; so an epoch that is delivered twice decides alike."""
        before = F.lit(True) if epoch is None else F.col("epoch") < epoch
        return self._both(spark, "ledger", "cost double, epoch long").where(before).agg(F.coalesce(F.sum("cost"), F.lit(0.0))).first()[0]

    def predictions(self, spark: SparkSession) -> DataFrame:
        return self._both(spark, "predictions", "id long, pred string, route string, epoch long").drop("flushed")

    def pending(self, spark: SparkSession, epoch: int | None = None) -> DataFrame:
        """Unsure records without a joint prediction yet, as seen before an epoch: those of the epochs since the last joint batch or flush, which took all that waited."""
        before = F.lit(True) if epoch is None else F.col("flushed") | (F.col("epoch") < epoch)
        last = self._both(spark, "ledger", "cost double, joint boolean, epoch long").where(F.col("joint") & before).agg(F.max("epoch")).first()[0]
        waiting = self._read(spark, "waiting", "id long, text string, hidden string, epoch long")
        return waiting if last is None else waiting.where(F.col("epoch") > last)

    def _write(self, df: DataFrame, name: str, epoch: int) -> None:
        df.drop("epoch").write.mode("overwrite").parquet(f"{self.folder}/{name}/epoch={epoch}")

    def __call__(self, rows: DataFrame, epoch: int) -> None:
        spark = rows.sparkSession
        if "hidden" not in rows.columns:
            rows = rows.withColumn("hidden", F.lit(None).cast("string"))
        rows = rows.select("id", "text", "hidden").persist()
        tier = self.pool.tier(self.proxy)
        scored = row_wise(rows, self.instruction, self.labels, tier).persist()
        cost = scored.agg(F.coalesce(F.sum(F.col("tokens_in") * tier.price_in + F.col("tokens_out") * tier.price_out), F.lit(0.0))).first()[0] / 1e6
        open_ = self.spent(spark, epoch) < self.budget
        sure = scored.where(F.col("confidence") >= self.tau) if open_ else scored
        self._write(rows.join(scored.where(F.col("confidence") < self.tau).select("id"), "id", "left_semi") if open_ else rows.limit(0), "waiting", epoch)
        out = sure.select("id", "pred", F.lit("proxy").alias("route"))
        waiting = self.pending(spark, epoch).where(F.col("epoch") <= epoch).persist()
        size = self.params.batch_size(len(self.labels))
        full = open_ and waiting.count() >= size
        if full:
            joint, price = self._joint(waiting.drop("epoch"))
            out, cost = out.unionByName(joint), cost + price
        self._write(out, "predictions", epoch)
        self._write(spark.createDataFrame([(float(cost), full)], "cost double, joint boolean"), "ledger", epoch)
        for df in (rows, scored, waiting):
            df.unpersist()

    def _joint(self, waiting: DataFrame) -> tuple[DataFrame, float]:
        from jointsem.plans.joint import usage_rows
        from jointsem.sources.stages import stage

        size = self.params.batch_size(len(self.labels))
        done = stage(label_batches(assign_batches(waiting, size, self.params.seed), "classify", self.instruction, self.labels, len(self.labels), self.pool, self.params), "stream")
        return done.select("id", "pred", F.lit("joint").alias("route")), sum(r[5] for r in usage_rows(done, "joint", self.pool))

    def flush(self, spark: SparkSession) -> None:
        """Label whatever still waits, as when a timer fires or the stream ends; call it between epochs."""
        waiting = self.pending(spark)
        epoch = waiting.agg(F.max("epoch")).first()[0]
        if epoch is not None:
            joint, cost = self._joint(waiting.drop("epoch"))
            self._write(joint, "flushed_predictions", epoch)
            self._write(spark.createDataFrame([(float(cost), True)], "cost double, joint boolean"), "flushed_ledger", epoch)


def run_available(stream: DataFrame, target: Callable[[DataFrame, int], None], checkpoint: str) -> None:
    """Process what the source holds now, epoch by epoch, and stop."""
    stream.writeStream.foreachBatch(target).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
