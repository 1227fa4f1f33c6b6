"""Reading the given tables and other sources; writing predictions and ledgers."""

from __future__ import annotations

import uuid

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read_table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A Parquet table of the folder, with only the columns asked for."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_any(spark: SparkSession, path: str, fmt: str, schema: str | None = None, **options) -> DataFrame:
    """CSV, JSON, ORC, text, JDBC or any other source Spark knows; give a schema to spare its inference."""
    reader = spark.read.format(fmt).options(**options)
    if schema:
        reader = reader.schema(schema)
    return reader.load(path) if path else reader.load()


def read_or_empty(spark: SparkSession, path: str, schema: str) -> DataFrame:
    """A Parquet table, or an empty one if nothing was written there yet; every other error is raised."""
    try:
        return spark.read.schema(schema).parquet(path)
    except AnalysisException as error:
        if error.getCondition() != "PATH_NOT_FOUND":
            raise
        return spark.createDataFrame([], schema)


def parse_props(events: DataFrame, schema: str = "k INT") -> DataFrame:
    """events with props as a struct; malformed JSON gives nulls."""
    return events.withColumn("props", F.from_json("props", schema))


def write_predictions(predictions: DataFrame, path: str, task: str, mode: str = "append") -> None:
    """Predictions as Parquet, in folders by task and route."""
    predictions.withColumn("task", F.lit(task)).write.mode(mode).partitionBy("task", "route").parquet(path)


def append_ledger(ledger: DataFrame, path: str, run: str | None = None) -> str:
    """Ledger rows under a run id, so that a run written twice can be told apart; returns the id."""
    run = run or uuid.uuid4().hex
    ledger.withColumn("run", F.lit(run)).write.mode("append").partitionBy("run").parquet(path)
    return run


class ResponseCache:
    """Answers by the hash of model and prompt, in a Parquet table: prompts asked before are looked up, the rest remain to be asked."""

    def __init__(self, spark: SparkSession, path: str, schema: str = "answer string"):
        self.spark, self.path, self.schema = spark, path, f"key string, {schema}"

    def _table(self) -> DataFrame:
        return read_or_empty(self.spark, self.path, self.schema)

    @staticmethod
    def keyed(prompts: DataFrame, model: str, prompt: str = "prompt") -> DataFrame:
        return prompts.withColumn("key", F.sha2(F.concat_ws("\0", F.lit(model), prompt), 256))

    def lookup(self, keyed: DataFrame) -> tuple[DataFrame, DataFrame]:
        """Prompts with their stored answers, and the distinct prompts without one."""
        known = self._table().dropDuplicates(["key"])
        return keyed.join(known, "key"), keyed.join(known, "key", "left_anti").dropDuplicates(["key"])

    def store(self, answers: DataFrame) -> None:
        answers.select("key", *[c for c in answers.columns if c != "key"]).write.mode("append").parquet(self.path)
