import os
import shutil

from pyspark.sql import functions as F

from jointsem.models.base import Pool, Tier
from jointsem.models.simulated import Profile, SimulatedModel
from jointsem.plans.params import Params
from jointsem.streaming.streams import JointSink, deduplicated, run_available, stream_row_by_row, stream_table, windowed_counts, with_customers, with_lateness

LABELS = ["a", "b"]


def split_events(spark, tmp_path, parts=3):
    folder = f"{tmp_path}/in"
    events = spark.read.parquet("/root/testdata/sf0.001/events.parquet")
    os.makedirs(folder)
    for p in range(parts):
        events.where(F.col("event_id") % parts == p).coalesce(1).write.parquet(f"{tmp_path}/w{p}")
        name = next(f for f in os.listdir(f"{tmp_path}/w{p}") if f.endswith(".parquet"))
        shutil.move(f"{tmp_path}/w{p}/{name}", f"{folder}/events_{p}.parquet")
    return folder, events


def test_windows_equal_the_batch_result(spark, tmp_path):
    folder, events = split_events(spark, tmp_path)
    schema = events.schema
    rows = spark.readStream.schema(schema).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))
    counts = windowed_counts(with_lateness(rows, "ts", "100 days"), "ts", "event_type", "1 day")
    q = counts.writeStream.outputMode("complete").format("memory").queryName("w").trigger(availableNow=True).start()
    q.awaitTermination()
    want = events.groupBy(F.window(F.col("ts").cast("timestamp"), "1 day").alias("w"), "event_type").count()
    assert spark.table("w").agg(F.sum("n")).first()[0] == events.count() and spark.table("w").count() == want.count()


def test_source_deduplication_and_static_join(spark, tmp_path):
    rows = with_lateness(stream_table(spark, "/root/testdata/sf0.001", "events"), "ts", "1000 days")
    customers = spark.read.parquet("/root/testdata/sf0.001/customer.parquet").select("c_custkey", "c_name")
    q = with_customers(deduplicated(rows, "event_id"), customers).writeStream.format("memory").queryName("d").trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.table("d").count() == spark.read.parquet("/root/testdata/sf0.001/events.parquet").count()


def test_joint_sink(spark, tmp_path):
    folder = f"{tmp_path}/in"
    for p in range(3):
        part = spark.range(p * 40, p * 40 + 40).selectExpr("id", "concat('text ', id) as text", "if(id % 2 = 0, 'a', 'b') as hidden")
        part.coalesce(1).write.mode("append").parquet(folder)
    strong, light = SimulatedModel(LABELS), SimulatedModel(LABELS, Profile(row=0.5), tag="light")
    pool = Pool(Tier("strong", strong, 1, 1), Tier("light", light, 1, 1))
    sink = JointSink(f"{tmp_path}/out", "?", LABELS, pool, 0.8, Params(batch=30, sample=20, stop_share=1e-4))
    stream = spark.readStream.schema("id long, text string, hidden string").option("maxFilesPerTrigger", 1).parquet(folder)
    run_available(stream, sink, f"{tmp_path}/checkpoint")
    before = sink.predictions(spark).count()
    assert 0 < before <= 120
    sink(spark.read.parquet(folder).where("id < 40"), 0)
    assert sink.predictions(spark).select("id").distinct().count() == sink.predictions(spark).count()
    sink.flush(spark)
    spent = sink.spent(spark)
    sink.flush(spark)
    sink(spark.read.parquet(folder).where("false"), 3)
    assert sink.spent(spark) == spent
    found = {r.id: r for r in sink.predictions(spark).collect()}
    assert len(found) == 120 and sink.pending(spark).count() == 0 and sink.spent(spark) > 0
    assert all(r.pred == LABELS[i % 2] for i, r in found.items() if r.route == "joint")


def test_row_wise_stage_on_a_stream(spark, tmp_path):
    spark.range(10).selectExpr("id", "'t' as text", "'a' as hidden").write.parquet(f"{tmp_path}/in")
    model = SimulatedModel(LABELS)
    stream = spark.readStream.schema("id long, text string, hidden string").parquet(f"{tmp_path}/in")
    q = stream_row_by_row(stream, "?", LABELS, Pool(Tier("strong", model, 1, 1), Tier("light", model, 1, 1))).writeStream.format("memory").queryName("r").trigger(availableNow=True).start()
    q.awaitTermination()
    assert {r.pred for r in spark.table("r").collect()} == {"a"}
