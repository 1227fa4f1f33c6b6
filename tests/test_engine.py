import math
import random
import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from jointsem.models.base import Pool, Records, Tier
from jointsem.models.endpoint import CallableModel, CallFailed
from jointsem.models.lexical import LexicalModel
from jointsem.models.simulated import Profile, SimulatedModel
from jointsem.operators.sampling import assign_batches
from jointsem.plans import baselines, cascade, tasks
from jointsem.plans.params import Params
from jointsem.sources.tables import ResponseCache, read_or_empty
from jointsem.streaming.streams import JointSink, late_truth

LABELS = ["red", "green", "blue"]
SURE = Params(batch=40, sample=20, stop_share=1e-4)


def pool(profile=None):
    return Pool(*(Tier(n, SimulatedModel(LABELS, profile or Profile()), 1.0, 1.0) for n in ("strong", "light")))


@pytest.fixture(scope="module")
def data(spark):
    return spark.createDataFrame([(i, f"item {i} is {LABELS[i % 3]}", LABELS[i % 3]) for i in range(120)], "id long, text string, truth string")


@pytest.mark.parametrize("ids", [[1, 1, 2], [1, None, 2]])
def test_ids_must_be_unique(spark, ids):
    rows = spark.createDataFrame([(i, "x red") for i in ids], "id long, text string")
    with pytest.raises(ValueError, match="unique"):
        tasks.classify(rows, "id", ["text"], "?", LABELS, pool())


def test_clusters_of_the_sample_are_found_once(data):
    found = {how: tasks.cluster(data, "id", ["text"], "?", 3, pool(), params=SURE.but(cluster_names=how), hidden="truth") for how in ("identity", "matching")}
    calls = {how: {r[0]: r[2] for r in f.ledger_rows} for how, f in found.items()}
    assert calls["matching"]["sample names"] == 3 and calls["matching"]["sample"] == calls["identity"]["sample"]


def test_batches_beyond_a_long(data):
    whole = {r.id: r.batch_id for r in assign_batches(data, 40, "s").collect()}
    huge = [r.batch_id for r in assign_batches(data, 40, "s", n=10**13, bucket_rows=10**13).collect()]
    assert set(huge) == {0, 1, 2} and sorted(set(whole.values())) == [0, 1, 2]
    many = {r.id: r.batch_id for r in assign_batches(data, 1, "s", n=6 * 10**18, bucket_rows=10**19).collect()}
    assert sorted(many.values()) == list(range(120))


def test_target_threshold_admits_its_default():
    confidence = np.linspace(0, 1, 200)
    assert baselines.target_threshold(confidence, np.ones(200, bool), 0.9) == 0.0
    agree = np.ones(200, bool)
    agree[100:106] = False  # 97 % agreement
    assert baselines.target_threshold(confidence, agree, 0.9) == 0.0
    agree[60:130] = False
    tau = baselines.target_threshold(confidence, agree, 0.9)
    allowed = baselines.most_losses(200, 0.9)
    assert 0 < tau <= 1 and ((confidence >= tau) & ~agree).sum() <= allowed < ((confidence >= tau - 0.006) & ~agree).sum() + 1
    assert baselines.target_threshold(confidence, agree, 1.0) > 1 and baselines.most_losses(200, 0.9) == max(k for k in range(200) if sum(math.comb(200, i) * 0.1**i * 0.9 ** (200 - i) for i in range(k + 1)) <= 0.1)


def test_conditions(spark, data):
    rows = data.withColumn("hidden", F.when(F.col("truth") == "red", "yes").otherwise("no"))
    model = SimulatedModel(["yes", "no"])
    both = Pool(Tier("strong", model, 1, 1), Tier("light", model, 1, 1))
    ask = lambda c: sorted(r.id for r in tasks.semantic_where(rows, "id", ["text"], c, both, params=SURE, hidden="hidden")[0].select("id").collect())
    red, rest = list(range(0, 120, 3)), [i for i in range(120) if i % 3]
    assert ask(("not", "red?")) == rest and ask(("and", "red?", "red too?")) == red and ask(("or", "red?", ("not", "red?"))) == list(range(120))
    kept, results = tasks.semantic_filter_all(rows, "id", ["text"], ["red?", "red too?"], both, probe=30, params=SURE, hidden="hidden")
    assert sorted(r.id for r in kept.collect()) == red and len(results) == 4


def test_split_runs_lose_no_pair(spark):
    left = spark.createDataFrame([(i, f"common words here again number {i}") for i in range(30)], "id long, text string")
    right = spark.createDataFrame([(100 + i, f"{i} common words here again") for i in range(20)], "id long, text string")
    pairs = {tuple(r) for r in tasks.candidate_pairs(left, right, 4, split=10).collect()}
    assert pairs == {(i, 100 + j) for i in range(30) for j in range(20)}
    truth = spark.createDataFrame([(1, 101), (1, 999)], "left_id long, right_id long")
    assert tuple(tasks.blocking_recall(tasks.candidate_pairs(left, right, 4), truth).first()) == (2, 1, 600, 0.5)


def test_endpoint_retries_and_reads_replies():
    calls = []

    def flaky(prompt):
        calls.append(prompt)
        if len(calls) < 3:
            raise OSError("busy")
        return "The answer is Green.", -0.1

    model = CallableModel(flaky, backoff_s=0)
    assert model.classify("?", LABELS, Records([1], ["x"])) == ("green", -0.1) and len(calls) == 3
    with pytest.raises(CallFailed):
        CallableModel(lambda p: time.sleep(1), max_retries=0, timeout_s=0.05).classify("?", LABELS, Records([1], ["x"]))
    said = lambda text: CallableModel(lambda p: text)
    three = Records([4, 5, 6], ["a", "b", "c"])
    assert said("4-5\n[5] - 6").group_pairs("?", three)[0] == (4, 5) and said("4, 5").group_clusters("?", three) == [[4, 5], [6]]
    assert said("4: red\n5: blue").classify_many("?", LABELS, three) == ["red", "blue", "red"]
    assert said("yes").same("?", three.take([0]), three.take([1])) and said("A").compare("?", three.take([0]), three.take([1]))
    logs = said("blue").score_labels("?", LABELS, three)
    assert sum(map(math.exp, logs)) == pytest.approx(1) and max(logs) == logs[2]
    assert said("size: 3\nkind: bolt").extract("?", {"kind": "what it is", "price": ""}, three) == {"kind": "bolt", "price": ""}
    assert said("- one\n- two\n").propose_labels("?", three) == ["one", "two"]


def test_answers_are_paid_once(spark, data, tmp_path):
    tier = Tier("light", LexicalModel({n: n for n in LABELS}), 1, 1)
    cache = ResponseCache(spark, f"{tmp_path}/answers", "pred string, confidence double")
    rows = data.select("id", "text")
    first = cascade.row_wise(rows, "?", LABELS, tier, cache=cache)
    again = cascade.row_wise(rows, "?", LABELS, tier, cache=cache)
    plain = {r.id: r.pred for r in cascade.row_wise(rows, "?", LABELS, tier).collect()}
    assert {r.id: r.pred for r in first.collect()} == {r.id: r.pred for r in again.collect()} == plain
    assert first.agg(F.sum("tokens_in")).first()[0] > 0 == again.agg(F.sum("tokens_in")).first()[0]


def test_cached_answers_whichever_copy_is_asked(spark, tmp_path, monkeypatch):
    """Of equal texts any may be the one that is asked, and another each time the plan runs, as when shuffled blocks arrive in another order."""
    draw = F.udf(lambda i: random.random(), "double").asNondeterministic()

    def any_copy(cache, keyed):
        known = cache._table().dropDuplicates(["key"])
        open_ = keyed.join(known, "key", "left_anti").withColumn("u", draw("id")).groupBy("key").agg(F.min_by("id", "u").alias("id"), F.min_by("text", "u").alias("text"))
        return keyed.join(known, "key"), open_

    monkeypatch.setattr(ResponseCache, "lookup", any_copy)
    rows = spark.createDataFrame([(i, f"item {i % 20} is {LABELS[i % 20 % 3]}") for i in range(400)], "id long, text string")
    cache = ResponseCache(spark, f"{tmp_path}/answers", "pred string, confidence double")
    found = cascade.row_wise(rows, "?", LABELS, Tier("light", LexicalModel({n: n for n in LABELS}), 1, 1), cache=cache).collect()
    assert sorted(r.id for r in found) == list(range(400)) and sum(r.tokens_in > 0 for r in found) == 20
    assert all(r.pred == LABELS[r.id % 20 % 3] for r in found)


@pytest.mark.parametrize("proxy", ["rows", "ladder", "batch", "rubric"])
def test_proxies(data, proxy):
    found = tasks.classify(data, "id", ["text"], "?", LABELS, pool(Profile(row=0.2)), params=SURE.but(proxy=proxy), hidden="truth", force_route="proxy")
    rows = found.predictions.collect()
    assert len({r.id for r in rows}) == 120 and found.report["c_proxy"] > 0 and {r.route for r in rows} == {"sample", "proxy"}


def test_only_a_missing_table_reads_as_empty(spark, tmp_path):
    assert read_or_empty(spark, f"{tmp_path}/none", "a long").collect() == []
    (tmp_path / "bad").mkdir()
    (tmp_path / "bad" / "x.parquet").write_text("no parquet")
    with pytest.raises(Exception):
        read_or_empty(spark, f"{tmp_path}/bad", "a long").collect()


def test_an_epoch_delivered_again_changes_nothing(spark, data, tmp_path):
    sink = JointSink(str(tmp_path), "?", LABELS, pool(Profile(row=0.3)), 0.9, SURE)
    rows = data.select("id", "text", F.col("truth").alias("hidden"))
    for epoch in (0, 1, 1):
        sink(rows.where(f"id % 2 = {epoch}"), epoch)
    sink.flush(spark)
    sink.flush(spark)
    ids = [r.id for r in sink.predictions(spark).collect()]
    assert sorted(ids) == list(range(120)) and sink.pending(spark).count() == 0


def test_late_truth(spark):
    predictions = spark.createDataFrame([(1, "a", "2024-01-01 00:00:00"), (2, "b", "2024-01-01 00:00:00")], "id long, pred string, ts string").withColumn("ts", F.col("ts").cast("timestamp"))
    truth = spark.createDataFrame([(1, "a", "2024-01-01 01:00:00"), (2, "b", "2024-01-01 05:00:00")], "id long, truth string, seen string").withColumn("seen", F.col("seen").cast("timestamp"))
    assert [(r.id, r.pred, r.truth) for r in late_truth(predictions, truth).collect()] == [(1, "a", "a")]
