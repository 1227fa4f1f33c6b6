import math

import pytest
from pyspark.sql import functions as F

from jointsem.functions import measures
from jointsem.functions.expressions import lexical_scores, page_text, register, render, require_unique_id, stable_id
from jointsem.models.base import Pool, Tier
from jointsem.models.lexical import LexicalModel
from jointsem.models.simulated import Profile, SimulatedModel
from jointsem.plans import baselines, tasks
from jointsem.plans.params import Params
from jointsem.sources.tables import ResponseCache, append_ledger, write_predictions

LABELS = ["red", "green", "blue"]
SURE = Params(batch=40, sample=20, stop_share=1e-4)


def pool(profile=None, light=None):
    return Pool(Tier("strong", SimulatedModel(LABELS, profile or Profile()), 2.5, 10.0), Tier("light", SimulatedModel(LABELS, light or profile or Profile(), tag="light"), 0.15, 0.6))


@pytest.fixture(scope="module")
def data(spark):
    rows = [(i, f"item {i} is {LABELS[i % 3]}", LABELS[i % 3]) for i in range(150)]
    return spark.createDataFrame(rows, "id long, text string, truth string")


def predicted(found):
    rows = found.predictions.collect()
    assert len(rows) == len({r.id for r in rows})
    return {r.id: r.pred for r in rows}


def test_classify_without_noise_returns_the_truth(data):
    for options in ({}, {"budget": 0.004}, {"force_route": "joint"}, {"force_route": "proxy"}):
        found = tasks.classify(data, "id", ["text"], "What colour?", LABELS, pool(), params=SURE, hidden="truth", **options)
        assert predicted(found) == {r.id: r.truth for r in data.collect()}
        assert found.report["cost"] == pytest.approx(found.cost)


def test_routes_and_budget(data):
    noisy = Profile(row=0.3, group=0.05, reach=3)
    whole = tasks.classify(data, "id", ["text"], "What colour?", LABELS, pool(noisy), params=SURE, hidden="truth")
    assert {r.route for r in whole.predictions.collect()} == {"sample", "joint"} and not any(r[0] == "proxy" for r in whole.ledger_rows)
    last = 0.0
    for share in (0.3, 0.5, 0.7, 0.9):
        found = tasks.classify(data, "id", ["text"], "What colour?", LABELS, pool(noisy), params=SURE, hidden="truth", budget=share * whole.cost)
        assert len(predicted(found)) == 150
        if found.report["proxy"] and not found.report["budget_exceeded"]:
            assert found.report["tau"] >= last or found.report["proxy"] == "strong"
            assert found.report["planned_cost"] <= share * whole.cost + 1e-12
            last = found.report["tau"]
    poor = tasks.classify(data, "id", ["text"], "What colour?", LABELS, pool(noisy), params=SURE, hidden="truth", budget=0.0)
    assert poor.report["budget_exceeded"] and {r.route for r in poor.predictions.collect()} == {"sample", "proxy"}
    with pytest.raises(ValueError):
        tasks.classify(data, "id", ["text"], "What colour?", LABELS, pool(noisy), params=SURE.but(on_infeasible="error"), hidden="truth", budget=0.0)


def test_results_do_not_depend_on_partitions(data):
    one, many = (predicted(tasks.classify(data.repartition(n), "id", ["text"], "?", LABELS, pool(Profile(group=0.2, reach=3)), params=SURE, hidden="truth")) for n in (1, 9))
    assert one == many


def test_truth_is_never_read_by_a_lexical_model(data):
    lexical = LexicalModel({n: n for n in LABELS})
    p = Pool(Tier("strong", lexical, 1, 1), Tier("light", lexical, 1, 1))
    found = tasks.classify(data.withColumn("truth", F.lit("x")), "id", ["text"], "?", LABELS, p, params=SURE, hidden="truth")
    assert predicted(found) == {r.id: r.truth for r in data.collect()}


def test_score_cluster_filter_join(data, spark):
    found = tasks.score(data, "id", ["text"], "How green?", 3, pool(), descriptions=LABELS, params=SURE, hidden="truth")
    assert predicted(found) == {r.id: r.truth for r in data.collect()}
    found = tasks.cluster(data, "id", ["text"], "By colour.", 3, pool(), params=SURE, hidden="truth")
    assert measures.clustering_accuracy(found.predictions, data).first()[0] == 1.0
    yes = data.withColumn("hidden", F.when(F.col("truth") == "red", "yes").otherwise("no"))
    model = SimulatedModel(["yes", "no"])
    both = Pool(Tier("strong", model, 1, 1), Tier("light", model, 1, 1))
    kept, _ = tasks.semantic_filter(yes, "id", ["text"], "Is it red?", both, params=SURE, hidden="hidden")
    assert sorted(r.id for r in kept.collect()) == list(range(0, 150, 3))
    left = spark.createDataFrame([(1, "one two three four five"), (2, "six seven eight nine ten")], "id long, text string")
    right = spark.createDataFrame([(7, "zero two three four end"), (8, "nothing shared at all here")], "id long, text string")
    assert [tuple(r) for r in tasks.candidate_pairs(left, right, 3).collect()] == [(1, 7)]
    with pytest.raises(ValueError):
        tasks.semantic_join(left, right, "?", both, block=None, cross_limit=2)


def test_small_and_empty_inputs(data, spark):
    for n in (0, 1, 2):
        found = tasks.classify(data.where(f"id < {n}"), "id", ["text"], "?", LABELS, pool(), params=SURE.but(max_rounds=20), hidden="truth")
        assert len(predicted(found)) == n
    nulls = spark.createDataFrame([(1, None, "red"), (2, "", "red")], "id long, text string, truth string")
    assert len(predicted(tasks.classify(nulls, "id", ["text"], "?", ["red"], pool(), params=SURE, hidden="truth"))) == 2


def test_baselines(data):
    records = data.withColumnRenamed("truth", "hidden")
    truth = {r.id: r.truth for r in data.collect()}
    for found in (
        baselines.row_by_row(records, "?", LABELS, pool()),
        baselines.batch_prompt(records, "?", LABELS, pool(), size=20),
        baselines.rubric_then_rows(records, "?", LABELS, pool()),
        baselines.plain_cascade(records, "?", LABELS, pool(), 0.8),
        baselines.target_cascade(records, "?", LABELS, pool(light=Profile(row=0.4)), 0.95, sample=50),
        baselines.label_then_assign(records, "?", 3, pool(), size=25),
    ):
        assert predicted(found) == truth
        assert found.cost > 0
    assert baselines.batch_prompt(records, "?", LABELS, pool(), size=20).ledger_rows[0][2] == 8
    for found in (baselines.embedding_kmeans(records, 3), baselines.keyphrase_kmeans(records, "?", 3, pool()), baselines.semantic_group_by(records, "?", 3, pool(), sample=30)):
        assert len(predicted(found)) == 150
    assert measures.clustering_accuracy(baselines.keyphrase_kmeans(records, "?", 3, pool()).predictions, data).first()[0] > 0.6
    assert len(predicted(baselines.direct_cluster(records, "?", pool(), 30))) == 30


def test_measures(spark):
    truth = spark.createDataFrame([(1, 1), (2, 2), (3, 2)], "id long, truth int")
    pred = spark.createDataFrame([(1, 1), (2, 2), (3, 3)], "id long, pred int")
    assert measures.accuracy(pred, truth).first()[0] == pytest.approx(2 / 3)
    assert measures.pairwise_accuracy(pred, truth).first()[0] == pytest.approx(2 / 3)
    assert measures.accuracy(pred.where("id < 3"), truth).first()[0] == pytest.approx(2 / 3)
    t = spark.createDataFrame([(1, "a"), (2, "a"), (3, "b"), (4, "b"), (5, "c")], "id long, truth string")
    c = spark.createDataFrame([(1, "x"), (2, "x"), (3, "x"), (4, "y"), (5, "y")], "id long, pred string")
    assert measures.clustering_accuracy(c, t).first()[0] == pytest.approx(0.6)
    report = spark.createDataFrame([("w", "a", 1.0, 0.5), ("w", "b", 2.0, 0.4), ("w", "c", 3.0, 0.9)], "workload string, method string, cost_per_1000 double, accuracy double")
    assert sorted(r.method for r in measures.frontier(report).collect()) == ["a", "c"]
    assert measures.cost_bound(100, 5, 10, 2, 3, 0.5, 1.0, 2.0, 0.1) == pytest.approx(100 * (0.1 + 1.5 + 1.0) + 50 * (0.1 + 2.0))


def test_expressions_and_sinks(spark, tmp_path):
    df = spark.createDataFrame([(1, "a ``` b", "<p>x&amp;y<script>z</script></p>")], "id long, text string, html string")
    r = df.select(render("Q {text} A", {"text": F.col("text")}).alias("p"), page_text(F.col("html")).alias("t"), lexical_scores(F.col("text"), {"k": "a", "m": "q"}).alias("s")).first()
    assert (r.p, r.t, r.s) == ("Q a '' b A", "x&y", {"k": 1, "m": 0})
    with pytest.raises(ValueError):
        require_unique_id(df.unionByName(df))
    assert stable_id(df.unionByName(df), "text").select("id").distinct().count() == 2
    register(spark)
    assert spark.sql("SELECT token_count('abcde') AS t, portable_uniform('a|1') AS u").first().t == 2
    preds = spark.createDataFrame([(1, "x", "joint")], "id long, pred string, route string")
    write_predictions(preds, f"{tmp_path}/p", "classify")
    assert spark.read.parquet(f"{tmp_path}/p").where("route = 'joint'").count() == 1
    ledger = spark.createDataFrame([("s", 1.0)], "stage string, cost double")
    append_ledger(ledger, f"{tmp_path}/l", "r1")
    append_ledger(ledger, f"{tmp_path}/l")
    assert spark.read.parquet(f"{tmp_path}/l").select("run").distinct().count() == 2
    cache = ResponseCache(spark, f"{tmp_path}/c")
    prompts = cache.keyed(spark.createDataFrame([("p1",), ("p2",), ("p2",)], "prompt string"), "m")
    known, open_ = cache.lookup(prompts)
    assert (known.count(), open_.count()) == (0, 2)
    cache.store(open_.where("prompt = 'p2'").select("key", F.lit("yes").alias("answer")))
    known, open_ = cache.lookup(prompts)
    assert (known.count(), open_.count()) == (2, 1)


def test_explain_cost():
    assert list(tasks.explain_cost(1000, 4, 1.0, 3.0, math.inf))[1] == "all joint"
    assert list(tasks.explain_cost(1000, 4, 1.0, 3.0, 2.0))[1] == "cascade, light proxy"
