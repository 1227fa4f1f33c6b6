import itertools
import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from jointsem import catalog_noise
from jointsem.functions.hashing import portable_uniform, uniform
from jointsem.models.base import Metered, Pool, Records, Tier
from jointsem.models.simulated import Profile, SimulatedModel
from jointsem.operators import assignment, correlation, edges, ordering, sampling, stopping
from jointsem.operators.clustering import cluster_batch
from jointsem.operators.sampling import assign_batches, sample_batch
from jointsem.plans import cascade
from jointsem.plans.params import Params, default_batch_size


def meter(model):
    return Metered(Tier("strong", model, 1.0, 1.0))


def pool(labels, profile=None):
    profile = profile or Profile()
    return Pool(Tier("strong", SimulatedModel(labels, profile), 2.5, 10.0), Tier("light", SimulatedModel(labels, profile, tag="light"), 0.15, 0.6))


def truth_records(n, labels, seed=1):
    rng = random.Random(seed)
    return Records(list(range(n)), [f"text {i}" for i in range(n)], [rng.choice(labels) for _ in range(n)])


def test_edge_update_example():
    """A pair with 2 positive and 3 negative votes weighs 0.6; an answer that closes over it makes that 0.5."""
    votes = edges.Votes(5)
    votes.positive[1, 4] = votes.positive[4, 1] = 2
    votes.negative[1, 4] = votes.negative[4, 1] = 3
    assert votes.weights()[1, 4] == 0.6
    ids = np.array([1, 3, 4])
    pairs, bad = edges.answered_rows([(1, 3), (1, 4), (1, 1), (1, 9)], ids)
    assert bad == 2
    votes.add(ids, edges.positive_matrix(3, pairs))
    w = votes.weights()
    assert (w[1, 4], w[3, 4], w[0, 2]) == (0.5, 0, 0.5)
    plain = edges.Votes(5)
    plain.add(ids, edges.positive_matrix(3, pairs, transitive=False))
    assert plain.weights()[3, 4] == 1


def test_votes_count_samples_and_split_them():
    rng = np.random.default_rng(0)
    votes, seen = edges.Votes(30), np.zeros((30, 30), int)
    for _ in range(40):
        rows = np.sort(rng.choice(30, 10, replace=False))
        pairs = rng.integers(0, 10, (6, 2))
        same = edges.positive_matrix(10, pairs[pairs[:, 0] != pairs[:, 1]])
        assert np.array_equal(same, same.T) and not np.diag(same).any()
        again = edges.positive_matrix(10, np.argwhere(same))
        assert np.array_equal(same, again)
        votes.add(rows, same)
        seen[np.ix_(rows, rows)] += 1
    np.fill_diagonal(seen, 0)
    assert np.array_equal(votes.positive + votes.negative, seen)
    w = votes.weights()
    assert np.array_equal(w, w.T) and w.min() >= 0 and w.max() <= 1


def test_weights_from_truth():
    w = edges.weights_from_truth(["x", "x", "y", "y"])
    assert w[0, 1] == 0 and w[0, 2] == 1
    assert edges.zero_weight_components(w).tolist() == [0, 0, 2, 2]


def test_correlation_search():
    rng = np.random.default_rng(4)
    for _ in range(8):
        w = rng.random((7, 7))
        w = (w + w.T) / 2
        np.fill_diagonal(w, 0)
        ids = correlation.correlation_cluster(w, 3, np.arange(7), restarts=12)
        d = correlation.disagreement(w, ids, 3)
        assert np.all(d.min(axis=1) >= d[np.arange(7), ids] - 1e-9)
        plain = [sum((w[a, b] if ids[b] == j else 1 - w[a, b]) for b in range(7) if b != a) for a in range(7) for j in range(3)]
        assert d.ravel() == pytest.approx(plain)
        assert correlation.objective(w, ids, 3) <= correlation.exact_correlation(w, 3)[1] + 1.0
    truth = ["a", "b", "c", "a", "b", "c", "a"]
    assert correlation.objective(edges.weights_from_truth(truth), correlation.correlation_cluster(edges.weights_from_truth(truth), 3, np.arange(7)), 3) == 0


def test_stop_bound_covers_errors():
    """With independent noisy pairs, fewer records are misplaced on average than the bound says."""
    rng = np.random.default_rng(2)
    truth = np.repeat([0, 1], 15)
    p = np.where(truth[:, None] == truth[None, :], 0.3, 0.7)
    np.fill_diagonal(p, 0)
    wrong, r = 0, 3
    for _ in range(60):
        votes = rng.binomial(r, p) / r
        w = np.triu(votes, 1) + np.triu(votes, 1).T
        d = correlation.disagreement(w, truth, 2)
        wrong += (d[np.arange(30), truth] > d.min(axis=1)).sum()
    assert wrong / 60 <= stopping.uncertain_bound(correlation.disagreement(p, truth, 2), truth, r)
    assert stopping.uncertain_bound(np.zeros((4, 1)), np.zeros(4, int), 2) == 0
    assert stopping.should_stop(1.9, 10, 0.2) and not stopping.should_stop(2.0, 10, 0.2)


def test_matching_example_and_brute_force():
    p = np.array([[0.6, 0.4], [0.9, 0.1]])
    gain = 10 * np.log(p)
    assert gain.argmax(axis=1).tolist() == [0, 0]
    assert assignment.hungarian(gain).tolist() == [1, 0]
    rng = np.random.default_rng(1)
    for k in range(1, 7):
        for _ in range(5):
            g = rng.normal(size=(k, k)).round(2)
            got = assignment.hungarian(g)
            best = max(sum(g[i, s[i]] for i in range(k)) for s in itertools.permutations(range(k)))
            assert sorted(got) == list(range(k)) and g[np.arange(k), got].sum() == pytest.approx(best)


def test_order_examples_and_brute_force():
    w = np.array([[0, 0.9, 0.7], [0.1, 0, 0.8], [0.3, 0.2, 0]])
    assert ordering.order_clusters(w) == [0, 1, 2] and ordering.ordering_objective(w, [0, 1, 2]) == pytest.approx(0.6)
    cycle = np.array([[0, 0.9, 0.4], [0.1, 0, 0.9], [0.6, 0.1, 0]])
    assert ordering.order_clusters(cycle) == [0, 1, 2] and ordering.ordering_objective(cycle, [0, 1, 2]) == pytest.approx(0.8)
    rng = np.random.default_rng(3)
    for k in (1, 2, 4, 6):
        w = rng.random((k, k))
        best = min(ordering.ordering_objective(w, list(s)) for s in itertools.permutations(range(k)))
        assert ordering.ordering_objective(w, ordering.order_clusters(w)) == pytest.approx(best)
    big = rng.random((18, 18))
    assert sorted(ordering.order_clusters(big)) == list(range(18))
    logs = np.log(np.array([[0.1, 0.8, 0.1], [0.1, 0.1, 0.8]]))
    assert ordering.to_scores([0, 1], logs, 3) == {0: 2, 1: 3} and ordering.to_scores([2, 0, 1], None, 3) == {2: 1, 0: 2, 1: 3}


@pytest.mark.parametrize("mode", ["pairs", "cluster_labels", "pairwise", "pairwise_context"])
def test_clustering_without_noise_is_exact(mode):
    labels = ["a", "b", "c"]
    records = truth_records(40, labels)
    m = meter(SimulatedModel(labels))
    found = cluster_batch(records, "", 3, m, Params(sample=15, stop_share=1e-4, edge_mode=mode, max_rounds=100))
    assert len({(c, h) for c, h in zip(found.ids, records.hidden, strict=True)}) == 3
    assert m.usage.calls == (40 * 39 // 2 if mode.startswith("pairwise") else found.rounds)


def test_clustering_edge_cases():
    m = meter(SimulatedModel(["a", "b"]))
    assert cluster_batch(Records([], [], []), "", 2, m, Params()).ids.tolist() == []
    assert cluster_batch(truth_records(1, ["a"]), "", 2, m, Params()).ids.tolist() == [0]
    assert cluster_batch(truth_records(5, ["a", "b"]), "", 1, m, Params()).ids.tolist() == [0] * 5
    few = cluster_batch(truth_records(3, ["a", "b"]), "", 7, m, Params(max_rounds=30))
    assert set(few.ids) <= set(range(7)) and few.rounds <= 30
    assert default_batch_size(4) == 200 and default_batch_size(38) == 380


def test_noise_costs_accuracy_and_rounds():
    labels, records = ["a", "b", "c", "d"], truth_records(200, ["a", "b", "c", "d"], 3)
    rounds = [cluster_batch(records, "", 4, meter(SimulatedModel(labels, Profile(group=e, reach=3))), Params()).rounds for e in (0.0, 0.25)]
    assert rounds[0] < rounds[1]


def test_portable_uniform(spark):
    df = spark.range(50).select("id", portable_uniform("s", 3, F.col("id")).alias("u"))
    assert [r.u for r in df.orderBy("id").collect()] == [uniform("s", 3, i) for i in range(50)]


def test_batches_do_not_depend_on_partitions(spark):
    ids = spark.range(1013)
    one = {r.id: r.batch_id for r in assign_batches(ids.repartition(1), 100, "x").collect()}
    many = {r.id: r.batch_id for r in assign_batches(ids.repartition(13), 100, "x", bucket_rows=90).collect()}
    assert one == many
    sizes = np.bincount(list(one.values()))
    assert len(sizes) == 11 and sizes.max() - sizes.min() <= 1
    a = sorted(r.id for r in sample_batch(ids.repartition(7), 20, "x").collect())
    b = sorted(r.id for r in sample_batch(ids.repartition(1), 20, "x", n=1013 * 10).collect())
    assert a == b and len(a) == 20
    assert assign_batches(spark.range(0), 100, "x").collect() == []


def brute_threshold(scores, allowed):
    return max(v for v in {*scores, 1.0} if sum(s < v for s in scores) <= allowed)


def test_threshold_examples(spark):
    def tau(scores, batch, c0, cp, budget):
        return cascade.choose_threshold(spark.createDataFrame([(float(s),) for s in scores], "confidence double"), batch, c0, cp, budget)

    assert tau([0.1, 0.2, 0.3, 0.4, 0.5], 2, 1, 1, 3) == 0.3
    assert cascade.cost_of_threshold(2, 2, 1, 1) == 3
    assert tau([0.5] * 5, 2, 1, 1, 2.5) == 0.5
    assert tau([0.5], 2, 1, 1, 0.5) is None and tau([0.5], 2, 0, 1, 0.5) == 1.0
    rng = random.Random(1)
    for _ in range(6):
        scores = [rng.choice([rng.random(), 0.25, 1.0, 0.0, 0.25 + 1e-12]) for _ in range(60)]
        for allowed in (0, 3, 17, 40, 60):
            assert tau(scores, 1, 1, 0, allowed + 1) == brute_threshold(scores, allowed)


def test_routes():
    assert cascade.full_joint_feasible(1, 10, 5, 2) and not cascade.full_joint_feasible(1, 11, 5, 2)
    assert (cascade.choose_proxy(1, 5, 4), cascade.choose_proxy(1, 5, 6)) == ("light", "strong")
    assert math.isinf(cascade.allowed_joint(5, 0, 1, 2))


def test_labels_of_samples_are_those_of_their_components(spark):
    """Random pairs, some of them repeated, turned round or with strangers; a sample without pairs keeps its ids."""
    rng = np.random.default_rng(3)
    samples, pairs, want = [], [], set()
    for batch, number in itertools.product(range(4), range(5)):
        ids = rng.choice(1000, 12, replace=False)
        asked = rng.integers(0, 12, (0 if number == 4 else 4 + 2 * number, 2))
        samples += [(batch, number, int(i)) for i in ids]
        pairs += [(batch, number, int(ids[a]), int(ids[b])) for a, b in asked] + [(batch, number, int(ids[0]), 5000), (batch, number, 5000, int(ids[1]))] * (number < 4)
        label = edges.components(12, asked)
        want |= {(batch, number, int(ids[r]), int(ids[label == label[r]].min())) for r in range(12)}
    got = edges.closed_labels_df(spark.createDataFrame(samples, "batch_id long, round int, id long"), spark.createDataFrame(pairs, "batch_id long, round int, a long, b long"))
    assert sorted(map(tuple, got.collect())) == sorted(want)


def test_batches_are_spread_by_their_number(spark):
    """A batch is bytes only, but many questions: hundreds of them are never one task's work."""
    from jointsem.operators.sampling import batch_tasks

    found = assign_batches(spark.range(4000), 10, "t")
    assert found.groupBy("batch_id").count().where("count <> 10").count() == 0
    assert found.rdd.getNumPartitions() == batch_tasks(400, 4) == 50
    assert batch_tasks(1, 200) == 1 and batch_tasks(0, 8) == 1 and batch_tasks(10**9, 200) == 100_000


def test_starts_settle_together_as_alone():
    rng = np.random.default_rng(9)
    for n, k in ((8, 2), (30, 4), (5, 5)):
        w = np.triu(rng.integers(0, 7, (n, n)) / 6, 1)
        w += w.T
        gain = 2 * w - 1
        np.fill_diagonal(gain, 0)
        first = rng.integers(0, k, (25, n))
        order = np.array([rng.permutation(n) for _ in first])
        alone = [correlation._settle(gain, f, k, o, 50).tolist() for f, o in zip(first, order, strict=True)]
        assert correlation._settle_all(gain, first, k, order, 50).tolist() == alone


def test_tiny_batches_share_tasks():
    """150,000 batches of eight records were 18,750 tasks, which cost more to start than to run; batches of 200 are spread as before."""
    assert sampling.batch_tasks(150_000, 16, 8) == 750
    assert sampling.batch_tasks(150_000, 16, 200) == sampling.batch_tasks(150_000, 16) == 18_750
    assert sampling.batch_tasks(150_000, 16, 5_000) == 18_750 and sampling.batch_tasks(3, 16, 8) == 3


def test_votes_alone_are_those_of_clustering():
    """What noisy_* compare by is asked without the search, and judged as the search judges it."""
    for batch in range(6):
        ids = list(range(batch * 50, batch * 50 + 8 - batch % 3))
        records = Records(ids, ["t"] * len(ids), [catalog_noise.KINDS[i * 7 % 3 % 2] for i in ids])
        found = cluster_batch(records, "", 2, Metered(catalog_noise._pool().strong), catalog_noise.SMALL, batch)
        w = catalog_noise._voted(records, batch)
        assert np.array_equal(w, found.weights)
        values = [correlation.objective(w, g, 2) for g in catalog_noise._groupings(len(ids))]
        assert np.allclose(catalog_noise._objectives(w), values) and min(values) == pytest.approx(correlation.objective(w, found.ids, 2))
