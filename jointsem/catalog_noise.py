"""Queries in which the model errs, with SQL that repeats its draws, finds the optimum by trying all groupings, and goes on from there.

Parts are of kind x or y by their noun, in batches of eight, so a batch has 128
groupings into two.  Batches whose best grouping is not unique are left to the
objective alone.
"""

from __future__ import annotations

import functools
import itertools

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from jointsem.catalog import LANGUAGES, _batch, query, simulated_pool
from jointsem.functions.hashing import uniform_sql as u
from jointsem.models.base import Metered, Records, Tier
from jointsem.models.simulated import Profile, SimulatedModel
from jointsem.operators import assignment, clustering, correlation, edges, ordering, stopping
from jointsem.operators.clustering import cluster_batch
from jointsem.operators.sampling import assign_batches, sample_batch
from jointsem.plans import joint, tasks
from jointsem.plans.params import Params
from jointsem.sources.stages import stage
from jointsem.sources.tables import read_table
from jointsem.workloads import workload

KINDS = ["x", "y"]
FIRST = ["anvil", "bolt", "gear", "gizmo"]
ERRING = Profile(group=0.12, drop=0.1, label=0.8, compare=0.25)
SMALL = Params(batch=8, sample=6, max_rounds=6, stop_share=0.0, restarts=40)

_KEY = "concat_ws('|', batch_id, round)"
_FLIP = "CASE truth WHEN 'x' THEN 'y' ELSE 'x' END"
_NOISY = f"""WITH q AS (SELECT p_partkey AS id, CASE WHEN split_part(p_name, ' ', 2) IN ({", ".join(f"'{n}'" for n in FIRST)}) THEN 'x' ELSE 'y' END AS truth,
  row_number() OVER (ORDER BY {u("'joint'", "p_partkey")}, p_partkey) AS n, count(*) OVER () AS c FROM part),
r AS (SELECT CASE WHEN n <= 8 THEN -1 ELSE CAST(floor((n - 9) * ceil((c - 8) / 8.0) / (c - 8)) AS BIGINT) END AS batch_id, id, truth FROM q),
s AS (SELECT batch_id, round, id, truth FROM (SELECT *, row_number() OVER (PARTITION BY batch_id, round ORDER BY {u("'joint'", "batch_id", "round", "id")}, id) AS p
  FROM r, (SELECT CAST(unnest(range(1, 7)) AS INT) AS round)) WHERE p <= 6),
seen AS (SELECT *, CASE WHEN {u("'sim'", "'group'", _KEY, "id")} < {ERRING.group} THEN {_FLIP} ELSE truth END AS k FROM s),
chain AS (SELECT *, lag(id) OVER (PARTITION BY batch_id, round, k ORDER BY id) AS a FROM seen),
linked AS (SELECT *, a IS NOT NULL AND {u("'sim'", "'drop'", _KEY, "a", "id")} >= {ERRING.drop} AS hit FROM chain),
seg AS (SELECT *, sum(CASE WHEN hit THEN 0 ELSE 1 END) OVER (PARTITION BY batch_id, round, k ORDER BY id) AS g FROM linked),
votes AS (SELECT x.batch_id, x.id AS a, y.id AS b, sum(CAST(x.k = y.k AND x.g = y.g AS INT)) AS pos, count(*) AS n FROM seg x JOIN seg y ON x.batch_id = y.batch_id AND x.round = y.round AND x.id < y.id GROUP BY ALL),
i AS (SELECT batch_id, id, truth, row_number() OVER (PARTITION BY batch_id ORDER BY id) - 1 AS k, count(*) OVER (PARTITION BY batch_id) AS size FROM r),
w AS (SELECT x.batch_id, x.size, x.k AS a, y.k AS b, coalesce((n - pos) / n, 0.5) AS weight FROM i x JOIN i y ON x.batch_id = y.batch_id AND x.k < y.k LEFT JOIN votes v ON v.batch_id = x.batch_id AND v.a = x.id AND v.b = y.id),
o AS (SELECT batch_id, m, 2 * sum(CASE WHEN ((2 * m) >> a) & 1 = ((2 * m) >> b) & 1 THEN weight ELSE 1 - weight END) AS objective FROM w, (SELECT unnest(range(0, 128)) AS m) WHERE m < (1 << (size - 1)) GROUP BY ALL),
f AS (SELECT batch_id, min(m) AS m, count(*) AS ties, min(objective) AS objective FROM (SELECT *, min(objective) OVER (PARTITION BY batch_id) AS least FROM o) WHERE objective < least + 1e-9 GROUP BY ALL),
cl AS (SELECT i.*, ((2 * m) >> k) & 1 AS c FROM i JOIN f USING (batch_id) WHERE ties = 1),
g AS (SELECT batch_id, c, count(*) AS len, count(*) FILTER (truth = 'x') AS cx, count(*) FILTER (truth = 'y') AS cy FROM cl GROUP BY ALL)"""
_U_LABEL = lambda n: u("'sim'", "'label'", "batch_id", "c", f"'{n}'")
_LABELLED = f"""{_NOISY},
raw AS (SELECT batch_id, c, len, 6 * (cx + 0.6 * cy) / len + {8 * ERRING.label} * ({_U_LABEL("x")} - 0.5) AS rx, 6 * (cy + 0.6 * cx) / len + {8 * ERRING.label} * ({_U_LABEL("y")} - 0.5) AS ry FROM g),
lg AS (SELECT batch_id, c, len * (rx - ln(exp(rx) + exp(ry))) AS wx, len * (ry - ln(exp(rx) + exp(ry))) AS wy FROM raw)"""
_MATCHED = f"""{_LABELLED},
tot AS (SELECT batch_id, sum(CASE c WHEN 0 THEN wx ELSE wy END) AS keep, sum(CASE c WHEN 0 THEN wy ELSE wx END) AS swap FROM lg GROUP BY ALL)
SELECT id, CASE WHEN (keep >= swap) = (c = 0) THEN 'x' ELSE 'y' END AS pred FROM cl JOIN tot USING (batch_id)"""
_ORDERED = f"""{_NOISY}, two AS (SELECT batch_id FROM g GROUP BY ALL HAVING count(*) = 2),
mem AS (SELECT batch_id, c, list(id ORDER BY id) AS ids FROM cl JOIN two USING (batch_id) GROUP BY ALL),
draws AS (SELECT a.batch_id, a.c AS i, b.c AS j, t, a.ids AS ai, b.ids AS bi FROM mem a JOIN mem b ON a.batch_id = b.batch_id AND a.c <> b.c, (SELECT unnest(range(20)) AS t)),
asked AS (SELECT batch_id, i, j, t, ai[1 + CAST(floor({u("'joint'", "'a'", "batch_id", "i", "j", "t")} * len(ai)) AS INT)] AS a, bi[1 + CAST(floor({u("'joint'", "'b'", "batch_id", "i", "j", "t")} * len(bi)) AS INT)] AS b FROM draws),
prec AS (SELECT z.batch_id, i, j, avg(CAST((x.truth < y.truth) <> ({u("'sim'", "'compare'", "z.batch_id", "i", "j", "t", "a", "b")} < {ERRING.compare}) AS INT)) AS p FROM asked z JOIN r x ON x.id = a JOIN r y ON y.id = b GROUP BY ALL),
ord AS (SELECT a.batch_id, b.p < a.p - 1e-12 AS first_low FROM prec a JOIN prec b USING (batch_id) WHERE a.i = 0 AND b.i = 1)
SELECT id, CASE WHEN first_low = (c = 0) THEN 'x' ELSE 'y' END AS pred FROM cl JOIN ord USING (batch_id)"""


def _pool():
    return simulated_pool(KINDS, ERRING)


def _records(spark, sf) -> DataFrame:
    kind = F.when(F.split("p_name", " ")[1].isin(FIRST), "x").otherwise("y")
    return read_table(spark, sf, "part", "p_partkey", "p_name").select(F.col("p_partkey").alias("id"), F.col("p_name").alias("text"), kind.alias("hidden"))


def _batches(spark, sf) -> DataFrame:
    """The batches that run_task makes of the parts."""
    records = _records(spark, sf)
    first = stage(sample_batch(records, SMALL.batch, SMALL.seed), "first")
    rest = records.join(F.broadcast(first.select("id")), "id", "left_anti")
    return assign_batches(rest, SMALL.batch, SMALL.seed).unionByName(first.withColumn("batch_id", F.lit(-1).cast("long")))


def _found(pdf: pd.DataFrame):
    pdf = pdf.sort_values("id")
    records, batch = Records(pdf["id"].tolist(), pdf["text"].tolist(), pdf["hidden"].tolist()), int(pdf["batch_id"].iloc[0])
    return records, batch, cluster_batch(records, "", 2, Metered(_pool().strong), SMALL, batch)


def _voted(records: Records, batch: int) -> np.ndarray:
    """The weights that cluster_batch ends with: at a stop share of 0 it asks every round, whatever it groups in between."""
    ids, model = np.array(records.ids, np.int64), Metered(_pool().strong)
    votes = edges.Votes(len(records), SMALL.unseen_weight)
    w = votes.weights()
    for r in range(1, SMALL.max_rounds + 1):
        clustering.ask_round(records, ids, "", model, SMALL, batch, r, votes, w)
    return w


@functools.cache
def _groupings(n: int) -> np.ndarray:
    """Every grouping of n records into at most two, the first record's being 0."""
    return np.array([(0, *m) for m in itertools.product(range(2), repeat=n - 1)])


def _objectives(w: np.ndarray) -> np.ndarray:
    """correlation.objective of every grouping: twice the weight of pairs inside a group and the similarity of pairs across."""
    every = _groupings(len(w))
    a, b = np.triu_indices(len(w), 1)
    return 2 * np.where(every[:, a] == every[:, b], w[a, b], 1 - w[a, b]).sum(axis=1)


def _unique(spark, sf) -> DataFrame:
    """(id, clusters) of the batches with one best grouping."""

    def work(table: pa.Table) -> pa.Table:
        records = joint.rows_of(table)
        values = _objectives(_voted(records, table["batch_id"][0].as_py()))
        least = int(values.argmin())
        unique = (values < values[least] + 1e-9).sum() == 1
        ids = records.ids if unique else []
        return pa.table({"id": pa.array(ids, pa.int64()), "clusters": pa.array([len(set(_groupings(len(records))[least].tolist()))] * len(ids), pa.int32())})

    return stage(_batches(spark, sf).groupBy("batch_id").applyInArrow(work, "id long, clusters int"), "unique")


def _where_unique(spark, sf, found: tasks.Result, both: bool = False) -> DataFrame:
    unique = _unique(spark, sf)
    return found.predictions.select("id", "pred").join((unique.where("clusters = 2") if both else unique).select("id"), "id", "left_semi")


@query(f"{_NOISY} SELECT batch_id, round(objective, 6) AS objective FROM f")
def noisy_grouping(spark, sf):
    """Votes of an erring model, and the least disagreement of any grouping: that of the search."""

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        _, batch, found = _found(pdf)
        return pd.DataFrame({"batch_id": [batch], "objective": [round(correlation.objective(found.weights, found.ids, 2), 6)]})

    return _batches(spark, sf).groupBy("batch_id").applyInPandas(work, "batch_id long, objective double")


@query(f"{_NOISY} SELECT batch_id, round(objective, 6) AS objective FROM f")
def noisy_grouping_cold(spark, sf):
    """As noisy_grouping, by random starts in every round."""

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("id")
        records, batch = Records(pdf["id"].tolist(), pdf["text"].tolist(), pdf["hidden"].tolist()), int(pdf["batch_id"].iloc[0])
        found = cluster_batch(records, "", 2, Metered(_pool().strong), SMALL.but(start="random"), batch)
        return pd.DataFrame({"batch_id": [batch], "objective": [round(correlation.objective(found.weights, found.ids, 2), 6)]})

    return _batches(spark, sf).groupBy("batch_id").applyInPandas(work, "batch_id long, objective double")


@query(f"{_NOISY} SELECT batch_id, round(objective, 6) AS objective FROM f")
def noisy_grouping_exact(spark, sf):
    """As noisy_grouping, by enumeration instead of the search."""

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        _, batch, found = _found(pdf)
        return pd.DataFrame({"batch_id": [batch], "objective": [round(correlation.exact_correlation(found.weights, 2)[1], 6)]})

    return _batches(spark, sf).groupBy("batch_id").applyInPandas(work, "batch_id long, objective double")


@query(_MATCHED)
def noisy_classify(spark, sf):
    """The whole of joint classification with an erring model: votes, grouping, and matching of noisy label weights."""
    found = tasks.classify(_records(spark, sf), "id", ["text"], "", KINDS, _pool(), params=SMALL, hidden="hidden")
    return _where_unique(spark, sf, found)


@query(f"{_LABELLED} SELECT id, CASE WHEN wx >= wy THEN 'x' ELSE 'y' END AS pred FROM cl JOIN lg USING (batch_id, c)")
def noisy_classify_independent(spark, sf):
    """As noisy_classify, each group labelled by itself: both may get one label."""
    found = tasks.classify(_records(spark, sf), "id", ["text"], "", KINDS, _pool(), params=SMALL.but(assign="independent"), hidden="hidden")
    return _where_unique(spark, sf, found)


_EXAMPLES = _LABELLED.replace(f"{8 * ERRING.label} *", f"CASE WHEN count(*) OVER (PARTITION BY batch_id) = 2 THEN {12 * ERRING.label} ELSE {8 * ERRING.label} END *")


@query(f"{_EXAMPLES} SELECT id, CASE WHEN wx >= wy THEN 'x' ELSE 'y' END AS pred FROM cl JOIN lg USING (batch_id, c)")
def noisy_classify_with_examples(spark, sf):
    """As noisy_classify_independent, the model seeing examples of the other group, which distract it."""
    found = tasks.classify(_records(spark, sf), "id", ["text"], "", KINDS, _pool(), params=SMALL.but(assign="with_examples"), hidden="hidden")
    return _where_unique(spark, sf, found)


@query(_LABELLED.replace("len * (rx - ln(exp(rx) + exp(ry)))", "len * exp(rx) / (exp(rx) + exp(ry))").replace("len * (ry - ln(exp(rx) + exp(ry)))", "len * exp(ry) / (exp(rx) + exp(ry))") + _MATCHED[len(_LABELLED) :])
def noisy_classify_probabilities(spark, sf):
    """As noisy_classify, weights from probabilities instead of their logs."""
    found = tasks.classify(_records(spark, sf), "id", ["text"], "", KINDS, _pool(), params=SMALL.but(weight="probability"), hidden="hidden")
    return _where_unique(spark, sf, found)


@query(f"{_NOISY} SELECT id, CASE WHEN cx > cy OR cx = cy AND 'x' < 'y' THEN 'x' ELSE 'y' END AS pred FROM cl JOIN g USING (batch_id, c)")
def noisy_classify_majority(spark, sf):
    """As noisy_classify, by the labels that most members get; lone readings do not err here."""
    found = tasks.classify(_records(spark, sf), "id", ["text"], "", KINDS, _pool(), params=SMALL.but(assign="majority"), hidden="hidden")
    return _where_unique(spark, sf, found)


@query(_ORDERED)
def noisy_score(spark, sf):
    """The whole of joint scoring with an erring model: votes, grouping, sampled comparisons, and the order that breaks fewest."""
    found = tasks.score(_records(spark, sf), "id", ["text"], "", 2, _pool(), descriptions=KINDS, params=SMALL, hidden="hidden")
    return _where_unique(spark, sf, found, True)


@query(f"{_MATCHED} WHERE batch_id >= 0")
def noisy_cluster(spark, sf):
    """Clustering: the first batch's groups are named by what most members are, and the other batches classified under these names."""
    found = tasks.cluster(_records(spark, sf), "id", ["text"], "", 2, _pool(), params=SMALL, hidden="hidden")
    return _where_unique(spark, sf, found).join(found.predictions.where("route = 'sample'").select("id"), "id", "left_anti")


@query(f"SELECT id FROM ({_MATCHED}) WHERE pred = 'x'")
def noisy_filter(spark, sf):
    """A filter is a classification of which one class is kept."""
    kept, found = tasks.semantic_filter(_records(spark, sf), "id", ["text"], "", _pool(), yes="x", no="y", params=SMALL, hidden="hidden")
    return kept.select("id").join(_unique(spark, sf).select("id"), "id", "left_semi")


# ---- how the clustering loop ends, and who is asked

_N_BATCHES = "CAST(ceil((count(*) - 8) / 8.0) AS BIGINT)"


@query(f"SELECT 'joint' AS stage, 6 * {_N_BATCHES} AS calls FROM part UNION ALL SELECT 'sample', 6")
def tier_calls(spark, sf):
    """The light model groups and the strong one labels: calls of the light one, six rounds a batch."""
    found = tasks.classify(_records(spark, sf), "id", ["text"], "", KINDS, _pool(), params=SMALL.but(cluster_tier="light"), hidden="hidden")
    return found.ledger.where("tier = 'light'").groupBy("stage").agg(F.sum("calls").alias("calls"))


@query(f"SELECT batch_id, 3 AS rounds FROM (SELECT unnest(range(-1, {_N_BATCHES})) AS batch_id FROM part)")
def rounds_at_the_cap(spark, sf):
    """Where nothing settles, the rounds end at their cap."""
    found = joint.label_batches(_batches(spark, sf), "classify", "", KINDS, 2, _pool(), SMALL.but(max_rounds=3))
    return found.groupBy("batch_id").agg(F.max("rounds").alias("rounds"))


@query("SELECT n_nationkey AS id, r_name AS pred, 'sample' AS route FROM nation JOIN region ON n_regionkey = r_regionkey")
def classify_one_batch(spark, sf):
    """Fewer records than a batch holds, and than a round samples: one batch, all of it in every round."""
    both = read_table(spark, sf, "nation").join(F.broadcast(read_table(spark, sf, "region", "r_regionkey", "r_name")), F.col("n_regionkey") == F.col("r_regionkey"))
    labels = [r.r_name for r in both.select("r_name").distinct().orderBy("r_name").collect()]
    found = tasks.classify(both, "n_nationkey", ["n_name"], "Which region?", labels, simulated_pool(labels), params=Params(sample=400, stop_share=1e-4), hidden="r_name")
    return found.predictions.select("id", "pred", "route")


@query(f"{_NOISY} SELECT x.batch_id, x.id AS a, y.id AS b, CAST(0.25 AS DOUBLE) AS weight FROM r x JOIN r y ON x.batch_id = y.batch_id AND x.id < y.id WHERE NOT EXISTS (SELECT 1 FROM votes v WHERE v.batch_id = x.batch_id AND v.a = x.id AND v.b = y.id)")
def unseen_pairs(spark, sf):
    """Pairs that no sample held have the weight that the parameters give them."""

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("id")
        ids, batch, votes = pdf["id"].to_numpy(), int(pdf["batch_id"].iloc[0]), edges.Votes(len(pdf), 0.25)
        for r in range(1, 7):
            rows = edges.draw_sample(ids, 6, "joint", batch, r)
            votes.add(rows, np.zeros((len(rows), len(rows)), bool))
        a, b = np.nonzero(np.triu(votes.positive + votes.negative == 0, 1))
        return pd.DataFrame({"batch_id": batch, "a": ids[a], "b": ids[b], "weight": votes.weights()[a, b]})

    return _batches(spark, sf).groupBy("batch_id").applyInPandas(work, "batch_id long, a long, b long, weight double")


@query(f"""{_NOISY} SELECT x.batch_id, x.id AS a, y.id AS b, CAST((x.truth <> y.truth) <> ({u("'sim'", "'pair'", "'0'", "x.id", "y.id")} < 0.15) AS DOUBLE) AS weight FROM r x JOIN r y ON x.batch_id = y.batch_id AND x.id < y.id""")
def edge_weights_pairwise_context(spark, sf):
    """Each pair asked by itself, with a sample as context: half as many errors as without."""
    from jointsem.operators.clustering import _pairwise

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("id")
        records = Records(pdf["id"].tolist(), pdf["text"].tolist(), pdf["hidden"].tolist())
        w = _pairwise(records, "", Metered(simulated_pool(KINDS, Profile(pair=0.3)).strong), SMALL, True)
        a, b = np.nonzero(np.triu(np.ones(w.shape, bool), 1))
        ids = np.array(records.ids)
        return pd.DataFrame({"batch_id": int(pdf["batch_id"].iloc[0]), "a": ids[a], "b": ids[b], "weight": w[a, b]})

    return _batches(spark, sf).groupBy("batch_id").applyInPandas(work, "batch_id long, a long, b long, weight double")


_D = f"""{_NOISY},
t AS (SELECT i.*, CAST(truth = 'y' AS INT) AS c FROM i),
pair AS (SELECT batch_id, a, b, weight FROM w UNION ALL SELECT batch_id, b, a, weight FROM w),
d AS (SELECT x.batch_id, x.k, x.c, sum(CASE WHEN y.c = x.c THEN weight ELSE 1 - weight END) AS own, sum(CASE WHEN y.c <> x.c THEN weight ELSE 1 - weight END) AS other
  FROM t x JOIN pair p ON p.batch_id = x.batch_id AND p.a = x.k JOIN t y ON y.batch_id = x.batch_id AND y.k = p.b GROUP BY ALL),
z AS (SELECT batch_id, sum(1 / pow(n, 2)) AS spread, count(*) AS used FROM (SELECT batch_id, c, count(*) AS n FROM t GROUP BY ALL) GROUP BY ALL),
mean AS (SELECT i.batch_id, CAST(6 * 6 * 5 AS DOUBLE) / (any_value(size) * (any_value(size) - 1)) AS seen FROM i GROUP BY ALL)"""


def _bounds(spark, sf, seen: str) -> DataFrame:
    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("id")
        records, batch = Records(pdf["id"].tolist(), pdf["text"].tolist(), pdf["hidden"].tolist()), int(pdf["batch_id"].iloc[0])
        ids, votes, model = np.array(records.ids), edges.Votes(len(records)), SimulatedModel(KINDS, ERRING)
        for r in range(1, 7):
            rows = edges.draw_sample(ids, 6, "joint", batch, r)
            pairs, _ = edges.answered_rows(model.group_pairs("", records.take(rows), f"{batch}|{r}"), ids[rows])
            votes.add(rows, edges.positive_matrix(len(rows), pairs))
        truth = np.array([KINDS.index(h) for h in records.hidden])
        if len(set(truth.tolist())) < 2:
            return pd.DataFrame({"batch_id": [], "bound": []}).astype({"batch_id": "int64", "bound": "float64"})
        d = correlation.disagreement(votes.weights(), truth, 2)
        return pd.DataFrame({"batch_id": [batch], "bound": [round(stopping.uncertain_bound(d, truth, votes.per_pair() if seen == "pair_mean" else 6), 6)]})

    return _batches(spark, sf).groupBy("batch_id").applyInPandas(work, "batch_id long, bound double")


_BOUND = "SELECT batch_id, round(sum(exp(-2 * {seen} * pow(greatest(0, (other - own) / 2), 2) * spread)), 6) AS bound FROM d JOIN z USING (batch_id) JOIN mean USING (batch_id) WHERE used = 2 GROUP BY ALL"


@query(f"{_D} {_BOUND.format(seen='mean.seen')}")
def bound_by_pair_mean(spark, sf):
    """The bound that ends the rounds, counting annotations per pair."""
    return _bounds(spark, sf, "pair_mean")


@query(f"{_D} {_BOUND.format(seen='6')}")
def bound_by_rounds(spark, sf):
    """The same bound, counting rounds."""
    return _bounds(spark, sf, "rounds")


# ---- fewer clusters than classes or scores

_EMPTY = f"""WITH b AS (SELECT doc_id AS id, lang FROM (SELECT * FROM documents ORDER BY {u("'joint'", "doc_id")}, doc_id LIMIT 200)),
kinds AS (SELECT lang, list_position(['de', 'en', 'es', 'fr'], lang) - 1 AS c, count(*) AS n FROM b WHERE lang <> 'es' GROUP BY ALL),
lab AS (SELECT unnest(range(4)) AS l),
raw AS (SELECT c, l, n, CASE WHEN l = c THEN 6.0 WHEN l = (c + 1) % 4 THEN 3.6 ELSE 0.0 END + 4.0 * ({u("'sim'", "'label'", "''", "c", "(['de', 'en', 'es', 'fr'])[l + 1]")} - 0.5) * 2 AS raw FROM kinds, lab),
lw AS (SELECT c, l, n * (raw - ln(sum(exp(raw)) OVER (PARTITION BY c))) AS weight, raw - ln(sum(exp(raw)) OVER (PARTITION BY c)) AS log FROM raw)"""


def _three_groups(spark, sf, then) -> DataFrame:
    """then(weights) for the true groups of a batch without Spanish texts, under noisy label weights."""

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf[pdf["hidden"] != "es"].sort_values("id")
        records = Records(pdf["id"].tolist(), [""] * len(pdf), pdf["hidden"].tolist())
        ids = pdf["hidden"].map(LANGUAGES.index).to_numpy()
        model = Metered(Tier("strong", SimulatedModel(LANGUAGES, Profile(label=1.0)), 1, 1))
        return pd.DataFrame({"total": [round(float(then(assignment.match_weights(records, ids, 4, "", LANGUAGES, model), ids)), 6)]})

    sample = sample_batch(workload(spark, sf, "W1").records, 200, "joint")
    return _batch(sample).groupBy("batch_id").applyInPandas(work, "total double")


@query(f"{_EMPTY} SELECT round(max(x.weight + y.weight + z.weight), 6) AS total FROM lw x, lw y, lw z WHERE x.c = 0 AND y.c = 1 AND z.c = 3 AND x.l <> y.l AND y.l <> z.l AND x.l <> z.l")
def match_with_an_empty_group(spark, sf):
    """An empty group weighs nothing and takes the class that is left."""
    return _three_groups(spark, sf, lambda w, ids: w[np.arange(4), assignment.hungarian(w)].sum())


@query(f"{_EMPTY} SELECT round(max(x.weight + y.weight + z.weight), 6) AS total FROM lw x, lw y, lw z WHERE x.c = 0 AND y.c = 1 AND z.c = 3 AND x.l < y.l AND y.l < z.l")
def score_fewer_groups(spark, sf):
    """Three ordered groups get the increasing three of four scores that fit best."""

    def then(w: np.ndarray, ids: np.ndarray) -> float:
        scores = ordering.to_scores([0, 1, 3], w, 4)
        return sum(w[c, s - 1] for c, s in scores.items())

    return _three_groups(spark, sf, then)
