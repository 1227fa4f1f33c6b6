"""Every method, variant, baseline and measure as a query over the given tables, with SQL for what SQL can express.

Queries with an oracle use the lexical model, or the simulated one with draws
that SQL repeats; the simulated model's accuracies say nothing about real ones.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from jointsem.functions import measures
from jointsem.functions.expressions import as_records, lexical_class, page_text, token_count
from jointsem.functions.hashing import uniform_sql as u
from jointsem.models.base import Metered, Pool, Records, Tier
from jointsem.models.lexical import LexicalModel
from jointsem.models.simulated import Profile, SimulatedModel
from jointsem.models.simulated_df import simulated_clusters, simulated_pairs, simulated_rows, simulated_same
from jointsem.operators import assignment, correlation, edges, ordering, stopping
from jointsem.operators.sampling import assign_batches, evaluation_sample, hash_sample, sample_batch
from jointsem.plans import baselines, cascade, joint, tasks
from jointsem.plans.params import Params
from jointsem.sources.stages import stage
from jointsem.sources.tables import parse_props, read_table
from jointsem.workloads import INSULTS, NOUNS, join_workload, language_spec, workload

Query = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, Query] = {}
_SQL: dict[str, str] = {}

STRONG, LIGHT = (2.5, 10.0), (0.15, 0.6)
NOISE = Profile(group=0.1, drop=0.1, clusters=0.3, pair=0.15)
SLIPS = Profile(row=0.1, ambiguous=0.15)
LANGUAGES = ["de", "en", "es", "fr"]
#: Asks on until next to no record may be misplaced; the default stops earlier, and leaves some.
SURE = Params(stop_share=1e-4)


def query(sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        _QUERIES[f.__name__] = f
        if sql:
            _SQL[f.__name__] = sql
        return f

    return add


def queries() -> dict[str, Query]:
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)


def pool_of(strong, light=None) -> Pool:
    return Pool(Tier("strong", strong, *STRONG), Tier("light", light or strong, *LIGHT))


def simulated_pool(labels: list[str], profile: Profile | None = None, light: Profile | None = None) -> Pool:
    profile = profile or Profile()
    return pool_of(SimulatedModel(labels, profile), SimulatedModel(labels, light or profile, tag="light"))


def _one(column: str, value) -> str:
    return f"SELECT {value} AS {column}"


# ---- sampling and batches

_U_DOC = u("'joint'", "doc_id")


@query(f"SELECT doc_id AS id FROM documents ORDER BY {_U_DOC}, doc_id LIMIT 200")
def sample_batch_docs(spark, sf):
    return sample_batch(read_table(spark, sf, "documents", "doc_id").withColumnRenamed("doc_id", "id"), 200, "joint")


@query(f"""SELECT id, CAST(floor((n - 1) * ceil(c / 200.0) / c) AS BIGINT) AS batch_id FROM (
  SELECT p_partkey AS id, row_number() OVER (ORDER BY {u("'joint'", "p_partkey")}, p_partkey) AS n, count(*) OVER () AS c FROM part)""")
def assign_batches_exact(spark, sf):
    parts = read_table(spark, sf, "part", "p_partkey").select(F.col("p_partkey").alias("id"))
    return assign_batches(parts, 200, "joint", bucket_rows=300)


@query(f"SELECT event_id FROM events WHERE {u("'share'", 'event_id')} < 0.05")
def hash_sample_events(spark, sf):
    return hash_sample(read_table(spark, sf, "events", "event_id"), "event_id", 0.05, "share")


@query(f"SELECT doc_id AS id FROM documents ORDER BY {u("'evaluation'", 'doc_id')}, doc_id LIMIT 2000")
def evaluation_sample_docs(spark, sf):
    return evaluation_sample(read_table(spark, sf, "documents", "doc_id").select(F.col("doc_id").alias("id")))


# ---- edge weights of small batches of parts

_NAMES = "[" + ", ".join(f"'{n}'" for n in NOUNS) + "]"


def _next(label: str, draw: str) -> str:
    step = f"CASE WHEN {draw} < 0.8 THEN 1 ELSE 1 + CAST(floor(({draw} - 0.8) * 5 * {len(NOUNS) - 1}) AS INT) END"
    return f"{_NAMES}[(list_position({_NAMES}, {label}) - 1 + {step}) % {len(NOUNS)} + 1]"


_KEY = "concat_ws('|', batch_id, round)"
_CTE = f"""WITH r AS (SELECT CAST(floor((n - 1) * ceil(c / 60.0) / c) AS BIGINT) AS batch_id, id, truth FROM (
  SELECT p_partkey AS id, split_part(p_name, ' ', 2) AS truth, row_number() OVER (ORDER BY {u("'edges'", "p_partkey")}, p_partkey) AS n, count(*) OVER () AS c FROM part)),
s AS (SELECT batch_id, round, id, truth FROM (SELECT *, row_number() OVER (PARTITION BY batch_id, round ORDER BY {u("'joint'", "batch_id", "round", "id")}, id) AS p
  FROM r, (SELECT CAST(unnest(range(1, 11)) AS INT) AS round)) WHERE p <= 20),
seen AS (SELECT *, CASE WHEN {u("'sim'", "'group'", _KEY, "id")} < {NOISE.group} THEN {_next("truth", u("'sim'", "'group'", "'other'", _KEY, "id"))} ELSE truth END AS c FROM s),
chain AS (SELECT *, lag(id) OVER (PARTITION BY batch_id, round, c ORDER BY id) AS a FROM seen),
linked AS (SELECT *, a IS NOT NULL AND {u("'sim'", "'drop'", _KEY, "a", "id")} >= {NOISE.drop} AS hit FROM chain),
answers AS (SELECT batch_id, round, a, id AS b FROM linked WHERE hit),
seg AS (SELECT *, sum(CASE WHEN hit THEN 0 ELSE 1 END) OVER (PARTITION BY batch_id, round, c ORDER BY id) AS g FROM linked),
closure AS (SELECT x.batch_id, x.round, x.id AS a, y.id AS b FROM seg x JOIN seg y ON x.batch_id = y.batch_id AND x.round = y.round AND x.c = y.c AND x.g = y.g AND x.id < y.id),
every AS (SELECT x.batch_id, x.round, x.id AS a, y.id AS b FROM s x JOIN s y ON x.batch_id = y.batch_id AND x.round = y.round AND x.id < y.id),
grouped AS (SELECT *, CASE WHEN {u("'sim'", "'clusters'", _KEY, "id")} < {NOISE.clusters} THEN {_next("truth", u("'sim'", "'clusters'", "'other'", _KEY, "id"))} ELSE truth END AS c2 FROM s),
inside AS (SELECT x.batch_id, x.round, x.id AS a, y.id AS b FROM grouped x JOIN grouped y ON x.batch_id = y.batch_id AND x.round = y.round AND x.c2 = y.c2 AND x.id < y.id)"""


def _weights(positives: str) -> str:
    return f"""SELECT e.batch_id, e.a, e.b, CAST(count(p.a) AS INT) AS pos, CAST(count(*) - count(p.a) AS INT) AS neg, round((count(*) - count(p.a)) / count(*), 9) AS weight
  FROM every e LEFT JOIN {positives} p ON p.batch_id = e.batch_id AND p.round = e.round AND p.a = e.a AND p.b = e.b GROUP BY ALL"""


def _parts(spark, sf) -> DataFrame:
    """All parts in batches of 60."""
    parts = read_table(spark, sf, "part", "p_partkey", "p_name").select(F.col("p_partkey").alias("id"), F.split("p_name", " ")[1].alias("truth"))
    return assign_batches(parts, 60, "edges").select("batch_id", "id", "truth")


def _samples(spark, sf) -> DataFrame:
    return edges.round_samples_df(_parts(spark, sf).select("batch_id", "id"), 20, 10, "joint")


def _answers(spark, sf) -> tuple[DataFrame, DataFrame]:
    samples = stage(_samples(spark, sf), "samples")
    return samples, simulated_pairs(samples, _parts(spark, sf), NOUNS, NOISE)


def _rounded(weights: DataFrame) -> DataFrame:
    return weights.withColumn("weight", F.round("weight", 9))


def _edges(spark, sf) -> DataFrame:
    samples, answers = _answers(spark, sf)
    return edges.edge_weights_df(samples, edges.pair_closure_df(samples, answers))


def _truth_clusters(spark, sf) -> DataFrame:
    number = F.array_position(F.array(*map(F.lit, NOUNS)), F.col("truth")).cast("int")
    return _parts(spark, sf).select("batch_id", "id", number.alias("cluster_id"))


@query(f"{_CTE} SELECT batch_id, round, id FROM s")
def round_sample(spark, sf):
    return _samples(spark, sf)


@query(f"{_CTE} SELECT * FROM answers")
def answered_pairs_simulated(spark, sf):
    return _answers(spark, sf)[1]


@query(f"{_CTE} SELECT * FROM closure")
def pair_closure(spark, sf):
    return edges.pair_closure_df(*_answers(spark, sf))


@query(f"{_CTE} SELECT * FROM every EXCEPT SELECT * FROM closure")
def pair_complement(spark, sf):
    samples, answers = _answers(spark, sf)
    return edges.pair_complement_df(samples, edges.pair_closure_df(samples, answers))


@query(f"{_CTE} {_weights('closure')}")
def edge_weights_simulated(spark, sf):
    return _rounded(_edges(spark, sf))


@query(f"{_CTE} {_weights('answers')}")
def edge_weights_no_closure(spark, sf):
    return _rounded(edges.edge_weights_df(*_answers(spark, sf)))


@query(f"{_CTE} {_weights('inside')}")
def edge_weights_cluster_labels(spark, sf):
    samples = stage(_samples(spark, sf), "samples")
    return _rounded(edges.edge_weights_df(samples, simulated_clusters(samples, _parts(spark, sf), NOUNS, NOISE)))


@query(f"""{_CTE} SELECT x.batch_id, x.id AS a, y.id AS b, CAST((x.truth <> y.truth) <> ({u("'sim'", "'pair'", "'0'", "x.id", "y.id")} < {NOISE.pair}) AS INT) AS weight
  FROM r x JOIN r y ON x.batch_id = y.batch_id AND x.id < y.id""")
def edge_weights_pairwise(spark, sf):
    return simulated_same(_parts(spark, sf), NOISE)


@query(f"{_CTE} SELECT x.batch_id, x.id AS a, y.id AS b, CAST(x.truth <> y.truth AS INT) AS weight FROM r x JOIN r y ON x.batch_id = y.batch_id AND x.id < y.id")
def edge_weights_truth(spark, sf):
    return edges.edge_weights_truth_df(_parts(spark, sf))


@query(f"{_CTE} SELECT batch_id, a, b, pos, neg, weight FROM ({_weights('closure')})")
def edge_weights_in_worker(spark, sf):
    """The array form, as the clustering uses it, with the simulated model asked in the worker."""

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("id")
        records = Records(pdf["id"].tolist(), [""] * len(pdf), pdf["truth"].tolist())
        ids, model, votes, batch = np.array(records.ids), SimulatedModel(NOUNS, NOISE), edges.Votes(len(pdf)), int(pdf["batch_id"].iloc[0])
        for r in range(1, 11):
            rows = edges.draw_sample(ids, 20, "joint", batch, r)
            pairs, _ = edges.answered_rows(model.group_pairs("", records.take(rows), f"{batch}|{r}"), ids[rows])
            votes.add(rows, edges.positive_matrix(len(rows), pairs))
        a, b = np.nonzero(np.triu(votes.positive + votes.negative, 1))
        return pd.DataFrame({"batch_id": batch, "a": ids[a], "b": ids[b], "pos": votes.positive[a, b], "neg": votes.negative[a, b], "weight": votes.weights()[a, b].round(9)})

    return _parts(spark, sf).groupBy("batch_id").applyInPandas(work, "batch_id long, a long, b long, pos int, neg int, weight double")


_CLUSTERS = f"""{_CTE}, w AS ({_weights('closure')}), k AS (SELECT batch_id, id, CAST(list_position({_NAMES}, truth) AS INT) AS cluster_id FROM r),
both_ AS (SELECT batch_id, a AS id, b AS other, (neg / (pos + neg)) AS weight FROM w UNION ALL SELECT batch_id, b, a, (neg / (pos + neg)) FROM w),
d AS (SELECT o.batch_id, o.id, c.cluster_id, o.outside + coalesce(i.inside, 0) AS d FROM (SELECT batch_id, id, sum(1 - weight) AS outside FROM both_ GROUP BY ALL) o
  JOIN (SELECT DISTINCT batch_id, cluster_id FROM k) c USING (batch_id)
  LEFT JOIN (SELECT e.batch_id, e.id, k.cluster_id, sum(2 * weight - 1) AS inside FROM both_ e JOIN k ON k.batch_id = e.batch_id AND k.id = e.other GROUP BY ALL) i
  ON i.batch_id = o.batch_id AND i.id = o.id AND i.cluster_id = c.cluster_id)"""


@query(f"{_CLUSTERS} SELECT batch_id, id, cluster_id, round(d, 6) AS d FROM d")
def disagreement_by_cluster(spark, sf):
    return correlation.disagreement_df(_edges(spark, sf), _truth_clusters(spark, sf)).withColumn("d", F.round("d", 6))


@query(f"{_CLUSTERS} SELECT batch_id, round(sum(d), 6) AS objective FROM d JOIN k USING (batch_id, id, cluster_id) GROUP BY ALL")
def objective_value(spark, sf):
    clusters = _truth_clusters(spark, sf)
    return correlation.objective_df(correlation.disagreement_df(_edges(spark, sf), clusters), clusters).withColumn("objective", F.round("objective", 6))


@query(f"""{_CLUSTERS}, own AS (SELECT d.batch_id, d.id, d.d AS own, k.cluster_id AS held FROM d JOIN k USING (batch_id, id, cluster_id)),
gap AS (SELECT d.batch_id, d.id, own, min(d.d) AS other FROM d JOIN own USING (batch_id, id) WHERE d.cluster_id <> held GROUP BY ALL),
z AS (SELECT batch_id, sum(1 / pow(n, 2)) AS spread FROM (SELECT batch_id, cluster_id, count(*) AS n FROM k GROUP BY ALL) GROUP BY ALL)
SELECT batch_id, round(sum(exp(-2 * 5.0 * pow(greatest(0, (other - own) / 2), 2) * spread)), 6) AS bound FROM gap JOIN z USING (batch_id) GROUP BY ALL""")
def uncertain_bound(spark, sf):
    clusters = _truth_clusters(spark, sf)
    return stopping.uncertain_bound_df(correlation.disagreement_df(_edges(spark, sf), clusters), clusters, 5.0).withColumn("bound", F.round("bound", 6))


@query(f"{_CTE}, w AS ({_weights('closure')}) SELECT round(avg(weight) FILTER (x.truth <> y.truth) - avg(weight) FILTER (x.truth = y.truth), 6) AS separation FROM w JOIN r x ON x.id = a JOIN r y ON y.id = b")
def weight_separation(spark, sf):
    return measures.weight_separation(_rounded(_edges(spark, sf)), _parts(spark, sf)).withColumn("separation", F.round("separation", 6))


# ---- clustering

def _batch(records: DataFrame) -> DataFrame:
    return records.select(F.lit(0).cast("long").alias("batch_id"), "id", "text", F.col("truth").alias("hidden"))


@query(_one("improvable", 0))
def correlation_local_optimum(spark, sf):
    """Records of noisy weights that another cluster would suit better after the search: none."""

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("id")
        w = edges.weights_from_truth(pdf["hidden"].tolist())
        noise = np.random.default_rng(3).random(w.shape)
        w = np.clip(w * 0.7 + np.triu(noise, 1) * 0.3 + np.triu(noise, 1).T * 0.3, 0, 1)
        np.fill_diagonal(w, 0)
        ids = correlation.correlation_cluster(w, len(NOUNS), pdf["id"].to_numpy())
        d = correlation.disagreement(w, ids, len(NOUNS))
        return pd.DataFrame({"improvable": [int((d.min(axis=1) < d[np.arange(len(d)), ids] - 1e-9).sum())]})

    sample = sample_batch(workload(spark, sf, "W4").records, 200, "joint")
    return _batch(sample).groupBy("batch_id").applyInPandas(work, "improvable int")


def _cluster_purity(spark, sf, name: str, params: Params = SURE) -> DataFrame:
    w = workload(spark, sf, name)
    sample = stage(sample_batch(w.records, params.batch_size(w.k), params.seed), "batch")
    found = joint.cluster_batches(_batch(sample), w.instruction, w.k, simulated_pool(w.labels), params)
    pred = found.select("id", F.col("cluster_id").alias("pred"))
    return measures.clustering_accuracy(pred, sample).withColumn("clustering_accuracy", F.round("clustering_accuracy", 6))


@query(_one("clustering_accuracy", "CAST(1.0 AS DOUBLE)"))
def cluster_lang_batch(spark, sf):
    return _cluster_purity(spark, sf, "W1")


@query(_one("clustering_accuracy", "CAST(1.0 AS DOUBLE)"))
def cluster_parts_noun_batch(spark, sf):
    return _cluster_purity(spark, sf, "W4")


@query(_one("clustering_accuracy", "CAST(1.0 AS DOUBLE)"))
def cluster_parts_adjective_batch(spark, sf):
    """The same records as for nouns, under another instruction."""
    return _cluster_purity(spark, sf, "W7")


@query()
def clustering_trace(spark, sf):
    w = workload(spark, sf, "W1")
    batch = _batch(sample_batch(w.records, 200, "joint"))
    trace = joint.trace_batches(batch, w.instruction, w.k, simulated_pool(w.labels, Profile(group=0.15, drop=0.2)), Params())
    return trace.withColumn("fell", F.col("objective") < F.lag("objective").over(Window.partitionBy("batch_id").orderBy("round")))


# ---- labelling clusters

_SPEC = language_spec()


def _count_sql(text: str, pattern: str) -> str:
    return f"len(regexp_extract_all(lower({text}), '{pattern}'))"


def _best_sql(text: str, spec: dict[str, str]) -> str:
    """The class with most matches; of equals the first."""
    names = list(spec)
    counts = [_count_sql(text, p) for p in spec.values()]
    cases = " ".join(f"WHEN {c} >= ALL_ THEN '{n}'".replace("ALL_", f"greatest({', '.join(counts)})") for n, c in zip(names, counts, strict=True))
    return f"CASE {cases} END"


_LANG_BEST = _best_sql("text", _SPEC)
_MATCH = f"""WITH b AS (SELECT lang AS cluster, {_LANG_BEST} AS best FROM (SELECT * FROM documents ORDER BY {_U_DOC}, doc_id LIMIT 200)),
n AS (SELECT c.cluster, l.best, (SELECT count(*) FROM b WHERE b.cluster = c.cluster AND b.best = l.best) AS hits, (SELECT count(*) FROM b WHERE b.cluster = c.cluster) AS size
  FROM (SELECT DISTINCT cluster FROM b) c, (SELECT unnest(['de', 'en', 'es', 'fr']) AS best) l),
w AS (SELECT cluster, best AS label, size * (6.0 * hits / size - ln(sum(exp(6.0 * hits / size)) OVER (PARTITION BY cluster))) AS weight FROM n)"""


def _lang_weights(spark, sf) -> DataFrame:
    """Match weights of the true language clusters of a batch, labelled by the lexical model."""

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("id")
        records = Records(pdf["id"].tolist(), pdf["text"].tolist())
        ids = pdf["hidden"].map(LANGUAGES.index).to_numpy()
        w = assignment.match_weights(records, ids, 4, "", LANGUAGES, Metered(Tier("strong", LexicalModel(_SPEC), *STRONG)))
        return pd.DataFrame([(c, n, float(w[i, j])) for i, c in enumerate(LANGUAGES) for j, n in enumerate(LANGUAGES) if (ids == i).any()], columns=["cluster", "label", "weight"])

    sample = sample_batch(workload(spark, sf, "W1").records, 200, "joint")
    return _batch(sample).groupBy("batch_id").applyInPandas(work, "cluster string, label string, weight double")


@query(f"{_MATCH} SELECT cluster, label, round(weight, 6) AS weight FROM w")
def match_weights(spark, sf):
    return _lang_weights(spark, sf).withColumn("weight", F.round("weight", 6))


@query(f"""{_MATCH}, p AS (SELECT a.label AS de, b.label AS en, c.label AS es, d.label AS fr, a.weight + b.weight + c.weight + d.weight AS total FROM w a, w b, w c, w d
  WHERE a.cluster = 'de' AND b.cluster = 'en' AND c.cluster = 'es' AND d.cluster = 'fr' AND len(list_distinct([a.label, b.label, c.label, d.label])) = 4)
SELECT round(max(total), 6) AS total FROM p""")
def match_assignment(spark, sf):
    """The optimum of the one-to-one assignment."""

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        w = pdf.pivot(index="cluster", columns="label", values="weight").to_numpy()
        return pd.DataFrame({"total": [round(float(w[np.arange(len(w)), assignment.hungarian(w)].sum()), 6)]})

    return _lang_weights(spark, sf).withColumn("g", F.lit(0)).groupBy("g").applyInPandas(work, "total double")


@query(f"{_MATCH} SELECT cluster, min(label) AS label FROM (SELECT *, max(weight) OVER (PARTITION BY cluster) AS top FROM w) WHERE weight >= top - 1e-9 GROUP BY ALL")
def assign_independent(spark, sf):
    best = F.max_by("label", F.struct("weight", F.expr("-ascii(label)")))
    return _lang_weights(spark, sf).groupBy("cluster").agg(best.alias("label"))


@query(f"{_MATCH}, c AS (SELECT cluster, best, count(*) AS n FROM b GROUP BY ALL) SELECT cluster, label FROM (SELECT cluster, best AS label, row_number() OVER (PARTITION BY cluster ORDER BY n DESC, best) AS r FROM c) WHERE r = 1")
def assign_majority(spark, sf):
    sample = sample_batch(workload(spark, sf, "W1").records, 200, "joint")
    return measures.majority(sample.select(F.col("truth").alias("cluster"), lexical_class(F.col("text"), _SPEC).alias("label")), "cluster", "label")


def _assigned(spark, sf, mode: str) -> DataFrame:
    w = workload(spark, sf, "W9")
    found = tasks.classify(w.records, "id", ["text"], w.instruction, w.labels, simulated_pool(w.labels, Profile(label=0.5, row=0.2)), params=Params(assign=mode), hidden="truth")
    return found.predictions.select("id", "pred")


@query()
def assign_with_examples(spark, sf):
    return _assigned(spark, sf, "with_examples")


@query()
def assign_matching_noisy(spark, sf):
    return _assigned(spark, sf, "matching")


# ---- scoring

_LEVELS = ["1", "2", "3", "4"]
_S4 = "CASE o_orderpriority WHEN '5-LOW' THEN '1' WHEN '3-MEDIUM' THEN '2' WHEN '2-HIGH' THEN '3' WHEN '1-URGENT' THEN '4' END"
_PRECEDENCE = f"""WITH q AS (SELECT o_orderkey AS id, {_S4} AS level FROM orders WHERE {_S4} IS NOT NULL),
m AS (SELECT level, list(id ORDER BY id) AS ids FROM (SELECT * FROM q ORDER BY {u("'joint'", "id")}, id LIMIT 200) GROUP BY level),
p AS (SELECT CAST(a.level AS INT) - 1 AS i, CAST(b.level AS INT) - 1 AS j, a.ids AS ai, b.ids AS bi, a.level AS al, b.level AS bl, t FROM m a, m b, (SELECT unnest(range(20)) AS t) WHERE a.level <> b.level),
x AS (SELECT i, j, t, al, bl, ai[1 + CAST(floor({u("'joint'", "'a'", "''", "i", "j", "t")} * len(ai)) AS INT)] AS a, bi[1 + CAST(floor({u("'joint'", "'b'", "''", "i", "j", "t")} * len(bi)) AS INT)] AS b FROM p),
w AS (SELECT i, j, avg(CAST((al < bl) <> ({u("'sim'", "'compare'", "'|' || i || '|' || j || '|' || t", "a", "b")} < 0.2) AS INT)) AS weight FROM x GROUP BY i, j)"""


def _precedence(spark, sf) -> DataFrame:
    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("id")
        records = Records(pdf["id"].tolist(), pdf["text"].tolist(), pdf["hidden"].tolist())
        ids = pdf["hidden"].map(_LEVELS.index).to_numpy()
        model = Metered(Tier("strong", SimulatedModel(_LEVELS, Profile(compare=0.2)), *STRONG))
        w = ordering.precedence(records, ids, 4, "", model, 20, "joint")
        return pd.DataFrame([(i, j, float(w[i, j])) for i in range(4) for j in range(4) if i != j], columns=["i", "j", "weight"])

    sample = sample_batch(workload(spark, sf, "S4").records, 200, "joint")
    return _batch(sample).groupBy("batch_id").applyInPandas(work, "i int, j int, weight double")


@query(f"{_PRECEDENCE} SELECT i, j, round(weight, 6) AS weight FROM w")
def precedence_matrix(spark, sf):
    return _precedence(spark, sf).withColumn("weight", F.round("weight", 6))


@query(f"""{_PRECEDENCE}, o AS (SELECT [a, b, c, d] AS o FROM (SELECT unnest(range(4)) AS a), (SELECT unnest(range(4)) AS b), (SELECT unnest(range(4)) AS c), (SELECT unnest(range(4)) AS d) WHERE len(list_distinct([a, b, c, d])) = 4),
v AS (SELECT o, (SELECT sum(weight) FROM w WHERE list_position(o, w.j) < list_position(o, w.i)) AS violation FROM o) SELECT round(min(violation), 6) AS violation FROM v""")
def order_min_violation(spark, sf):
    """The least violation of any total order."""

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        w = np.zeros((4, 4))
        w[pdf["i"], pdf["j"]] = pdf["weight"]
        return pd.DataFrame({"violation": [round(ordering.ordering_objective(w, ordering.order_clusters(w)), 6)]})

    return _precedence(spark, sf).withColumn("g", F.lit(0)).groupBy("g").applyInPandas(work, "violation double")


def _scored(spark, sf, name: str, mode: str) -> DataFrame:
    w = workload(spark, sf, name)
    return tasks.score(w.records, "id", ["text"], w.instruction, w.k, simulated_pool(w.labels), params=SURE.but(score_assign=mode), hidden="truth").predictions.select("id", "pred")


_PRIORITY = f"SELECT o_orderkey AS id, {_S4} AS pred FROM orders WHERE {_S4} IS NOT NULL"


@query(_PRIORITY)
def score_priority(spark, sf):
    return _scored(spark, sf, "S4", "order")


@query("SELECT event_id AS id, CAST(ntile(5) OVER (ORDER BY value, event_id) AS VARCHAR) AS pred FROM events")
def score_events(spark, sf):
    return _scored(spark, sf, "S5", "order")


@query(_PRIORITY)
def score_matching(spark, sf):
    return _scored(spark, sf, "S4", "matching")


@query(_PRIORITY)
def score_independent(spark, sf):
    return _scored(spark, sf, "S4", "independent")


# ---- row-wise methods with the lexical model

def _lexical(spark, sf, name: str) -> tuple:
    w = workload(spark, sf, name)
    return w, pool_of(w.lexical())


_TOXIC = f"CASE WHEN regexp_matches(lower(text), '{'|'.join(INSULTS)}') THEN '1' ELSE '0' END"
_JUNK = "CASE WHEN regexp_matches(lower(text), '!!|[#$%&*]{3}| [|] ') THEN '0' ELSE '1' END"


def _rows(spark, sf, name: str, labels: list[str] | None = None) -> DataFrame:
    w, pool = _lexical(spark, sf, name)
    return baselines.row_by_row(w.records.select("id", "text"), w.instruction, labels or w.labels, pool).predictions.select("id", "pred")


@query(f"SELECT doc_id AS id, {_LANG_BEST} AS pred FROM documents")
def row_by_row_lang(spark, sf):
    return _rows(spark, sf, "W1")


@query(f"SELECT doc_id AS id, {_LANG_BEST} AS pred FROM documents")
def lexical_class_lang(spark, sf):
    """The lexical model as a column expression."""
    return read_table(spark, sf, "documents", "doc_id", "text").select(F.col("doc_id").alias("id"), lexical_class(F.col("text"), _SPEC).alias("pred"))


@query(f"SELECT doc_id AS id, {_TOXIC} AS pred FROM documents JOIN labels USING (doc_id)")
def row_by_row_toxic(spark, sf):
    return _rows(spark, sf, "W12", ["0", "1"]).select("id", "pred")


@query(f"SELECT doc_id AS id, {_JUNK} AS pred FROM documents JOIN labels USING (doc_id)")
def row_by_row_quality(spark, sf):
    return _rows(spark, sf, "W11", ["1", "0"])


@query(f"SELECT doc_id AS id, {_LANG_BEST} AS pred FROM documents")
def batch_prompt_lang(spark, sf):
    w, pool = _lexical(spark, sf, "W1")
    return baselines.batch_prompt(w.records.select("id", "text"), w.instruction, w.labels, pool).predictions.select("id", "pred")


@query(f"SELECT doc_id AS id, {_LANG_BEST} AS pred FROM documents")
def rubric_lang(spark, sf):
    w, pool = _lexical(spark, sf, "W1")
    return baselines.rubric_then_rows(w.records.select("id", "text"), w.instruction, w.labels, pool).predictions.select("id", "pred")


# ---- the budget cascade, over the simulated row-wise pass on documents

_LANGS = "['de', 'en', 'es', 'fr']"


def _slip(label: str, draw: str) -> str:
    step = f"CASE WHEN {draw} < 0.8 THEN 1 ELSE 1 + CAST(floor(({draw} - 0.8) * 5 * 3) AS INT) END"
    return f"{_LANGS}[(list_position({_LANGS}, {label}) - 1 + {step}) % 4 + 1]"


_AMBIGUOUS = f"{u("'sim'", "'ambiguous'", 'doc_id')} < {SLIPS.ambiguous}"
_WRONG = f"{u("'sim'", "'row'", 'doc_id')} < {SLIPS.row}"
_SIM = f"""WITH p AS (SELECT doc_id AS id, lang AS truth, CASE WHEN {_AMBIGUOUS} THEN {_slip('lang', '0.0')} WHEN {_WRONG} THEN {_slip('lang', u("'sim'", "'other'", 'doc_id'))} ELSE lang END AS pred,
  CASE WHEN {_AMBIGUOUS} OR {_WRONG} THEN 0.2 + 0.6 * {u("'sim'", "'confidence'", 'doc_id')} ELSE 0.6 + 0.4 * {u("'sim'", "'confidence'", 'doc_id')} END AS confidence FROM documents)"""


def _sim(spark, sf) -> DataFrame:
    docs = read_table(spark, sf, "documents", "doc_id", "lang").select(F.col("doc_id").alias("id"), F.col("lang").alias("hidden"))
    return simulated_rows(docs, LANGUAGES, SLIPS)


def _lang_truth(spark, sf) -> DataFrame:
    return read_table(spark, sf, "documents", "doc_id", "lang").select(F.col("doc_id").alias("id"), F.col("lang").alias("truth"))


@query(f"{_SIM} SELECT id, pred, round(confidence, 9) AS confidence FROM p")
def row_by_row_simulated(spark, sf):
    """The simulated model asked in workers; SQL repeats its draws."""
    w = workload(spark, sf, "W1")
    records = w.records.select("id", "text", F.col("truth").alias("hidden"))
    found = cascade.row_wise(records, w.instruction, LANGUAGES, Tier("strong", SimulatedModel(LANGUAGES, SLIPS), *STRONG))
    return found.select("id", "pred", F.round("confidence", 9).alias("confidence"))


_C0, _CP, _B = 0.01, 0.02, 200
_ALLOWED = f"CAST(floor((budget - {_CP}) / {_C0} - 1 + 1e-9) * {_B} AS BIGINT)"


@query(f"""{_SIM}, t AS (SELECT unnest([0.04, 0.05, 0.06, 0.08, 0.2]) AS budget), c AS (SELECT DISTINCT round(confidence, 9) AS v FROM p UNION SELECT 1.0),
b AS (SELECT v, (SELECT count(*) FROM p WHERE round(p.confidence, 9) < c.v) AS below FROM c) SELECT budget, max(v) AS tau FROM t, b WHERE below <= {_ALLOWED} GROUP BY budget""")
def threshold_choice(spark, sf):
    scores = stage(_sim(spark, sf).select(F.round("confidence", 9).alias("confidence")), "scores")
    rows = [(b, cascade.choose_threshold(scores, _B, _C0, _CP, b)) for b in (0.04, 0.05, 0.06, 0.08, 0.2)]
    return spark.createDataFrame(rows, "budget double, tau double")


@query(f"{_SIM} SELECT confidence >= 0.7 AS sure, count(*) AS n, round({_CP} + {_C0} * (1 + ceil(count(*) FILTER (confidence < 0.7) / {_B}.0)), 9) AS cost FROM p GROUP BY sure")
def route_counts(spark, sf):
    scored = _sim(spark, sf)
    parts = []
    for sure, part in zip((True, False), cascade.route(scored, 0.7), strict=True):
        parts.append(part.groupBy().agg(F.lit(sure).alias("sure"), F.count("*").alias("n")))
    n = F.when(F.col("sure"), 0).otherwise(F.col("n"))
    return parts[0].unionByName(parts[1]).withColumn("cost", F.round(_CP + _C0 * (1 + F.ceil(n / _B)), 9))


@query(f"{_SIM}, b AS (SELECT CAST(least(floor(confidence * 50), 49) AS INT) AS bin, count(*) AS n FROM p GROUP BY ALL) SELECT bin, n, CAST(coalesce(sum(n) OVER (ORDER BY bin ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS below FROM b")
def score_histogram(spark, sf):
    return cascade.score_histogram(_sim(spark, sf), 50)


@query(f"""{_SIM}, b AS (SELECT CAST(least(floor(confidence * 50), 49) AS INT) AS bin, count(*) AS n FROM p GROUP BY ALL),
c AS (SELECT bin, coalesce(sum(n) OVER (ORDER BY bin ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below FROM b)
SELECT bin / 50.0 AS tau, round({_CP} + {_C0} * (1 + ceil(below / {_B}.0)), 9) AS cost FROM c""")
def cost_curve(spark, sf):
    """Cost of every binned threshold."""
    return cascade.score_histogram(_sim(spark, sf), 50).select((F.col("bin") / 50).alias("tau"), F.round(_CP + _C0 * (1 + F.ceil(F.col("below") / _B)), 9).alias("cost"))


@query("""WITH t AS (SELECT sum(ceil(length(text) / 4.0)) + count(*) * (9 + 4 + 2) AS tin, count(*) AS n FROM documents), b AS (SELECT unnest([0.1, 1.0, 10.0]) AS budget)
SELECT budget, CASE WHEN 0.05 + (tin * 2.5 + n * 10.0) / 1e6 <= budget THEN 'strong' ELSE 'light' END AS proxy FROM t, b""")
def proxy_choice(spark, sf):
    docs = as_records(read_table(spark, sf, "documents", "doc_id", "text"), "doc_id", ["text"])
    strong, _ = cascade.predicted_cost(docs, "Which language is this text in?"[:36], LANGUAGES, [Tier("strong", None, *STRONG), Tier("light", None, *LIGHT)])
    return spark.createDataFrame([(b, cascade.choose_proxy(0.05, strong, b)) for b in (0.1, 1.0, 10.0)], "budget double, proxy string")


@query("SELECT b AS budget, 0.01 * ceil((SELECT count(*) FROM documents) / 200.0) <= b AS feasible FROM (SELECT unnest([0.01, 0.045, 0.065, 0.45, 0.65]) AS b)")
def full_joint_feasible(spark, sf):
    n = read_table(spark, sf, "documents", "doc_id").count()
    return spark.createDataFrame([(b, cascade.full_joint_feasible(0.01, n, 200, b)) for b in (0.01, 0.045, 0.065, 0.45, 0.65)], "budget double, feasible boolean")


# ---- joint tasks; a simulated model without noise must return the truth

def _classified(spark, sf, name: str, n: int | None = None, **options) -> tasks.Result:
    w = workload(spark, sf, name)
    records = evaluation_sample(w.records, n) if n else w.records
    return tasks.classify(records, "id", ["text"], w.instruction, w.labels, simulated_pool(w.labels), hidden="truth", params=SURE, **options)


@query("SELECT doc_id AS id, lang AS pred FROM documents")
def classify_lang_unbounded(spark, sf):
    return _classified(spark, sf, "W1").predictions.select("id", "pred")


@query("SELECT doc_id AS id, lang AS pred FROM documents")
def classify_lang_budget(spark, sf):
    """A tight budget: most records by the proxy, the unsure ones jointly."""
    return _classified(spark, sf, "W1", budget=0.8).predictions.select("id", "pred")


@query("SELECT p_partkey AS id, split_part(p_name, ' ', 2) AS pred FROM part")
def classify_parts_noun(spark, sf):
    return _classified(spark, sf, "W4").predictions.select("id", "pred")


@query("SELECT p_partkey AS id, split_part(p_name, ' ', 1) AS pred FROM part")
def classify_parts_adjective(spark, sf):
    return _classified(spark, sf, "W7").predictions.select("id", "pred")


@query("SELECT c_custkey AS id, n_name AS pred FROM customer JOIN nation ON c_nationkey = n_nationkey")
def classify_customers_nation(spark, sf):
    return _classified(spark, sf, "W9").predictions.select("id", "pred")


@query("SELECT conv_id * 100000 + turn AS id, role AS pred FROM conversations")
def classify_turns_role(spark, sf):
    return _classified(spark, sf, "W6").predictions.select("id", "pred")


@query("SELECT count(*) AS n, count(*) AS ids FROM documents")
def route_coverage(spark, sf):
    """Every record is predicted once, whatever its route."""
    found = _classified(spark, sf, "W1", budget=0.8).predictions
    return found.agg(F.count("*").alias("n"), F.count_distinct("id").alias("ids"))


@query("SELECT doc_id AS id, lang AS pred FROM documents")
def classify_forced_joint(spark, sf):
    return _classified(spark, sf, "W1", budget=0.0, force_route="joint").predictions.select("id", "pred")


@query("SELECT doc_id AS id, lang AS pred FROM documents")
def classify_forced_proxy(spark, sf):
    return _classified(spark, sf, "W1", force_route="proxy").predictions.select("id", "pred")


@query(_one("clustering_accuracy", "CAST(1.0 AS DOUBLE)"))
def cluster_parts(spark, sf):
    w = workload(spark, sf, "W4")
    found = tasks.cluster(w.records, "id", ["text"], w.instruction, w.k, simulated_pool(w.labels), hidden="truth", params=SURE)
    return measures.clustering_accuracy(found.predictions, w.records).withColumn("clustering_accuracy", F.round("clustering_accuracy", 6))


@query("SELECT doc_id AS id, lang AS pred FROM documents")
def cluster_docs(spark, sf):
    """Clusters are named by their summaries, which the simulated model gives as the true names."""
    w = workload(spark, sf, "W1")
    found = tasks.cluster(w.records, "id", ["text"], w.instruction, w.k, simulated_pool(w.labels), hidden="truth", params=SURE.but(cluster_names="matching"))
    return found.predictions.select("id", "pred")


def _filtered(spark, sf, name: str, value: str) -> DataFrame:
    w = workload(spark, sf, name)
    rows = w.records.select("id", "text", F.when(F.col("truth") == value, "yes").otherwise("no").alias("hidden"))
    return tasks.semantic_filter(rows, "id", ["text"], w.instruction, simulated_pool(["yes", "no"]), hidden="hidden", params=SURE)[0].select("id")


@query("SELECT doc_id AS id FROM documents JOIN labels USING (doc_id) WHERE toxic = 1")
def filter_toxic(spark, sf):
    return _filtered(spark, sf, "W12", "1")


@query("SELECT doc_id AS id FROM documents JOIN labels USING (doc_id) WHERE quality = 1")
def filter_quality(spark, sf):
    return _filtered(spark, sf, "W11", "1")


def _runs_sql(table: str, key: str, name: str, length: int) -> str:
    """CTE of (id, gram): the distinct runs of `length` words of a table's texts."""
    return f"""{name}_w AS (SELECT {key} AS id, regexp_extract_all(lower(coalesce(text, '')), '[\\p{{L}}\\p{{N}}]+') AS w FROM {table}),
{name} AS (SELECT DISTINCT id, array_to_string(w[p:p + n - 1], ' ') AS gram FROM (SELECT id, w, least({length}, len(w)) AS n, unnest(range(1, len(w) - least({length}, len(w)) + 2)) AS p FROM {name}_w))"""


def _pairs_sql(length: int, tag: str) -> str:
    return f"""{_runs_sql("documents", "doc_id", f"d{tag}", length)}, {_runs_sql("benchmark", "item_id", f"b{tag}", length)},
p{tag} AS (SELECT DISTINCT d.id AS left_id, b.id AS right_id FROM d{tag} d JOIN b{tag} b USING (gram))"""


@query(f"WITH {_pairs_sql(8, '8')} SELECT * FROM p8")
def join_candidates(spark, sf):
    """Pairs that share a run of eight words."""
    return tasks.candidate_pairs(*join_workload(spark, sf), 8)


@query(f"WITH {_pairs_sql(13, '13')} SELECT * FROM p13")
def join_benchmark(spark, sf):
    """Candidate pairs, asked whether the document quotes the passage: whether any 13 words of it, in order, stand in the document."""
    docs, items = join_workload(spark, sf)
    pairs = tasks.candidate_pairs(docs, items, 8)
    quoted = tasks.candidate_pairs(docs, items, 13).withColumn("quoted", F.lit("yes"))
    both = pairs.join(quoted, ["left_id", "right_id"], "left").join(docs.select(F.col("id").alias("left_id"), F.col("text").alias("l")), "left_id").join(items.select(F.col("id").alias("right_id"), F.col("text").alias("r")), "right_id")
    rows = stage(both.select("left_id", "right_id", F.xxhash64("left_id", "right_id").alias("id"), F.concat_ws(" ⟂ ", "l", "r").alias("text"), F.coalesce("quoted", F.lit("no")).alias("hidden")), "pairs")
    return tasks.semantic_filter(rows, "id", ["text"], "Does the text quote the passage?", simulated_pool(["yes", "no"]), hidden="hidden", params=SURE.but(max_rounds=60))[0].select("left_id", "right_id")


@query(f"WITH {_pairs_sql(13, '13')}, {_pairs_sql(16, '16')} SELECT (SELECT count(*) FROM p13) AS n_true, count(*) AS n_found, (SELECT count(*) FROM p16) AS n_candidates, round(count(*) / (SELECT count(*) FROM p13), 9) AS recall FROM p13 JOIN p16 USING (left_id, right_id)")
def join_blocking_recall(spark, sf):
    """What blocking by runs of sixteen words finds of the pairs that share thirteen."""
    docs, items = join_workload(spark, sf)
    return tasks.blocking_recall(tasks.candidate_pairs(docs, items, 16), tasks.candidate_pairs(docs, items, 13)).withColumn("recall", F.round("recall", 9))


@query("SELECT doc_id AS id, min(doc_id) OVER (PARTITION BY text) AS class_id, count(*) OVER (PARTITION BY text) AS copies FROM documents")
def join_equal_texts(spark, sf):
    """Equal texts as classes: each document with the least id of its class, never all pairs of one.  Counts combine before the shuffle, and the classes of several texts come back by the hash."""
    docs = read_table(spark, sf, "documents", "doc_id", "text").select(F.col("doc_id").alias("id"), F.md5(F.col("text").cast("binary")).alias("key"))
    classes = docs.groupBy("key").agg(F.min("id").alias("class_id"), F.count("*").alias("copies"))
    return docs.join(classes, docs.key.eqNullSafe(classes.key)).select("id", "class_id", "copies")


@query("SELECT p_partkey AS id, split_part(p_name, ' ', 2) AS answer FROM part")
def contextual_summaries(spark, sf):
    w = workload(spark, sf, "W4")
    records = stage(w.records.withColumnRenamed("truth", "hidden"), "records")
    found = tasks.classify(records, "id", ["text"], w.instruction, w.labels, simulated_pool(w.labels), hidden="hidden", params=SURE)
    return tasks.contextual_map(found.predictions, records, "Describe it.", simulated_pool(w.labels))


# ---- clustering baselines

@query()
def kmeans_embeddings(spark, sf):
    vectors = baselines.vector_rows(read_table(spark, sf, "embeddings", "vec_id", "embedding"), "vec_id", "embedding")
    return baselines.kmeans(vectors, 10).predictions.select("id", "pred")


def _clustered(spark, sf, how: Callable, name: str = "W4") -> DataFrame:
    w = workload(spark, sf, name)
    return how(stage(w.records.withColumnRenamed("truth", "hidden"), "records"), w).predictions.select("id", "pred")


@query()
def embedding_kmeans(spark, sf):
    return _clustered(spark, sf, lambda r, w: baselines.embedding_kmeans(r, w.k))


@query()
def keyphrase_kmeans(spark, sf):
    return _clustered(spark, sf, lambda r, w: baselines.keyphrase_kmeans(r, w.instruction, w.k, simulated_pool(w.labels)))


@query("SELECT p_partkey AS id, split_part(p_name, ' ', 2) AS pred FROM part")
def label_then_assign(spark, sf):
    return _clustered(spark, sf, lambda r, w: baselines.label_then_assign(r, w.instruction, w.k, simulated_pool(w.labels)))


@query()
def semantic_group_by(spark, sf):
    return _clustered(spark, sf, lambda r, w: baselines.semantic_group_by(r, w.instruction, w.k, simulated_pool(w.labels)))


@query()
def direct_cluster(spark, sf):
    """One question about 200 records drawn from all."""
    return _clustered(spark, sf, lambda r, w: baselines.direct_cluster(r, w.instruction, simulated_pool(w.labels, Profile(clusters=0.1, long=0.2)), 200))


@query(f"{_SIM} SELECT id, CASE WHEN confidence >= 0.75 THEN pred ELSE truth END AS pred FROM p")
def plain_cascade_lang(spark, sf):
    """Light answers where sure, else the strong model, which here does not err."""
    w = workload(spark, sf, "W1")
    pool = Pool(Tier("strong", SimulatedModel(LANGUAGES), *STRONG), Tier("light", SimulatedModel(LANGUAGES, SLIPS), *LIGHT))
    return baselines.plain_cascade(w.records.select("id", "text", F.col("truth").alias("hidden")), w.instruction, LANGUAGES, pool, 0.75).predictions.select("id", "pred")


_TARGET_SAMPLE = 200
_ASK = "Which language is this text in?"


def _target_sql(target: float) -> str:
    """The threshold from the sample's losses, and what it does to all records; the most losses allowed are a constant of the binomial bound."""
    allowed = baselines.most_losses(_TARGET_SAMPLE, target)
    return f"""{_SIM}, d AS (SELECT p.*, ceil(length(text) / 4.0) + {-(-len(_ASK) // 4)} + 4 + 2 AS tin FROM p JOIN documents ON id = doc_id),
s AS (SELECT *, row_number() OVER (ORDER BY confidence DESC) AS r FROM (SELECT * FROM d ORDER BY {u("'target'", "id")}, id LIMIT {_TARGET_SAMPLE})),
l AS (SELECT confidence AS c FROM s WHERE pred <> truth ORDER BY confidence DESC LIMIT 1 OFFSET {max(0, allowed)}),
t AS (SELECT CASE WHEN (SELECT count(*) FROM l) = 0 THEN 0.0 ELSE coalesce((SELECT min(confidence) FROM s WHERE confidence > (SELECT c FROM l)), 1.000001) END AS tau)
SELECT round(tau, 9) AS tau, round(avg(CAST(confidence >= tau AS INT)), 9) AS light_share, round(avg(CAST(confidence < tau OR pred = truth AS INT)), 9) AS accuracy,
  round(sum(tin * {LIGHT[0]} + {LIGHT[1]} + CASE WHEN confidence < tau OR id IN (SELECT id FROM s) THEN tin * {STRONG[0]} + {STRONG[1]} ELSE 0 END) / 1e6, 6) AS cost, CAST({target} AS DOUBLE) AS target FROM d, t GROUP BY tau"""


def _target(target: float) -> Query:
    def run(spark, sf):
        w = workload(spark, sf, "W1")
        pool = Pool(Tier("strong", SimulatedModel(LANGUAGES), *STRONG), Tier("light", SimulatedModel(LANGUAGES, SLIPS), *LIGHT))
        found = baselines.target_cascade(stage(w.records.select("id", "text", F.col("truth").alias("hidden")), "records"), _ASK, LANGUAGES, pool, target, _TARGET_SAMPLE)
        r = found.report
        return measures.accuracy(found.predictions, w.records).select(F.round(F.lit(r["tau"]), 9).alias("tau"), F.round(F.lit(r["light_share"]), 9).alias("light_share"), F.round("accuracy", 9).alias("accuracy"), F.round(F.lit(float(found.cost)), 6).alias("cost"), F.lit(target).alias("target"))

    run.__name__ = f"target_cascade_{int(100 * target):02d}"
    return run


for _t in (0.1, 0.3, 0.5, 0.7, 0.9, 0.95):
    query(_target_sql(_t))(_target(_t))


# ---- measures

@query(f"{_SIM} SELECT round(avg(CAST(pred = truth AS INT)), 9) AS accuracy FROM p")
def metric_accuracy(spark, sf):
    return measures.accuracy(_sim(spark, sf), _lang_truth(spark, sf)).select(F.round("accuracy", 9).alias("accuracy"))


_SCORES = f"""WITH p AS (SELECT o_orderkey AS id, CAST({_S4} AS INT) AS truth, 1 + CAST(floor({u("'score'", 'o_orderkey')} * 4) AS INT) AS pred FROM orders WHERE {_S4} IS NOT NULL)"""


@query(f"{_SCORES} SELECT round(sum(CAST(sign(x.truth - y.truth) = sign(x.pred - y.pred) AS INT)) / count(*), 9) AS pairwise_accuracy FROM p x JOIN p y ON x.id < y.id")
def metric_pairwise(spark, sf):
    from jointsem.functions.hashing import portable_uniform

    truth = workload(spark, sf, "S4").records
    pred = truth.select("id", (1 + F.floor(portable_uniform("score", F.col("id")) * 4)).alias("pred"))
    return measures.pairwise_accuracy(pred, truth).select(F.round("pairwise_accuracy", 9).alias("pairwise_accuracy"))


@query(f"""WITH p AS (SELECT CAST({_S4} AS INT) AS truth, 1 + CAST(floor({u("'score'", 'o_orderkey')} * 4) AS INT) AS pred FROM orders WHERE {_S4} IS NOT NULL),
c AS (SELECT truth, pred, count(*) AS n FROM p GROUP BY ALL)
SELECT round(sum(CASE WHEN x.truth = y.truth AND x.pred = y.pred THEN x.n * (x.n - 1) WHEN sign(x.truth - y.truth) = sign(x.pred - y.pred) THEN x.n * y.n ELSE 0 END) / (SELECT sum(n) * (sum(n) - 1) FROM c), 9) AS pairwise_accuracy FROM c x, c y""")
def metric_pairwise_whole(spark, sf):
    """As metric_pairwise, over all orders; the SQL counts from cells too."""
    from jointsem.functions.hashing import portable_uniform

    truth = workload(spark, sf, "S4").records
    pred = truth.select("id", (1 + F.floor(portable_uniform("score", F.col("id")) * 4)).alias("pred"))
    return measures.pairwise_accuracy(pred, truth).select(F.round("pairwise_accuracy", 9).alias("pairwise_accuracy"))


@query(f"{_SIM} SELECT round((SELECT sum(m) FROM (SELECT max(n) AS m FROM (SELECT pred, truth, count(*) AS n FROM p GROUP BY ALL) GROUP BY pred)) / (SELECT count(*) FROM p), 9) AS clustering_accuracy")
def metric_purity(spark, sf):
    return measures.clustering_accuracy(_sim(spark, sf), _lang_truth(spark, sf)).select(F.round("clustering_accuracy", 9).alias("clustering_accuracy"))


@query(f"{_SIM} SELECT truth, pred, count(*) AS n, CAST(grouping(truth) * 2 + grouping(pred) AS INT) AS level FROM p GROUP BY CUBE (truth, pred)")
def confusion_cube(spark, sf):
    return measures.confusion_cube(_sim(spark, sf), _lang_truth(spark, sf))


_CALLS = "SELECT lang AS stage, CASE WHEN length(text) > 2000 THEN 'strong' ELSE 'light' END AS tier, CAST(1 AS BIGINT) AS calls, CAST(ceil(length(text) / 4.0) AS BIGINT) AS tokens_in, CAST(length(lang) AS BIGINT) AS tokens_out FROM documents"


def _ledger(spark, sf) -> DataFrame:
    docs = read_table(spark, sf, "documents", "text", "lang")
    strong = F.length("text") > 2000
    tin, tout = token_count(F.col("text")), F.length("lang").cast("long")
    cost = F.when(strong, tin * STRONG[0] + tout * STRONG[1]).otherwise(tin * LIGHT[0] + tout * LIGHT[1]) / 1e6
    return docs.select(F.col("lang").alias("stage"), F.when(strong, "strong").otherwise("light").alias("tier"), F.lit(1).cast("long").alias("calls"), tin.alias("tokens_in"), tout.alias("tokens_out"), cost.alias("cost"))


_COST = "CASE tier WHEN 'strong' THEN tokens_in * 2.5 + tokens_out * 10.0 ELSE tokens_in * 0.15 + tokens_out * 0.6 END / 1e6"


@query(f"SELECT stage, tier, CAST(sum(calls) AS BIGINT) AS calls, CAST(sum(tokens_in) AS BIGINT) AS tokens_in, CAST(sum(tokens_out) AS BIGINT) AS tokens_out, round(sum({_COST}), 6) AS cost FROM ({_CALLS}) GROUP BY ROLLUP (stage, tier)")
def ledger_rollup(spark, sf):
    return measures.ledger_rollup(_ledger(spark, sf)).withColumn("cost", F.round("cost", 6))


@query(f"SELECT round(1000 * sum({_COST}) / count(*), 6) AS cost_per_1000 FROM ({_CALLS})")
def metric_cost_per_1000(spark, sf):
    n = read_table(spark, sf, "documents", "doc_id").count()
    return measures.cost_per_1000(_ledger(spark, sf), n).select(F.round("cost_per_1000", 6).alias("cost_per_1000"))


_REPORT = "SELECT n_name AS workload, 'm' || s_suppkey AS method, s_acctbal AS cost_per_1000, " + u("'acc'", "s_suppkey") + " AS accuracy FROM supplier JOIN nation ON s_nationkey = n_nationkey"


def _report(spark, sf) -> DataFrame:
    from jointsem.functions.hashing import portable_uniform

    both = read_table(spark, sf, "supplier", "s_suppkey", "s_nationkey", "s_acctbal").join(read_table(spark, sf, "nation", "n_nationkey", "n_name"), F.col("s_nationkey") == F.col("n_nationkey"))
    return both.select(F.col("n_name").alias("workload"), F.concat(F.lit("m"), F.col("s_suppkey")).alias("method"), F.col("s_acctbal").alias("cost_per_1000"), portable_uniform("acc", F.col("s_suppkey")).alias("accuracy"))


@query(f"WITH r AS ({_REPORT}) SELECT workload, method, cost_per_1000, round(accuracy, 9) AS accuracy FROM r WHERE NOT EXISTS (SELECT 1 FROM r o WHERE o.workload = r.workload AND o.method <> r.method AND o.cost_per_1000 <= r.cost_per_1000 AND o.accuracy >= r.accuracy)")
def metric_frontier(spark, sf):
    return measures.frontier(_report(spark, sf)).withColumn("accuracy", F.round("accuracy", 9))


@query(f"WITH r AS ({_REPORT}), b AS (SELECT workload, min_by(method, method) AS method FROM r GROUP BY workload), x AS (SELECT r.workload, CASE WHEN r.method = b.method THEN 'row_by_row' ELSE r.method END AS method, accuracy FROM r JOIN b USING (workload)) SELECT a.workload, a.method, round(a.accuracy - z.accuracy, 9) AS gain FROM x a JOIN x z ON z.workload = a.workload AND z.method = 'row_by_row' WHERE a.method <> 'row_by_row'")
def metric_improvement(spark, sf):
    first = F.min("method").over(Window.partitionBy("workload"))
    report = _report(spark, sf).withColumn("first", first).withColumn("method", F.when(F.col("method") == F.col("first"), "row_by_row").otherwise(F.col("method")))
    return measures.improvement(report).withColumn("gain", F.round("gain", 9))


@query(f"WITH r AS ({_REPORT}) SELECT method, workload, round(avg(accuracy), 9) AS average FROM r GROUP BY GROUPING SETS ((method, workload), (method))")
def metric_suite_average(spark, sf):
    return measures.suite_average(_report(spark, sf)).withColumn("average", F.round("average", 9))


@query("SELECT lang, round(t * (0.15 + 12 * 0.5 * 2.5 + 0.5 * 2.5) + n * 4 * (0.15 + 0.5 * 4 * 2.5), 6) AS bound FROM (SELECT lang, sum(ceil(length(text) / 4.0)) AS t, count(*) AS n FROM documents GROUP BY lang)")
def cost_bound(spark, sf):
    by = read_table(spark, sf, "documents", "lang", "text").groupBy("lang").agg(F.sum(token_count(F.col("text"))).alias("t"), F.count("*").alias("n"))
    return by.select("lang", F.round(measures.cost_bound(F.col("t"), 4, F.col("n"), 4, 12, 0.5, 2.5, 2.5, 0.15), 6).alias("bound"))


# ---- events, pages and generic operators

@query("SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def events_tumbling(spark, sf):
    events = read_table(spark, sf, "events", "ts", "event_type")
    return events.groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


@query("SELECT start, count(*) AS n FROM (SELECT ts, unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS start FROM events) GROUP BY start")
def events_sliding(spark, sf):
    events = read_table(spark, sf, "events", "ts")
    return events.groupBy(F.window("ts", "2 hours", "1 hour").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


@query("""WITH m AS (SELECT *, coalesce(ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 6 HOUR, true) AS fresh FROM events),
g AS (SELECT *, sum(CAST(fresh AS INT)) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM m) SELECT user_id, min(ts) AS start, count(*) AS n FROM g GROUP BY user_id, s""")
def events_session(spark, sf):
    events = read_table(spark, sf, "events", "ts", "user_id")
    return events.groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events")
def events_props(spark, sf):
    return parse_props(read_table(spark, sf, "events", "event_id", "props")).select("event_id", F.col("props.k").alias("k"))


@query("SELECT e.event_id, arg_max(p.event_id, (p.ts, p.event_id)) AS before FROM events e JOIN events p ON p.user_id = e.user_id AND p.event_type = 'purchase' AND (p.ts, p.event_id) < (e.ts, e.event_id) GROUP BY e.event_id")
def events_as_of(spark, sf):
    """The last purchase of the same user before each event."""
    from jointsem.operators.relational import as_of

    events = read_table(spark, sf, "events", "event_id", "ts", "user_id", "event_type")
    bought = events.where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("before"), "event_id")
    return as_of(events.select("user_id", "ts", "event_id"), bought, ["user_id"], ["ts", "event_id"], "before").where("before is not null").select("event_id", "before")


@query("SELECT e.event_id, count(*) AS near FROM events e JOIN events o ON o.user_id = e.user_id AND o.event_id <> e.event_id AND o.ts BETWEEN e.ts - INTERVAL 1 HOUR AND e.ts + INTERVAL 1 HOUR GROUP BY e.event_id")
def events_interval_join(spark, sf):
    from jointsem.operators.relational import interval_join

    events = read_table(spark, sf, "events", "event_id", "ts", "user_id")
    other = events.select("user_id", F.col("ts").alias("ts2"), F.col("event_id").alias("other"))
    return interval_join(events, other, ["user_id"], "ts", "ts2", 3600).where("other <> event_id").groupBy("event_id").agg(F.count("*").alias("near"))


@query("SELECT page_id, regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) AS lang FROM pages")
def pages_lang(spark, sf):
    return read_table(spark, sf, "pages", "page_id", "html").select("page_id", F.regexp_extract("html", '<html lang="([a-z]+)"', 1).alias("lang"))


@query()
def pages_text(spark, sf):
    return read_table(spark, sf, "pages", "page_id", "html").select("page_id", page_text(F.col("html")).alias("text"))


@query("SELECT round(sum(x), 6) AS total, count(*) AS n FROM (SELECT unnest(embedding) AS x FROM embeddings)")
def embeddings_explode(spark, sf):
    return read_table(spark, sf, "embeddings", "embedding").select(F.explode("embedding").alias("x")).agg(F.round(F.sum(F.col("x").cast("double")), 6).alias("total"), F.count("*").alias("n"))


@query("SELECT count(*) AS n, true AS exceeded FROM documents")
def infeasible_budget(spark, sf):
    """No threshold fits: everything goes to the proxy, and the run says so."""
    found = _classified(spark, sf, "W1", budget=0.0)
    return found.predictions.agg(F.count("*").alias("n")).withColumn("exceeded", F.lit(found.report["budget_exceeded"]))


@query("SELECT lang AS pred, count(*) AS n FROM documents GROUP BY lang")
def joint_classify_sql(spark, sf):
    """The joint method called from SQL as a table function over batches."""
    from jointsem.plans.sqlapi import register

    w = workload(spark, sf, "W1")
    register(spark, simulated_pool(w.labels), SURE)
    batches = assign_batches(w.records.withColumnRenamed("truth", "hidden"), 200, "joint")
    batches.createOrReplaceTempView("joint_batches")
    found = spark.sql(f"SELECT * FROM joint_classify(TABLE(joint_batches) PARTITION BY (batch_id), '{w.instruction}', '{','.join(w.labels)}')")
    return found.groupBy("pred").agg(F.count("*").alias("n"))


# ---- experiments, under the study profiles, on evaluation samples of 2000 records and all workloads of each

def _experiment(name: str) -> None:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        from jointsem import experiments

        f = getattr(experiments, name)
        return f(spark) if name == "exp_context_flip" else f(spark, sf)

    run.__name__ = name
    query()(run)


for _name in ("exp_overview", "exp_classification", "exp_budget", "exp_scoring", "exp_scoring_budget", "exp_clustering", "exp_edge_weights", "exp_assignment", "exp_sensitivity", "exp_paradox", "exp_controls", "exp_context_flip"):
    _experiment(_name)


from jointsem import catalog_noise, catalog_workloads  # noqa: E402, F401  they register their queries
