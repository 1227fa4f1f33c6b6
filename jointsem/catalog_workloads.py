"""Each workload read row by row by a model that errs, with SQL that derives the workload and repeats the draws; and what runs cost and keep to."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from jointsem.catalog import SLIPS, SURE, query, simulated_pool
from jointsem.functions import measures
from jointsem.functions.hashing import uniform_sql as u
from jointsem.models.base import Pool, Records, Tier
from jointsem.models.endpoint import CallableModel
from jointsem.models.lexical import LexicalModel
from jointsem.models.simulated import Profile
from jointsem.plans import baselines, cascade, tasks
from jointsem.sources.stages import shared_folder, stage
from jointsem.sources.tables import ResponseCache
from jointsem.workloads import workload

# Truth of each workload, from the tables alone.
TRUTH = {
    "W2": "SELECT p_partkey AS id, p_type || '/' || CAST(least(6, ceil(p_size / 8.5)) AS BIGINT) AS truth FROM part",
    "W3": "SELECT event_id AS id, event_type || '-' || CASE WHEN value >= 50 THEN 'high' ELSE 'low' END AS truth FROM events",
    "W5": "SELECT p_partkey AS id, p_brand AS truth FROM part",
    "W6": "SELECT conv_id * 100000 + turn AS id, role AS truth FROM conversations",
    "W7": "SELECT p_partkey AS id, split_part(p_name, ' ', 1) AS truth FROM part",
    "W8": "SELECT p_partkey AS id, p_type || ' ' || split_part(p_name, ' ', 2) AS truth FROM part",
    "W9": "SELECT c_custkey AS id, n_name AS truth FROM customer JOIN nation ON c_nationkey = n_nationkey",
    "W10": "SELECT p_partkey AS id, p_name AS truth FROM part",
    "W13": "SELECT page_id AS id, regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) AS truth FROM pages",
    "W14": "SELECT doc_id AS id, source AS truth FROM documents",
    "W15": "SELECT vec_id AS id, CAST(label AS VARCHAR) AS truth FROM embeddings",
    "S1": "SELECT o_orderkey AS id, CAST(ntile(6) OVER (ORDER BY o_totalprice, o_orderkey) AS VARCHAR) AS truth FROM orders",
    "S2": "SELECT doc_id AS id, CAST(ntile(4) OVER (ORDER BY n_chars, doc_id) AS VARCHAR) AS truth FROM documents",
    "S3": "SELECT doc_id AS id, CAST(CASE WHEN toxic = 1 THEN 1 ELSE quality + 2 END AS VARCHAR) AS truth FROM documents JOIN labels USING (doc_id)",
}


def _read_sql(truth: str) -> str:
    """Truth and the answers of the erring model; labels are the sorted values of the truth."""
    other = lambda draw: f"ls[(list_position(ls, truth) - 1 + CASE WHEN {draw} < 0.8 THEN 1 ELSE 1 + CAST(floor(({draw} - 0.8) * 5 * (len(ls) - 1)) AS INT) END) % len(ls) + 1]"
    return f"""WITH t AS ({truth}), l AS (SELECT list(DISTINCT truth ORDER BY truth) AS ls FROM t)
SELECT id, truth, CASE WHEN {u("'sim'", "'ambiguous'", "id")} < {SLIPS.ambiguous} THEN {other("0.0")} WHEN {u("'sim'", "'row'", "id")} < {SLIPS.row} THEN {other(u("'sim'", "'other'", "id"))} ELSE truth END AS pred FROM t, l"""


def _read(name: str):
    def run(spark, sf) -> DataFrame:
        w = workload(spark, sf, name)
        records = stage(w.records, name)
        found = baselines.row_by_row(records.withColumnRenamed("truth", "hidden"), w.instruction, w.labels, simulated_pool(w.labels, SLIPS))
        return records.select("id", "truth").join(found.predictions.select("id", "pred"), "id")

    run.__name__ = f"workload_{name.lower()}"
    return run


for _name, _truth in TRUTH.items():
    query(_read_sql(_truth))(_read(_name))


@query(f"SELECT round(avg(CAST(pred = truth AS INT)), 9) AS accuracy FROM ({_read_sql(TRUTH['W9'])})")
def row_by_row_nations(spark, sf):
    """Accuracy of the erring model on the customers' nations."""
    w = workload(spark, sf, "W9")
    found = baselines.row_by_row(w.records.withColumnRenamed("truth", "hidden"), w.instruction, w.labels, simulated_pool(w.labels, SLIPS))
    return measures.accuracy(found.predictions, w.records).select(F.round("accuracy", 9).alias("accuracy"))


# ---- proxies before the joint method, forced, so that all but the first batch is theirs

_LANGS = "['de', 'en', 'es', 'fr']"


def _languages_sql(seed: str) -> str:
    """(id, truth, pred, confidence) of a model that errs on languages."""
    other = lambda draw: f"{_LANGS}[(list_position({_LANGS}, lang) - 1 + CASE WHEN {draw} < 0.8 THEN 1 ELSE 1 + CAST(floor(({draw} - 0.8) * 5 * 3) AS INT) END) % 4 + 1]"
    ambiguous, wrong = f"{u("'sim'", "'ambiguous'", 'doc_id')} < {SLIPS.ambiguous}", f"{u(seed, "'row'", 'doc_id')} < {SLIPS.row}"
    sure = u(seed, "'confidence'", "doc_id")
    return f"""SELECT doc_id AS id, lang AS truth, CASE WHEN {ambiguous} THEN {other("0.0")} WHEN {wrong} THEN {other(u(seed, "'other'", "doc_id"))} ELSE lang END AS pred,
  CASE WHEN {ambiguous} OR {wrong} THEN 0.2 + 0.6 * {sure} ELSE 0.6 + 0.4 * {sure} END AS confidence FROM documents"""


def _forced(pred: str, seed: str) -> str:
    return f"SELECT id, CASE WHEN id IN (SELECT doc_id FROM documents ORDER BY {u("'joint'", 'doc_id')}, doc_id LIMIT 200) THEN truth ELSE {pred} END AS pred FROM ({_languages_sql(seed)})"


def _through(spark, sf, proxy: str, strong: Profile) -> DataFrame:
    w = workload(spark, sf, "W1")
    found = tasks.classify(w.records, "id", ["text"], w.instruction, w.labels, simulated_pool(w.labels, strong, SLIPS), params=SURE.but(proxy=proxy), hidden="truth", force_route="proxy")
    return found.predictions.select("id", "pred")


@query(_forced("CASE WHEN confidence >= 0.7 THEN pred ELSE truth END", "'simlight'"))
def cascade_ladder(spark, sf):
    """Light, then strong, then joint: the strong model, which does not err here, reads what the light one is unsure of."""
    return _through(spark, sf, "ladder", Profile())


@query(_forced("pred", "'sim'"))
def cascade_batch_proxy(spark, sf):
    """Batch prompts as the proxy."""
    return _through(spark, sf, "batch", SLIPS)


@query(_forced("pred", "'sim'"))
def cascade_rubric_proxy(spark, sf):
    """Rows with a rubric as the proxy."""
    return _through(spark, sf, "rubric", SLIPS)


@query("SELECT 'all joint' AS run, CAST(1.0 AS DOUBLE) AS joint_fraction UNION ALL SELECT 'forced proxy', round(least(200, count(*)) / count(*), 9) FROM documents")
def joint_fraction(spark, sf):
    w = workload(spark, sf, "W1")
    rows = []
    for name, options in (("all joint", {}), ("forced proxy", {"force_route": "proxy"})):
        found = tasks.classify(w.records, "id", ["text"], w.instruction, w.labels, simulated_pool(w.labels), params=SURE, hidden="truth", **options)
        rows.append((name, round(float(found.report["joint_fraction"]), 9)))
    return spark.createDataFrame(rows, "run string, joint_fraction double")


@query("SELECT CAST(s AS DOUBLE) AS share, true AS planned_within, (SELECT count(*) FROM documents) AS predicted FROM (SELECT unnest([0.5, 0.8]) AS s)")
def budget_adherence(spark, sf):
    """Budgets as shares of the all-joint cost: the planned cost keeps them (or the run says that nothing can), and every record is predicted."""
    w = workload(spark, sf, "W1")
    run = lambda **options: tasks.classify(w.records, "id", ["text"], w.instruction, w.labels, simulated_pool(w.labels, SLIPS), hidden="truth", **options)
    whole, rows = run().cost, []
    for share in (0.5, 0.8):
        found = run(budget=share * whole)
        said = measures.budget_report(found.report, share * whole)
        rows.append((share, bool(found.report["budget_exceeded"] or said["planned"] is None or said["planned"] <= share * whole + 1e-9), found.predictions.count()))
    return spark.createDataFrame(rows, "share double, planned_within boolean, predicted long")


# ---- models behind a function, answers kept, extraction

def _reply(prompt: str) -> tuple[str, float]:
    """A stand-in for a service: it answers the last paragraphs of a prompt by the words in them."""
    from jointsem.workloads import language_spec

    labels = ["de", "en", "es", "fr"]
    return LexicalModel(language_spec()).classify("", labels, Records([0], [prompt.split("\n\n", 1)[1]]))


def _language_rows_sql() -> str:
    from jointsem.catalog import _LANG_BEST

    return f"SELECT doc_id AS id, {_LANG_BEST} AS pred FROM documents"


@query(_language_rows_sql())
def endpoint_rows(spark, sf):
    """A model behind a user's function, several calls at a time."""
    w = workload(spark, sf, "W1")
    model = CallableModel(_reply)
    pool = Pool(Tier("strong", model, 2.5, 10.0), Tier("light", model, 0.15, 0.6))
    return baselines.row_by_row(w.records.select("id", "text"), w.instruction, w.labels, pool).predictions.select("id", "pred")


@query("""SELECT 'en' AS asked, (SELECT count(DISTINCT text) FROM documents WHERE lang = 'en') AS calls, (SELECT count(*) FROM documents WHERE lang = 'en') AS answers
UNION ALL SELECT 'all', (SELECT count(DISTINCT text) FROM documents WHERE text NOT IN (SELECT text FROM documents WHERE lang = 'en')), (SELECT count(*) FROM documents)""")
def cached_rows(spark, sf):
    """Texts asked about before cost nothing: first the English ones are asked, then all."""
    import uuid

    w = workload(spark, sf, "W1")
    cache = ResponseCache(spark, f"{shared_folder(spark)}/answers-{uuid.uuid4().hex}", "pred string, confidence double")
    tier, rows = Tier("light", w.lexical(), 0.15, 0.6), []
    for name, part in (("en", w.records.where("truth = 'en'")), ("all", w.records)):
        found = stage(cascade.row_wise(part.select("id", "text"), w.instruction, w.labels, tier, cache=cache), "cached")
        r = found.agg(F.count(F.when(F.col("tokens_in") > 0, 1)).alias("calls"), F.count("pred").alias("answers")).first()
        rows.append((name, r.calls, r.answers))
    return spark.createDataFrame(rows, "asked string, calls long, answers long")


@query("SELECT p_partkey AS id, split_part(p_name, ' ', 1) AS quality, split_part(p_name, ' ', 2) AS product FROM part")
def contextual_fields(spark, sf):
    """Fields of each part, asked with others of its group as context."""
    w = workload(spark, sf, "W4")
    records = stage(w.records.withColumnRenamed("truth", "hidden"), "records")
    found = tasks.classify(records, "id", ["text"], w.instruction, w.labels, simulated_pool(w.labels), hidden="hidden", params=SURE)
    model = LexicalModel({})
    pool = Pool(Tier("strong", model, 2.5, 10.0), Tier("light", model, 0.15, 0.6))
    return tasks.contextual_extract(found.predictions, records.select("id", "text"), "Describe it.", {"quality": r"^\w+", "product": r"\w+$"}, pool)
