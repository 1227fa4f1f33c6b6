"""Joint classification, scoring, clustering, filtering, joining and contextual maps.

Each task clusters and labels an initial sample, decides by its cost how the
rest is read, and returns predictions with a ledger of every call.  The plan is
staged: costs and thresholds are scalars the driver needs between jobs.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from jointsem.functions.expressions import as_records
from jointsem.models.base import Metered, Pool, Records
from jointsem.operators.sampling import assign_batches, sample_batch
from jointsem.plans.cascade import choose_proxy, choose_threshold, cost_of_threshold, full_joint_feasible, predicted_cost, route
from jointsem.plans.joint import label_batches, label_clusters, usage_rows
from jointsem.plans.params import Params
from jointsem.plans.proxies import proxy_scores
from jointsem.sources.stages import stage

LEDGER = "stage string, tier string, calls long, tokens_in long, tokens_out long, cost double"
_KEPT = ["id", "pred", "route", "confidence", "batch_id", "cluster_id"]


@dataclass
class Result:
    """predictions (id, pred, route, confidence, batch_id, cluster_id), ledger rows, and figures of the run."""

    predictions: DataFrame
    ledger_rows: list[tuple]
    report: dict

    @property
    def cost(self) -> float:
        return sum(r[5] for r in self.ledger_rows)

    @property
    def ledger(self) -> DataFrame:
        return self.predictions.sparkSession.createDataFrame(self.ledger_rows, LEDGER)


def _routed(labelled: DataFrame, name: str) -> DataFrame:
    return labelled.withColumn("route", F.lit(name)).select(*_KEPT)


def _counted(records: DataFrame) -> int:
    """The number of records; an id that is null or repeats would make joins on it multiply rows, and is an error."""
    each = records.groupBy("id").agg(F.count("*").alias("n"))
    n, most, nulls = each.agg(F.coalesce(F.sum("n"), F.lit(0)), F.max("n"), F.count(F.when(F.col("id").isNull(), 1))).first()
    if nulls or (most or 0) > 1:
        raise ValueError("ids must be unique and not null; stable_id() makes such ids")
    return n


def run_task(
    task: str,
    df: DataFrame,
    id_col: str,
    text_cols: list[str],
    instruction: str,
    pool: Pool,
    k: int | None = None,
    labels: list[str] | None = None,
    budget: float = math.inf,
    params: Params | None = None,
    hidden: str | None = None,
    force_route: str | None = None,
    where: Column | str | None = None,
) -> Result:
    """task: classify, score or cluster.  force_route: joint or proxy, whatever the budget.  hidden feeds the simulated model alone."""
    params = params or Params()
    if where is not None:
        df = df.where(where)
    k = len(labels) if labels else int(k or 0)
    if k < 1:
        raise ValueError("give labels or k")
    if task == "score" and not labels:
        labels = [str(s) for s in range(1, k + 1)]
    records = as_records(df, id_col, text_cols, hidden)
    n, size = _counted(records), params.batch_size(k)
    first = stage(sample_batch(records, size, params.seed, n=n).withColumn("batch_id", F.lit(-1).cast("long")), "sample")
    done = stage(label_batches(first, task, instruction, labels or [], k, pool, params), "first")
    ledger = usage_rows(done, "sample", pool)
    c0 = sum(r[5] for r in ledger)
    if task == "cluster" and not labels:
        labels = [r.pred for r in done.select("cluster_id", "pred").distinct().orderBy("cluster_id").collect()]
        labels += [f"empty {c}" for c in range(len(labels) + 1, k + 1)]
        if params.cluster_names == "matching":
            clustered = first.join(done.select("id", "cluster_id"), "id")
            done = stage(label_clusters(clustered, "classify", instruction, labels, k, pool, params), "first")
            ledger += usage_rows(done, "sample names", pool)
    report = {"n": n, "k": k, "batch": size, "c0": c0, "tau": None, "proxy": None, "budget_exceeded": False, "labels": labels}
    parts = [_routed(done, "sample")]
    rest_n = max(0, n - size)
    if rest_n:
        rest = records.join(F.broadcast(first.select("id")), "id", "left_anti")
        joint_task = "classify" if task == "cluster" else task
        left, left_n = rest, rest_n
        whole = force_route == "joint" or force_route is None and (math.isinf(budget) or full_joint_feasible(c0, n, size, budget))
        if not whole:
            strong, light = predicted_cost(rest, instruction, labels, [pool.strong, pool.light])
            name = choose_proxy(c0, strong, budget)
            scored, paid = proxy_scores(rest, instruction, labels, pool, name, params)
            c_proxy = sum(r[5] for r in paid)
            ledger += paid
            tau = 0.0 if force_route == "proxy" else choose_threshold(scored, size, c0, c_proxy, budget)
            if tau is None:
                if params.on_infeasible == "error":
                    raise ValueError("no threshold fits the budget")
                report["budget_exceeded"], tau = True, 0.0
            sure, unsure = route(scored, tau)
            blank = sure.select("id", "pred", F.lit("proxy").alias("route"), "confidence", F.lit(None).cast("long").alias("batch_id"), F.lit(None).cast("int").alias("cluster_id"))
            parts.append(blank)
            left = rest.join(unsure.select("id"), "id", "left_semi")
            left_n = unsure.count()
            report |= {"tau": tau, "proxy": name, "c_proxy": c_proxy, "planned_cost": cost_of_threshold(left_n, size, c0, c_proxy)}
        if left_n:
            batches = assign_batches(left, size, params.seed, n=left_n)
            labelled = stage(label_batches(batches, joint_task, instruction, labels, k, pool, params), "joint")
            ledger += usage_rows(labelled, "joint", pool)
            parts.append(_routed(labelled, "joint"))
            done = done.unionByName(labelled)
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    figures = done.where("rounds > 0").groupBy("batch_id").agg(F.max("rounds").alias("m")).agg(F.avg("m"), F.max("m")).first()
    joint_rows = done.count()
    report |= {"rounds": figures[0], "max_rounds": figures[1], "joint_fraction": joint_rows / n if n else 0.0, "cost": sum(r[5] for r in ledger)}
    return Result(out, ledger, report)


def classify(df: DataFrame, id_col: str, text_cols: list[str], instruction: str, labels: list[str], pool: Pool, **options) -> Result:
    return run_task("classify", df, id_col, text_cols, instruction, pool, labels=labels, **options)


def score(df: DataFrame, id_col: str, text_cols: list[str], instruction: str, k: int, pool: Pool, descriptions: list[str] | None = None, **options) -> Result:
    """Scores 1..k; descriptions, if given, name the levels from lowest to highest, and predictions are these names."""
    return run_task("score", df, id_col, text_cols, instruction, pool, k=k, labels=descriptions, **options)


def cluster(df: DataFrame, id_col: str, text_cols: list[str], instruction: str, k: int, pool: Pool, **options) -> Result:
    return run_task("cluster", df, id_col, text_cols, instruction, pool, k=k, **options)


def semantic_filter(df: DataFrame, id_col: str, text_cols: list[str], predicate: str, pool: Pool, yes: str = "yes", no: str = "no", **options) -> tuple[DataFrame, Result]:
    """Rows of df for which the predicate holds: classification into two classes, of which one is kept."""
    found = classify(df, id_col, text_cols, predicate, [yes, no], pool, **options)
    kept = found.predictions.where(F.col("pred") == yes).select(F.col("id").alias(id_col))
    return df.join(kept, id_col, "left_semi"), found


def semantic_filter_all(df: DataFrame, id_col: str, text_cols: list[str], predicates: list[str], pool: Pool, probe: int = 200, **options) -> tuple[DataFrame, list[Result]]:
    """A conjunction: each predicate is asked only of the rows that passed those before.

    A sample is asked all of them first; what rejects most for its price comes first.  Probes cost what they cost, and their results come first.
    """
    sample = stage(sample_batch(df.withColumnRenamed(id_col, "id"), probe, "probe").withColumnRenamed("id", id_col), "probe")
    n = max(1, sample.count())
    results, rank = [], []
    for place, p in enumerate(predicates):
        kept, found = semantic_filter(sample, id_col, text_cols, p, pool, **options)
        results.append(found)
        rank.append((found.cost / n / max(1e-9, 1 - kept.count() / n), place, p))
    for _, _, p in sorted(rank):
        df, found = semantic_filter(df, id_col, text_cols, p, pool, **options)
        df = stage(df, "filtered")
        results.append(found)
    return df, results


def semantic_where(df: DataFrame, id_col: str, text_cols: list[str], condition, pool: Pool, **options) -> tuple[DataFrame, list[Result]]:
    """Rows that meet a condition: a predicate, ("not", c), ("and", c, ...) or ("or", c, ...).

    What is decided is not asked again: later parts of "and" see the rows that passed, those of "or" the rows that did not.
    """
    if isinstance(condition, str):
        kept, found = semantic_filter(df, id_col, text_cols, condition, pool, **options)
        return kept, [found]
    kind, *parts = condition
    if kind == "not":
        kept, found = semantic_where(df, id_col, text_cols, parts[0], pool, **options)
        return df.join(kept.select(id_col), id_col, "left_anti"), found
    if kind not in ("and", "or"):
        raise ValueError(f"no such condition: {kind}")
    results, left, passed = [], df, None
    for c in parts:
        kept, found = semantic_where(left, id_col, text_cols, c, pool, **options)
        results += found
        kept = stage(kept, "kept")
        if kind == "and":
            left = kept
        else:
            passed = kept if passed is None else passed.unionByName(kept)
            left = stage(left.join(kept.select(id_col), id_col, "left_anti"), "left")
    return (left if kind == "and" else passed), results


def word_runs(df: DataFrame, name: str, length: int) -> DataFrame:
    """(id, text) -> (name, gram): hashes of the distinct runs of `length` words; a shorter text is one run."""
    words = F.filter(F.split(F.lower("text"), r"[^\p{L}\p{N}]+"), lambda w: w != "")
    at = F.sequence(F.lit(1), F.size("words") - (length - 1))
    joined = lambda part: F.xxhash64(F.array_join(part, " "))
    grams = F.when(F.size("words") >= length, F.array_distinct(F.transform(at, lambda i: joined(F.slice("words", i, length))))).otherwise(F.array(joined(F.col("words"))))
    return df.select(F.col("id").alias(name), words.alias("words")).select(name, F.explode(grams).alias("gram"))


def candidate_pairs(left: DataFrame, right: DataFrame, shingle: int = 8, split: int = 100_000) -> DataFrame:
    """(left_id, right_id) of texts that share a run of `shingle` words; left and right are (id, text).

    Runs are counted on both sides first.  Those that only one side holds go no
    further, and one that would make over `split` pairs is cut into parts: each
    left holder goes to one of them, and the right ones to all, so no task gets a
    frequent run as a whole.  Pairs are distinct before they are rendered.
    """
    l, r = stage(word_runs(left, "left_id", shingle), "runs"), stage(word_runs(right, "right_id", shingle), "runs")
    both = l.groupBy("gram").agg(F.count("*").alias("n")).join(r.groupBy("gram").agg(F.count("*").alias("m")), "gram")
    parts = stage(both.select("gram", F.greatest(F.lit(1), F.least(F.ceil(F.col("n") * F.col("m") / split), F.col("n"))).cast("int").alias("parts")), "counts")
    dealt = l.join(parts, "gram").select("left_id", "gram", F.pmod(F.xxhash64("left_id"), F.col("parts")).cast("int").alias("part"))
    copies = r.join(parts, "gram").select("right_id", "gram", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"))
    return dealt.join(copies, ["gram", "part"]).select("left_id", "right_id").distinct()


def blocking_recall(candidates: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: true pairs, how many of them are candidates, how many candidates there are, and the share found (1 if nothing is true)."""
    hit = truth.select("left_id", "right_id").join(candidates.withColumn("_hit", F.lit(1)), ["left_id", "right_id"], "left")
    counted = hit.agg(F.count("*").alias("n_true"), F.count("_hit").alias("n_found")).join(F.broadcast(candidates.agg(F.count("*").alias("n_candidates"))))
    return counted.withColumn("recall", F.when(F.col("n_true") > 0, F.col("n_found") / F.col("n_true")).otherwise(1.0))


def semantic_join(left: DataFrame, right: DataFrame, predicate: str, pool: Pool, block: int | None = 8, cross_limit: int = 1_000_000, **options) -> tuple[DataFrame, Result]:
    """(left_id, right_id) pairs for which the predicate holds.  Pairs are blocked by shared runs of words; all pairs only below cross_limit."""
    if block:
        pairs = candidate_pairs(left, right, block)
    else:
        if left.count() * right.count() > cross_limit:
            raise ValueError("too many pairs for a join without blocking")
        pairs = left.select(F.col("id").alias("left_id")).join(F.broadcast(right.select(F.col("id").alias("right_id"))))
    both = pairs.join(left.select(F.col("id").alias("left_id"), F.col("text").alias("l")), "left_id").join(right.select(F.col("id").alias("right_id"), F.col("text").alias("r")), "right_id")
    rows = stage(both.select("left_id", "right_id", F.xxhash64("left_id", "right_id").alias("pair"), F.concat_ws(" ⟂ ", "l", "r").alias("both"), *[c for c in (options.get("hidden"),) if c and c in both.columns]), "pairs")
    kept, found = semantic_filter(rows, "pair", ["both"], predicate, pool, **options)
    return kept.select("left_id", "right_id"), found


def _in_context(labelled: DataFrame, records: DataFrame, n_context: int, answer, schema: str) -> DataFrame:
    """answer(every, near) for each record, with the members nearest in id order of its cluster; (id, ...) rows.

    labelled is (id, batch_id, cluster_id), records (id, text[, hidden]).
    """
    both = records.join(labelled.where("cluster_id is not null").select("id", "batch_id", "cluster_id"), "id")
    columns = [c.split()[0] for c in schema.split(", ")]

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("id")
        hidden = pdf["hidden"].where(pdf["hidden"].notna(), None).tolist() if "hidden" in pdf else []
        every = Records(pdf["id"].astype(int).tolist(), pdf["text"].fillna("").tolist(), hidden)
        rows = []
        for r in range(len(every)):
            near = [(r + s) % len(every) for s in range(min(len(every), n_context + 1))]
            rows.append((every.ids[r], *answer(every.take(near))))
        return pd.DataFrame(rows, columns=columns)

    return both.groupBy("batch_id", "cluster_id").applyInPandas(work, schema)


def contextual_map(labelled: DataFrame, records: DataFrame, instruction: str, pool: Pool, tier: str = "strong", n_context: int = 3) -> DataFrame:
    """(id, answer): an open-ended answer per record, asked with neighbours of its cluster as context."""
    one = pool.tier(tier)
    return _in_context(labelled, records, n_context, lambda near: (Metered(one).summarize(instruction, near),), "id long, answer string")


def contextual_extract(labelled: DataFrame, records: DataFrame, instruction: str, fields: dict[str, str], pool: Pool, tier: str = "strong", n_context: int = 3) -> DataFrame:
    """(id, a column for each field): values found in each record, asked with neighbours of its cluster as context; fields gives each name its meaning (a pattern, for the lexical model)."""
    one = pool.tier(tier)

    def answer(near: Records) -> tuple:
        found = Metered(one).extract(instruction, fields, near)
        return tuple(found.get(n, "") for n in fields)

    return _in_context(labelled, records, n_context, answer, "id long, " + ", ".join(f"{n} string" for n in fields))


def explain_cost(n: int, k: int, c0: float, row_cost: float, budget: float, params: Params | None = None) -> Iterator[str]:
    """What a plan of these sizes would do, before anything is paid for."""
    size = (params or Params()).batch_size(k)
    batches = math.ceil(n / size)
    yield f"{batches} batches of {size}; all joint: {c0 * batches:.6f}; all row-wise: {c0 + row_cost:.6f}; budget: {budget:.6f}"
    yield "all joint" if full_joint_feasible(c0, n, size, budget) else f"cascade, {choose_proxy(c0, row_cost, budget)} proxy"
