"""The experiment workloads on the given tables: records with texts, truth, an instruction and labels."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from jointsem.functions.expressions import page_text
from jointsem.models.lexical import LexicalModel
from jointsem.sources.tables import read_table

# Frequent words of four languages, insults, and the values that the tables use.
LANGUAGE_WORDS = {
    "de": "der die und den das mit sich des auf für ist im dem nicht ein eine als auch von zu",
    "en": "the of and to in that is was for on are with as his they be at by this have",
    "es": "de la que el en y a los se del las un por con no una su para es al",
    "fr": "le les et des en un une du dans qui par pour au sur pas plus ce sont la de",
}
INSULTS = ["trash", "scum", "clown", "idiot", "worthless", "moron", "pathetic", "loser", "disgusting", "stupid"]
ADJECTIVES = ["blue", "cold", "hot", "large", "new", "old", "red", "small"]
NOUNS = ["anvil", "bolt", "gear", "gizmo", "plate", "ring", "rod", "widget"]
PRIORITIES = {"5-LOW": 1, "3-MEDIUM": 2, "2-HIGH": 3, "1-URGENT": 4}


def language_spec() -> dict[str, str]:
    return {lang: " (?:" + "|".join(words.split()) + ") " for lang, words in LANGUAGE_WORDS.items()}


def toxic_spec() -> dict[str, str]:
    return {"1": "|".join(INSULTS), "0": "^$"}


def quality_spec() -> dict[str, str]:
    return {"0": "!!|[#$%&*]{3}| [|] ", "1": "^$"}


@dataclass
class Workload:
    """records (id, text, truth); kind is class or score."""

    name: str
    records: DataFrame
    instruction: str
    labels: list[str]
    kind: str = "class"

    @property
    def k(self) -> int:
        return len(self.labels)

    def lexical(self) -> LexicalModel:
        spec = {"W1": language_spec, "W13": language_spec, "W11": quality_spec, "W12": toxic_spec}.get(self.name)
        return LexicalModel(spec() if spec else {n: n.lower() for n in self.labels})


def _card(*columns: str) -> Column:
    return F.concat_ws(" ", *[F.col(c).cast("string") for c in columns])


def _made(name: str, df: DataFrame, key: str, text: Column, truth: Column, instruction: str, kind: str = "class", labels: list[str] | None = None) -> Workload:
    records = df.select(F.col(key).cast("long").alias("id"), text.alias("text"), truth.cast("string").alias("truth")).where("truth is not null")
    if labels is None:
        labels = [r.truth for r in records.select("truth").distinct().orderBy("truth").collect()]
    return Workload(name, records, instruction, labels, kind)


def _ntile(k: int, column: str, key: str) -> Column:
    return F.ntile(k).over(Window.orderBy(column, key))


def workload(spark: SparkSession, sf_dir: str, name: str) -> Workload:
    """W1-W13 classes, W14-W15 controls without signal, S1-S5 scores.

    The bands of S1, S2 and S5 are quantiles, so their truth needs one total
    order; they are evaluation sets and are only built for measuring.
    """
    t = lambda table, *columns: read_table(spark, sf_dir, table, *columns)
    word = lambda n: F.split("p_name", " ")[n]
    part = lambda: t("part", "p_partkey", "p_name", "p_brand", "p_type", "p_size")
    card = _card("p_name", "p_type", "p_size")
    if name == "W1":
        return _made(name, t("documents", "doc_id", "text", "lang"), "doc_id", F.col("text"), F.col("lang"), "Which language is this text in?")
    if name == "W2":
        band = F.least(F.lit(6), F.ceil(F.col("p_size") / 8.5))
        return _made(name, part(), "p_partkey", card, F.concat_ws("/", "p_type", band), "Which catalogue shelf does the item go on?")
    if name == "W3":
        half = F.when(F.col("value") >= 50, "high").otherwise("low")
        return _made(name, t("events", "event_id", "event_type", "value"), "event_id", _card("event_type", "value"), F.concat_ws("-", "event_type", half), "What kind of action was this?")
    if name == "W4":
        return _made(name, part(), "p_partkey", F.col("p_name"), word(1), "What product is it?")
    if name == "W5":
        return _made(name, part(), "p_partkey", _card("p_name", "p_brand", "p_type"), F.col("p_brand"), "Which maker?")
    if name == "W6":
        talk = t("conversations").withColumn("key", F.col("conv_id") * 100_000 + F.col("turn"))
        return _made(name, talk, "key", F.concat_ws(": ", F.col("turn").cast("string"), "text"), F.col("role"), "Who is speaking?")
    if name == "W7":
        return _made(name, part(), "p_partkey", F.col("p_name"), word(0), "Which quality describes it?")
    if name == "W8":
        return _made(name, part(), "p_partkey", card, F.concat_ws(" ", F.col("p_type"), word(1)), "Which product line?")
    if name == "W9":
        both = t("customer", "c_custkey", "c_name", "c_nationkey", "c_mktsegment").join(F.broadcast(t("nation", "n_nationkey", "n_name")), F.col("c_nationkey") == F.col("n_nationkey"))
        return _made(name, both, "c_custkey", _card("c_name", "n_name", "c_mktsegment"), F.col("n_name"), "Where does the customer live?")
    if name == "W10":
        return _made(name, part(), "p_partkey", F.col("p_name"), F.col("p_name"), "Which exact variant?")
    if name in ("W11", "W12"):
        column = "quality" if name == "W11" else "toxic"
        both = t("documents", "doc_id", "text").join(t("labels", "doc_id", column), "doc_id")
        return _made(name, both, "doc_id", F.col("text"), F.col(column), "Is it well written?" if name == "W11" else "Is it abusive?", labels=["0", "1"])
    if name == "W13":
        return _made(name, t("pages", "page_id", "html"), "page_id", page_text(F.col("html")), F.regexp_extract("html", '<html lang="([a-z]+)"', 1), "Which language?")
    if name == "W14":
        return _made(name, t("documents", "doc_id", "text", "source"), "doc_id", F.col("text"), F.col("source"), "Where is it from?")
    if name == "W15":
        return _made(name, t("embeddings", "vec_id", "label"), "vec_id", F.lit(""), F.col("label"), "Which group?")
    if name == "S1":
        return _made(name, t("orders", "o_orderkey", "o_totalprice"), "o_orderkey", _card("o_totalprice"), _ntile(6, "o_totalprice", "o_orderkey"), "How large is the order?", "score")
    if name == "S2":
        return _made(name, t("documents", "doc_id", "text", "n_chars"), "doc_id", F.col("text"), _ntile(4, "n_chars", "doc_id"), "Grade by length.", "score")
    if name == "S3":
        both = t("documents", "doc_id", "text").join(t("labels"), "doc_id")
        level = F.when(F.col("toxic") == 1, 1).otherwise(F.col("quality") + 2)
        return _made(name, both, "doc_id", F.col("text"), level, "How acceptable?", "score", ["1", "2", "3"])
    if name == "S4":
        level = F.coalesce(*[F.when(F.col("o_orderpriority") == p, s) for p, s in PRIORITIES.items()])
        return _made(name, t("orders", "o_orderkey", "o_orderpriority", "o_orderdate"), "o_orderkey", _card("o_orderpriority", "o_orderdate"), level, "How urgent?", "score", ["1", "2", "3", "4"])
    if name == "S5":
        return _made(name, t("events", "event_id", "event_type", "value"), "event_id", _card("value", "event_type"), _ntile(5, "value", "event_id"), "How strong?", "score")
    raise KeyError(name)


def join_workload(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """J1: documents and benchmark passages as (id, text)."""
    docs = read_table(spark, sf_dir, "documents", "doc_id", "text").select(F.col("doc_id").alias("id"), "text")
    return docs, read_table(spark, sf_dir, "benchmark").select(F.col("item_id").alias("id"), "text")
