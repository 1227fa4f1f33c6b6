"""Five stages from raw documents to token ids: quality rules, near copies, repeated strings, benchmark passages, encoding.

Each stage takes (spark, docs, sf_dir) and works on all its predecessor kept.
All but the last return the columns of documents.  Columns besides doc_id, text
and n_chars pass through them, whatever their names.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from jointsem.llm import byte_dedup, contamination, pieces, quality, simhash
from jointsem.llm.store import spread, stage

#: The rows of run() cannot be had from SQL: XXH64 fingerprints and byte-pair merges have no counterpart there.
ORACLE_SQL = None
TOKENIZER = "piece_bpe_32k.model"
_OWN = ("doc_id", "text")


def _safe(docs: DataFrame) -> DataFrame:
    """docs with every column but doc_id and text under a name that no operator uses."""
    return docs.select(*[F.col(c) if c in _OWN else F.col(c).alias(f"_own{n}") for n, c in enumerate(docs.columns)])


def _back(found: DataFrame, docs: DataFrame) -> DataFrame:
    """The columns of docs under their names."""
    return found.select(*[F.col(c) if c in _OWN else F.col(f"_own{n}").alias(c) for n, c in enumerate(docs.columns)])


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules or the likelihood ratio reject go.

    A null or empty text has no words and goes; very long texts are judged whole.
    A null id never is a trusted one.  Repeated rows are judged each by itself.
    """
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "quality")
    return _back(quality.score(_safe(docs), labels).where("kept"), docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies the document with the least id stays; of rows that repeat its id and text, one.

    Null and empty texts are one group.  A row with a null id stays only if no
    member of its group has an id.
    """
    near = simhash.near_duplicates(docs)
    kept = near.where("doc_id <=> component_id").groupBy(F.col("doc_id").alias("_kept_id")).agg(F.count("*").alias("_rows"))
    left = _safe(docs).join(kept, F.col("doc_id").eqNullSafe(F.col("_kept_id")))
    # only rows whose id occurs again are compared
    again = left.where("_rows > 1").withColumns({"_h1": F.xxhash64("text"), "_h2": F.xxhash64(F.lit(1), "text")}).dropDuplicates(["doc_id", "_h1", "_h2"])
    return _back(left.where("_rows = 1").unionByName(again.drop("_h1", "_h2")), docs)


def substring_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Bytes that an earlier document holds go; a document goes if nothing of it is left.

    A null text becomes an empty one; empty texts stay.  A null id comes after all
    others.  n_chars, if docs has it, is counted anew where bytes went.
    """
    left = byte_dedup.dedup_bytes(_safe(docs), text_out=True).where("n_removed = 0 or text <> ''").select(*_safe(docs).columns, F.col("n_removed").alias("_gone"))
    if "n_chars" in docs.columns:
        own = f"_own{docs.columns.index('n_chars')}"
        left = left.withColumn(own, F.when(F.col("_gone") > 0, F.length("text").cast("long")).otherwise(F.col(own)))
    return _back(left, docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of which at least a twentieth is benchmark passages go.

    Null and empty texts are clean.  An empty benchmark leaves every document.
    """
    benchmark = spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    return _back(contamination.judged(contamination.hits(_safe(docs), benchmark, carry=True)).where("not contaminated"), docs)


def encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of ids and decoded text; null and empty texts have no ids, and the digests of nothing."""
    return pieces.round_trip(docs, public_tokenizers.path(TOKENIZER))


STAGES = [
    ("quality_rules", quality_rules),
    ("simhash_near_dedup", near_dedup),
    ("suffix_array_dedup", substring_dedup),
    ("benchmark_decontamination", decontamination),
    ("sentencepiece_encoding", encoding),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spread(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    for name, work in STAGES[:-1]:
        docs = stage(work(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
