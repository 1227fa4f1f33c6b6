"""The thin queries of this package: one per operator, over its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from jointsem.llm.store import spread


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    df = df.select(*columns) if columns else df
    return spread(df) if name in ("documents", "pages") else df


def op1_log_frequency_bloom(spark: SparkSession, sf_dir: str) -> DataFrame:
    from jointsem.llm.language_model import score

    return score(table(spark, sf_dir, "documents", "doc_id", "text"))


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from jointsem.llm.toxicity import score_documents

    return score_documents(table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "labels", "doc_id", "toxic"))


def op3_winnowing_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from jointsem.llm.contamination import hits, judged

    found = judged(hits(table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "benchmark")))
    return found.select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")


def op4_recompression_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from jointsem.llm.word_dedup import dedup_words

    return dedup_words(table(spark, sf_dir, "documents", "doc_id", "text"))


def op5_suffix_array_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from jointsem.llm.byte_dedup import dedup_bytes

    return dedup_bytes(table(spark, sf_dir, "documents", "doc_id", "text"))


def op6_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    from jointsem.llm.store import new_folder
    from jointsem.llm.warc import read_archives, write_archives

    folder = new_folder(spark, "archives")
    write_archives(table(spark, sf_dir, "pages", "page_id", "url", "html"), folder)
    found = read_archives(spark, folder).where("type is not null")
    return found.select("page_id", "payload_bytes", "payload_digest", F.col("type").alias("record_type"), "refers_to")


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from jointsem.llm.quality import score

    found = score(table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "labels", "doc_id", "quality"))
    return found.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", F.round("llr", 9).alias("llr"))


def op8_site_templates(spark: SparkSession, sf_dir: str) -> DataFrame:
    from jointsem.llm.html_text import main_texts

    return main_texts(table(spark, sf_dir, "pages", "page_id", "url", "html"))


def op9_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from jointsem.llm.pieces import round_trip

    return round_trip(table(spark, sf_dir, "documents", "doc_id", "text"), public_tokenizers.path("piece_bpe_32k.model"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def op10_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from jointsem.llm.simhash import near_duplicates

    found = near_duplicates(table(spark, sf_dir, "documents", "doc_id", "text"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_log_frequency_bloom, op2_toxicity, op3_winnowing_decontamination, op4_recompression_dedup, op5_suffix_array_dedup, op6_warc, op7_quality_rules, op8_site_templates, op9_sentencepiece, op10_simhash_near_dedup, pipeline)}


#: The scores, hashes and merges of the other queries have no counterpart in SQL; tests hold them against brute force.
#: That of op8 reads the article of the pages as they are generated.
ORACLES = {
    "op3_winnowing_decontamination": r"""
WITH d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
bw AS (SELECT DISTINCT item_id, n, array_to_string(w[p:p + n - 1], ' ') AS g FROM (SELECT item_id, w, least(13, len(w)) AS n, unnest(range(1, len(w) - least(13, len(w)) + 2)) AS p FROM b WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT n FROM bw),
dw AS (SELECT doc_id, n, p, array_to_string(w[p:p + n - 1], ' ') AS g FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS p FROM d, sizes WHERE len(w) >= n)),
hit AS (SELECT doc_id, dw.n, p, item_id FROM dw JOIN bw ON dw.n = bw.n AND dw.g = bw.g),
covered AS (SELECT doc_id, count(DISTINCT k) AS n_hit FROM (SELECT doc_id, unnest(range(p, p + n)) AS k FROM (SELECT DISTINCT doc_id, n, p FROM hit)) GROUP BY doc_id),
found AS (SELECT doc_id, count(*) AS n_items, string_agg(i, ',' ORDER BY i) AS items FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS i FROM hit) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM d LEFT JOIN covered USING (doc_id) LEFT JOIN found USING (doc_id)
""",
    "op4_recompression_dedup": r"""
WITH d AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
win AS (SELECT doc_id, p, md5(array_to_string(w[p:p + 34], ' ')) AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 33)) AS p FROM d WHERE len(w) >= 35)),
dup AS (SELECT doc_id, p FROM (SELECT *, count(*) OVER (PARTITION BY g) AS c FROM win) WHERE c > 1),
gone AS (SELECT DISTINCT doc_id, unnest(range(p, p + 35)) AS k FROM dup),
lost AS (SELECT doc_id, list(k) AS ks FROM gone GROUP BY doc_id)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(len(ks), 0) AS BIGINT) AS n_removed,
  sha256(coalesce((SELECT string_agg(w[i], ' ' ORDER BY i) FROM (SELECT unnest(range(1, len(w) + 1)) AS i) WHERE ks IS NULL OR NOT list_contains(ks, i)), '')) AS kept_sha256
FROM d LEFT JOIN lost USING (doc_id)
""",
    "op6_warc": """
WITH p AS (SELECT page_id, strlen(coalesce(html, '')) AS n, sha256(coalesce(html, '')) AS digest FROM pages),
f AS (SELECT *, min(page_id) OVER (PARTITION BY digest) AS first FROM p)
SELECT page_id, n AS payload_bytes, digest AS payload_digest, CASE WHEN n >= 100 AND page_id > first THEN 'revisit' ELSE 'response' END AS record_type, CASE WHEN n >= 100 AND page_id > first THEN first END AS refers_to FROM f
""",
    "op8_site_templates": r"""
WITH a AS (SELECT page_id, url, regexp_extract(coalesce(html, ''), '<article>(.*?)</article>', 1, 's') AS x FROM pages),
b AS (SELECT page_id, url, regexp_replace(regexp_replace(x, '</?(?:p|h1|br|ul|li)[^>]*>', ' ', 'g'), '<[^>]*>', '', 'g') AS x FROM a),
c AS (SELECT page_id, url, replace(replace(replace(replace(replace(x, '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#x27;', ''''), '&amp;', '&') AS x FROM b)
SELECT page_id, url, trim(regexp_replace(x, '\s+', ' ', 'g')) AS text, length(trim(regexp_replace(x, '\s+', ' ', 'g'))) AS n_chars FROM c
""",
}


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
