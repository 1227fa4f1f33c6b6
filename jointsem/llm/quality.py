"""Quality rules and a hashed n-gram log-likelihood ratio, in DataFrame operations only.

Two multinomials over hashed n-grams are compared: one of trusted documents
(label quality = 1) and one of the whole corpus.  A document's score is the mean
log ratio of its n-grams, so its length has no part in it, and a document stays
if the base rules pass and the score reaches `threshold`.

The n-grams of a text are its words and its pairs of neighbouring words.  The ratio table has `buckets` entries
whatever the corpus holds; it reaches the scoring projection as a scalar
subquery.  Counting combines on the map side, and scoring shuffles nothing.

Nulls: a null text has no words and fails the base rules.  Labels with a null
id or quality are unused.  Without trusted documents every ratio is 0 and the
base rules alone decide.  Repeated rows are counted and returned as often as
they occur.  Of a column of docs that has the name of a result, the result stays.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from jointsem.llm.store import stage

BUCKETS = 100_000
THRESHOLD = -0.2
#: Pseudo counts of every bucket on either side: what a bucket of few n-grams says counts little.
PRIOR = 4.0
MIN_WORDS = 50
MAX_REPEAT_PERCENT = 50
#: Up to so many trusted ids are broadcast (16 MB); more are joined by shuffling texts.
BROADCAST_IDS = 2_000_000
_SPACE = " \t\n\x0b\x0c\r"
_SYMBOLS = r"[#*$%&|<>]"
_FEW = 16
_RULES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")


def _words(text: Column) -> Column:
    inner = F.btrim(text, F.lit(_SPACE))
    return F.when(inner == "", F.expr("cast(array() as array<string>)")).otherwise(F.split(inner, "[ \t-\r]+"))


def _hashed(df: DataFrame, keep: list[Column | str]) -> DataFrame:
    """keep, with _hashes, the hash of each of _words, and _pairs, the hash of each pair of neighbouring words."""
    df = df.select(*keep, F.expr("transform(_words, w -> xxhash64(w))").alias("_hashes"))
    pairs = F.expr("if(size(_hashes) < 2, cast(array() as array<bigint>), transform(slice(_hashes, 1, size(_hashes) - 1), (h, i) -> xxhash64(h, _hashes[i + 1])))")
    return df.withColumn("_pairs", pairs)


def _counted(docs: DataFrame, text_col: str) -> DataFrame:
    """docs with the counts that need its words and lines, _hashes and _pairs.  Words and lines go no further: every projection copies what it keeps."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    df = docs.select(*docs.columns, _words(text).alias("_words"), F.filter(F.split(text, "\n"), lambda x: x.rlike("[^ \t-\r]")).alias("_lines"))
    return _hashed(
        df,
        [
            *docs.columns,
            F.size("_words").cast("long").alias("n_words"),
            F.expr("aggregate(_words, 0L, (s, w) -> s + length(w))").alias("word_chars"),
            F.regexp_count(text, F.lit(_SYMBOLS)).cast("long").alias("n_symbols"),
            (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long").alias("n_dup_lines"),
        ],
    )


def _judged(df: DataFrame, keep: list[str]) -> DataFrame:
    """keep, with n_repeat_words and base_failed, from _hashes.

    A word of a 3-word window that occurs twice in the text counts once.  Windows
    and words are told apart by 64-bit hashes; the windows' positions are found by
    membership when few windows repeat, and by sorting (hash, position) otherwise.
    """
    none = "cast(array() as array<bigint>)"
    df = df.select(*keep, F.expr(f"if(size(_hashes) < 3, {none}, transform(slice(_hashes, 1, size(_hashes) - 2), (h, i) -> xxhash64(h, _hashes[i + 1], _hashes[i + 2])))").alias("_grams"))
    df = df.select(*keep, F.expr(f"if(size(array_distinct(_grams)) = size(_grams), {none}, _grams)").alias("_grams"))
    df = df.withColumn("_sorted", F.sort_array("_grams"))
    df = df.withColumn("_twice", F.expr("array_distinct(array_compact(zip_with(_sorted, slice(_sorted, 2, greatest(size(_sorted), 1)), (a, b) -> if(a = b, a, null))))")).drop("_sorted")
    df = df.withColumn("_places", F.expr(f"if(size(_twice) <= {_FEW}, cast(array() as array<struct<h: bigint, p: int>>), sort_array(transform(_grams, (h, p) -> struct(h, p))))"))
    at = F.expr(
        f"""case when size(_twice) = 0 then cast(array() as array<int>)
        when size(_twice) <= {_FEW} then array_compact(transform(_grams, (h, p) -> if(array_contains(_twice, h), p, null)))
        else sort_array(array_distinct(flatten(zip_with(_places, slice(_places, 2, size(_places)),
             (a, b) -> if(a.h = b.h, array(a.p, b.p), cast(array() as array<int>)))))) end"""
    )
    df = df.select(*keep, at.alias("_at"))
    covered = F.expr("aggregate(zip_with(_at, slice(_at, 2, greatest(size(_at), 1)), (a, b) -> least(3, coalesce(b - a, 3))), 0L, (s, x) -> s + x)")
    return df.select(*keep, covered.alias("n_repeat_words")).withColumn("base_failed", F.expr(f"n_words < {MIN_WORDS} or 100 * n_repeat_words > {MAX_REPEAT_PERCENT} * n_words"))


def _apart(docs: DataFrame, made: tuple[str, ...]) -> tuple[DataFrame, dict[str, str]]:
    """docs without columns named as results, the others under names that nothing here uses, and these names by their own."""
    names = {c: f"_c{n}" for n, c in enumerate(docs.columns) if c not in made}
    return docs.select(*[F.col(c).alias(n) for c, n in names.items()]), names


def _kept_columns(df: DataFrame) -> list[str]:
    return [c for c in df.columns if c not in ("_hashes", "_pairs")]


def with_rules(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """docs with n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words and base_failed."""
    docs, names = _apart(docs, _RULES)
    df = _counted(docs, names[text_col])
    return _judged(df, _kept_columns(df)).withColumnsRenamed({n: c for c, n in names.items()})


def log_ratios(docs: DataFrame, labels: DataFrame, buckets: int = BUCKETS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(bucket, ratio): log of the trusted count over the one to be expected of so many n-grams of the raw corpus, both with PRIOR added; buckets without n-grams have no row."""
    trusted = labels.where("quality = 1").select(F.col("doc_id").alias("_id")).where("_id is not null").distinct()
    if trusted.count() <= BROADCAST_IDS:
        trusted = F.broadcast(trusted)
    rows = docs.select(F.col(id_col).alias("_doc"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("_text"))
    rows = rows.join(trusted, F.col("_doc") == F.col("_id"), "left").select(F.when(F.col("_id").isNull(), 0).otherwise(1).alias("t"), _words(F.col("_text")).alias("_words"))
    grams = _hashed(rows, ["t"]).select("t", F.explode(F.concat("_hashes", "_pairs")).alias("h")).select("t", F.expr(f"pmod(h, {buckets})").cast("int").alias("bucket"))
    counts = stage(grams.groupBy("bucket").agg(F.count("*").alias("raw"), F.sum("t").alias("trusted")), "buckets")
    total = counts.agg(F.sum("raw").alias("raw"), F.sum("trusted").alias("trusted"))
    both = counts.select("bucket", "raw", "trusted", total.select("raw").scalar().alias("raws"), total.select("trusted").scalar().alias("trusteds"))
    expected = F.col("raw") * F.col("trusteds") / F.col("raws")
    return both.select("bucket", F.when(F.col("trusteds") > 0, F.log((F.col("trusted") + PRIOR) / (expected + PRIOR))).otherwise(0.0).alias("ratio"))


def score(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD, buckets: int = BUCKETS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with the rules' columns, llr (mean log ratio, null without words) and kept."""
    docs, names = _apart(docs, (*_RULES, "llr", "kept"))
    id_col, text_col = names[id_col], names[text_col]
    ratios = docs.sparkSession.range(buckets).select(F.col("id").cast("int").alias("bucket")).join(log_ratios(docs, labels, buckets, id_col, text_col), "bucket", "left")
    pairs = F.array_sort(F.collect_list(F.struct("bucket", F.coalesce("ratio", F.lit(0.0)).alias("ratio"))))
    table = stage(ratios.agg(F.transform(pairs, lambda x: x.ratio).alias("ratios")), "ratios")
    df = _counted(docs, text_col).withColumn("_ratios", table.scalar())
    total = F.expr(f"aggregate(concat(_hashes, _pairs), 0D, (s, h) -> s + _ratios[cast(pmod(h, {buckets}) as int)])")
    df = df.withColumn("llr", F.when(F.size("_hashes") > 0, total / (F.size("_hashes") + F.size("_pairs")))).drop("_pairs", "_ratios")
    df = _judged(df, _kept_columns(df)).withColumn("kept", ~F.col("base_failed") & (F.col("llr") >= threshold))
    # made by a generator of one row, so that a filter on them is not pushed into the expressions below, where it would multiply
    made = [c for c in df.columns if c not in docs.columns]
    return df.select(*[F.col(n).alias(c) for c, n in names.items()], F.inline_outer(F.array(F.struct(*made))))
