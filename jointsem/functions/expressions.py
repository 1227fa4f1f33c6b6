"""Column helpers: prompts, tokens, prices, page text and lexical scores."""

from __future__ import annotations

from collections.abc import Mapping

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def token_count(text: Column) -> Column:
    """Tokens of a text, taken as a quarter of its characters, rounded up; null counts 0."""
    return F.coalesce(F.ceil(F.length(text) / 4), F.lit(0)).cast("long")


def tokens_of(text: str | None) -> int:
    return -(-len(text or "") // 4)


def call_cost(tokens_in: Column, tokens_out: Column, price_in: float, price_out: float) -> Column:
    """Price of a call; prices are per million tokens."""
    return ((tokens_in * price_in + tokens_out * price_out) / 1e6).cast("decimal(18,6)")


def render(template: str, columns: Mapping[str, Column], limit: int | None = None) -> Column:
    """A prompt from a template with {name} places; values cannot hold a fence of their own, and are whole unless a model's limit is given."""
    parts: list[Column] = []
    rest = template
    for name, value in sorted(columns.items(), key=lambda kv: template.index("{" + kv[0] + "}")):
        before, _, rest = rest.partition("{" + name + "}")
        whole = F.coalesce(value.cast("string"), F.lit(""))
        clean = F.regexp_replace(F.substring(whole, 1, limit) if limit else whole, "`{3,}", "''")
        parts += [F.lit(before), clean]
    return F.concat(*parts, F.lit(rest))


def as_records(df: DataFrame, id_col: str, text_cols: list[str], hidden: str | None = None) -> DataFrame:
    """(id, text) and, for the simulated model alone, (hidden); only these columns go to the workers."""
    text = F.concat_ws(" ", *[F.col(c).cast("string") for c in text_cols])
    return df.select(F.col(id_col).cast("long").alias("id"), F.coalesce(text, F.lit("")).alias("text"), *([F.col(hidden).cast("string").alias("hidden")] if hidden else []))


def require_unique_id(df: DataFrame, id_col: str = "id") -> DataFrame:
    """df, after checking that its id is never null and never repeats."""
    bad = df.groupBy(id_col).count().where(f"`{id_col}` is null or count > 1").limit(1).collect()
    if bad:
        raise ValueError(f"{id_col} must be unique and not null; found {bad[0][0]!r} {bad[0][1]} times")
    return df


def stable_id(df: DataFrame, text_col: str) -> DataFrame:
    """df with an id made of the text's hash and the number of its occurrence; equal texts are interchangeable."""
    from pyspark.sql import Window

    n = F.row_number().over(Window.partitionBy(F.md5(F.col(text_col).cast("binary"))).orderBy(text_col))
    return df.withColumn("id", F.xxhash64(F.md5(F.col(text_col).cast("binary")), n))


def page_text(html: Column) -> Column:
    """Visible text of simple markup by nested replacements."""
    bare = F.regexp_replace(F.coalesce(html, F.lit("")), r"(?is)<(script|style|head)\b.*?</\1>|<!--.*?-->|<[^>]*>", " ")
    for name, value in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&amp;", "&")):
        bare = F.replace(bare, F.lit(name), F.lit(value))
    return F.trim(F.regexp_replace(bare, r"\s+", " "))


def lexical_scores(text: Column, spec: Mapping[str, str]) -> Column:
    """Map from class to how often its pattern matches the lower-cased text."""
    low = F.lower(F.coalesce(text, F.lit("")))
    return F.map_from_arrays(F.array(*[F.lit(c) for c in spec]), F.array(*[F.regexp_count(low, F.lit(p)) for p in spec.values()]))


def lexical_class(text: Column, spec: Mapping[str, str]) -> Column:
    """The class with most matches; of equals the first in the spec."""
    low = F.lower(F.coalesce(text, F.lit("")))
    ranked = F.array_max(F.array(*[F.struct(F.regexp_count(low, F.lit(p)).alias("n"), F.lit(-i).alias("order"), F.lit(c).alias("label")) for i, (c, p) in enumerate(spec.items())]))
    return ranked["label"]


def register(spark: SparkSession) -> None:
    """SQL functions for the same expressions, as temporary SQL functions of the session."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION token_count(text STRING) RETURNS BIGINT RETURN CAST(coalesce(ceil(length(text) / 4), 0) AS BIGINT)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION portable_uniform(key STRING) RETURNS DOUBLE RETURN CAST(conv(substr(md5(key), 1, 8), 16, 10) AS DOUBLE) / 4294967296D")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION call_cost(tin BIGINT, tout BIGINT, pin DOUBLE, pout DOUBLE) RETURNS DECIMAL(18,6) RETURN CAST((tin * pin + tout * pout) / 1e6 AS DECIMAL(18,6))")
