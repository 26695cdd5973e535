"""SQL surface: the text methods as SQL functions and table functions of a session."""

from __future__ import annotations

from pyspark.sql import SparkSession, functions as F

# Each is inlined by the optimizer: no Python runs.
SCALARS = {
    "class_share": "(t STRING, chars STRING) RETURNS DOUBLE RETURN CASE WHEN length(t) = 0 THEN 0D ELSE regexp_count(t, concat('[', chars, ']')) / length(t) END",
    "is_short": "(t STRING) RETURNS BOOLEAN RETURN length(t) < 400",
    "term_share": "(t STRING, pattern STRING) RETURNS DOUBLE RETURN CASE WHEN length(t) = 0 THEN 0D ELSE (length(t) - length(regexp_replace(lower(t), pattern, ''))) / length(t) END",
    "lsh_probability": "(s DOUBLE, per_band INT, bands INT) RETURNS DOUBLE RETURN 1 - pow(1 - pow(s, per_band), bands)",
    "declared_language": "(html STRING) RETURNS STRING RETURN lower(regexp_extract(substring(html, 1, 4096), '(?i)<html[^>]*?lang\\\\s*=\\\\s*[\"\\']?([a-z]+)', 1))",
}


@F.udtf(returnType="pos int, line string")
class TextLines:
    """The non-empty lines of a text."""

    def eval(self, text: str):
        for i, line in enumerate(x for x in (text or "").split("\n") if x):
            yield i, line


def register(spark: SparkSession, sf_dir: str | None = None) -> None:
    """Temporary functions for the session, and views of the given tables if a folder is named."""
    for name, body in SCALARS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    spark.udtf.register("text_lines", TextLines)
    if sf_dir:
        from .plans.relational import views

        views(spark, sf_dir)
