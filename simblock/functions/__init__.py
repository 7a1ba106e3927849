"""SQL functions of the library, registered by name."""

from __future__ import annotations

from pyspark.sql import SparkSession

SQL = {
    # fixed values: names and bodies
    "token_words": ("t STRING", "ARRAY<STRING>", r"filter(split(lower(coalesce(t, '')), '[^\\p{L}\\p{N}]+'), x -> x <> '')"),
    "token_ngrams": ("t STRING, n INT", "ARRAY<STRING>", "flatten(transform(array(trim(regexp_replace(lower(coalesce(t, '')), '\\\\s+', ' '))), s -> CASE WHEN s = '' THEN array() WHEN length(s) <= n THEN array(s) ELSE transform(sequence(1, length(s) - n + 1), i -> substring(s, i, n)) END))"),
    "set_overlap": ("a ARRAY<STRING>, b ARRAY<STRING>", "INT", "size(array_intersect(a, b))"),
    "set_jaccard": ("a ARRAY<STRING>, b ARRAY<STRING>", "DOUBLE", "CAST(size(array_intersect(a, b)) AS DOUBLE) / nullif(size(array_union(a, b)), 0)"),
    "set_dice": ("a ARRAY<STRING>, b ARRAY<STRING>", "DOUBLE", "2D * size(array_intersect(a, b)) / (size(array_distinct(a)) + size(array_distinct(b)))"),
    "set_cosine": ("a ARRAY<STRING>, b ARRAY<STRING>", "DOUBLE", "size(array_intersect(a, b)) / sqrt(CAST(size(array_distinct(a)) AS DOUBLE) * size(array_distinct(b)))"),
}


def register(spark: SparkSession) -> None:
    """Temporary SQL functions that Catalyst inlines; no Python runs for them."""
    for name, (args, result, body) in SQL.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {result} RETURN {body}")
