"""Line dedup by site-relative frequency; DataFrame functions only.

For each host, a line's share is the number of the host's pages with it over all pages
of the host. Lines over ``ratio`` (on ``min_pages`` pages or more) are boilerplate and go
from every page of that host. A page with a line many times counts once. A host has at
most (mean lines a page) / ratio boilerplate lines, so they travel as one array a host.

Defined results: a null host is a host of its own; blank lines are never dropped; a null text
stays null; lines are compared without blanks at their ends; repeated rows count as
pages; an empty table gives an empty result; all other columns are kept as they are.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.stages import cut


def boilerplate_lines(df: DataFrame, host_col: str, text_col: str, ratio: float, min_pages: int) -> DataFrame:
    """``(_host, _lines)``: hashes of each host's boilerplate lines. Counts are over all rows."""
    host = F.coalesce(F.col(host_col).cast("string"), F.lit("\x00"))
    pages = df.select(host.alias("_host"), F.col(text_col).alias("_text"))
    totals = pages.groupBy("_host").agg(F.count("*").alias("_pages"))
    hashes = F.array_distinct(F.transform(F.filter(F.split("_text", "\n", -1), lambda x: F.trim(x) != ""), lambda x: F.xxhash64(F.trim(x))))
    counts = pages.select("_host", F.explode(hashes).alias("_line")).groupBy("_host", "_line").agg(F.count("*").alias("_with"))
    often = counts.where(F.col("_with") >= min_pages).join(totals, "_host").where(F.col("_with") > F.col("_pages") * F.lit(ratio))
    return often.groupBy("_host").agg(F.collect_set("_line").alias("_lines"))


def drop_boilerplate(df: DataFrame, host_col: str = "source", text_col: str = "text", ratio: float = 0.05, min_pages: int = 5) -> DataFrame:
    """``df`` with boilerplate lines out of the text, and ``n_lines``, ``n_dropped`` in a struct ``_lines_seen``."""
    found = cut(boilerplate_lines(df, host_col, text_col, ratio, min_pages), "boilerplate")
    # the row travels as one struct, so that no column of it can clash with those added here
    whole = F.struct(*[F.col(f"`{c}`") for c in df.columns])
    host = F.coalesce(F.col(host_col).cast("string"), F.lit("\x00"))
    rows = df.select(whole.alias("_row"), host.alias("_host")).join(found, "_host", "left")
    text = F.col("_row")[text_col]
    lines = F.split(text, "\n", -1)
    common = F.coalesce(F.col("_lines"), F.array().cast("array<bigint>"))
    stays = F.filter(lines, lambda x: ~((F.trim(x) != "") & F.array_contains(common, F.xxhash64(F.trim(x)))))
    rows = rows.withColumn("_stays", F.when(F.size(common) > 0, stays).otherwise(lines))
    count = lambda c: F.coalesce(F.when(text.isNotNull(), c), F.lit(0)).cast("long")
    seen = F.struct(count(F.size(lines)).alias("n_lines"), count(F.size(lines) - F.size("_stays")).alias("n_dropped"))
    keep = [(F.array_join("_stays", "\n") if c == text_col else F.col("_row")[c]).alias(c) for c in df.columns]
    return rows.select(*keep, seen.alias("_lines_seen"))
