"""Inverted half-lists, traversal ranks, and the approximate join that stops at a rank.

Each token's list is split at its mean prefix weight; halves are sorted by suffix. A
probe walks its tokens rare-first, lower half before upper half; the rank of an index record is
the number of list entries visited when its first shared token is met. Ranks need the uncut
index, so thresholds never shorten it here.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .measures import MEASURES
from .weights import Prepared


def half_lists(side: DataFrame, parts: int = 2) -> DataFrame:
    """Postings ``(key, half, b_id, pos, w, p_b, s_b, t_b, list_pos, list_len, list_min_prefix)``.

    Two parts split at the mean prefix weight; more parts at equal steps of the mean's multiples.
    """
    by_key = Window.partitionBy("key")
    post = side.select("key", F.col("rec_id").alias("b_id"), "pos", "w", F.col("pre").alias("p_b"), F.col("suf").alias("s_b"), F.col("total").alias("t_b"))
    count, total = F.count("*").over(by_key), F.sum("p_b").over(by_key)
    if parts == 2:
        half = (F.col("p_b") * count >= total).cast("int")
    else:
        half = F.least(F.when(total > 0, F.floor(F.col("p_b") * count * (parts / 2) / total)).otherwise(parts - 1), F.lit(parts - 1)).cast("int")
    post = post.withColumn("half", half)
    lists = Window.partitionBy("key", "half")
    return post.withColumn("list_pos", F.row_number().over(lists.orderBy("s_b", "b_id"))).withColumn("list_len", F.count("*").over(lists)).withColumn("list_min_prefix", F.min("p_b").over(lists))


def met_lists(p: Prepared, probe: DataFrame) -> DataFrame:
    """:func:`half_lists` of the index, of a small probe side only the lists of its tokens: the others are never walked."""
    from .join import smaller
    from .weights import entries

    if p.dedup or smaller(p) != "a":
        return half_lists(p.b)
    keys = np.unique([r[0] for r in probe.select("key").distinct().collect()]).astype(np.int64)
    return half_lists(entries(p.b._packed, MEASURES[p.measure].power, among=keys))


def list_bases(probe: DataFrame, postings: DataFrame) -> DataFrame:
    """For each probe token and half: entries in all earlier lists of the probe, ``base``."""
    lengths = postings.groupBy("key", "half").agg(F.max("list_len").cast("long").alias("n"))
    walk = probe.select(F.col("rec_id").alias("a_id"), "key", F.col("w").alias("w_a"), F.col("suf").alias("s_a")).join(lengths, "key")
    order = Window.partitionBy("a_id").orderBy("key", "half").rowsBetween(Window.unboundedPreceding, -1)
    return walk.withColumn("base", F.coalesce(F.sum("n").over(order), F.lit(0)))


def candidate_log(probe: DataFrame, p: Prepared, postings: DataFrame | None = None, rho: int | None = None) -> DataFrame:
    """``(a_id, b_id, rank, sim, suffix)`` of every pair that shares a token (up to rank ``rho``).

    Lists are truncated to what the cutoff leaves before they are joined, so a probe
    meets at most ``rho`` entries at their first shared token.
    """
    m = MEASURES[p.measure]
    postings = met_lists(p, probe) if postings is None else postings
    bases = list_bases(probe, postings)
    met = bases.join(postings, ["key", "half"]).withColumn("rank", F.col("base") + F.col("list_pos"))
    if p.dedup:
        met = met.where("a_id <> b_id")
    totals = probe.select(F.col("rec_id").alias("a_id"), F.col("total").alias("t_a")).distinct()
    each = met.groupBy("a_id", "b_id").agg(F.min_by(F.struct("rank", "s_a"), "key").alias("f"), F.sum(m.shared(F.col("w_a"), F.col("w"))).alias("i"), F.first("t_b").alias("t_b"))
    if rho is not None:
        each = each.where(F.col("f.rank") <= rho)
    out = each.join(totals, "a_id")
    return out.select("a_id", "b_id", F.col("f.rank").alias("rank"), m.value(F.col("i"), F.col("t_a"), F.col("t_b")).alias("sim"), F.col("f.s_a").alias("suffix"))


def rank_cut_pairs(p: Prepared, rho: int) -> DataFrame:
    """Scored pairs whose rank is within the cutoff.

    Only list entries within the cutoff are met, by bases and positions; each met pair is
    then scored over its whole sets.
    """
    from .join import arrays, verify

    postings = met_lists(p, p.a)
    bases = list_bases(p.a, postings).where(F.col("base") < rho)
    met = bases.join(postings.where(F.col("list_pos") <= rho), ["key", "half"]).where(F.col("base") + F.col("list_pos") <= rho)
    if p.dedup:
        met = met.where("a_id <> b_id")
    pairs = met.select("a_id", "b_id").distinct()
    return verify(pairs, arrays(p.a, "a"), arrays(p.b, "b"), p.measure)
