"""The one-filter and one-condition joins that the hybrid join is measured against."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .join import arrays, candidates, conditions, pre_candidates, smaller, thresholds, unordered, verify
from .measures import MEASURES, SLACK
from .sweep import swept
from .weights import Prepared, running


def scored_pairs(p: Prepared) -> DataFrame:
    """All pairs that share a token, scored by merging lists (also the brute-force join)."""
    m = MEASURES[p.measure]
    a = p.a.select("key", F.col("rec_id").alias("a_id"), F.col("w").alias("w_a"), F.col("total").alias("t_a"))
    b = p.b.select("key", F.col("rec_id").alias("b_id"), F.col("w").alias("w_b"), F.col("total").alias("t_b"))
    met = a.join(b, "key")
    if p.dedup:
        met = met.where("a_id <> b_id")
    sums = met.groupBy("a_id", "b_id").agg(F.sum(m.shared(F.col("w_a"), F.col("w_b"))).alias("i"), F.first("t_a").alias("t_a"), F.first("t_b").alias("t_b"))
    return sums.select("a_id", "b_id", m.value(F.col("i"), F.col("t_a"), F.col("t_b")).alias("sim"))


def overlap_counts(p: Prepared) -> DataFrame:
    """``(a_id, b_id, shared)``: merge-lists counting of common tokens."""
    a, b = p.a.select("key", F.col("rec_id").alias("a_id")), p.b.select("key", F.col("rec_id").alias("b_id"))
    met = a.join(b, "key")
    if p.dedup:
        met = met.where("a_id < b_id")
    return met.groupBy("a_id", "b_id").agg(F.count("*").alias("shared"))


def naive_hybrid(p: Prepared, tau: float = 0.0, tau_r: float = 0.0, k: int | None = None) -> DataFrame:
    """The three conditions applied after scoring everything."""
    out = conditions(scored_pairs(p), tau, tau_r, k)
    return unordered(out) if p.dedup else out


def _filtered(p: Prepared, tau: float, filters: set) -> DataFrame:
    m = MEASURES[p.measure]
    if not p.dedup and smaller(p) is None and hasattr(p.a, "_packed") or p.dedup and hasattr(p.a, "_packed"):
        found = swept(p.a._packed, p.b._packed, m, tau, frozenset(filters), p.dedup, (tau, 0.0, None))
    else:
        probe = thresholds(p.a, m, F.lit(float(tau)), frozenset(filters))
        met = candidates(pre_candidates(probe, p.b, m, frozenset(filters), p.dedup, tau, half=True), m).select("a_id", "b_id")
        found = verify(met, arrays(p.a, "a"), arrays(p.b, "b"), p.measure)
    out = conditions(found, tau, 0.0, None)
    return unordered(out) if p.dedup else out


def prefix_self_join(p: Prepared, tau: float) -> DataFrame:
    """Positional prefix self-join with size filter; each unordered pair once."""
    return _filtered(p, tau, {"prefix", "size", "positional"})


def generalised_prefix_join(p: Prepared, tau: float) -> DataFrame:
    """Positional prefix join of two weighted collections under any of the four measures."""
    return _filtered(p, tau, {"prefix", "size", "positional"})


def global_top_k(pairs: DataFrame, k: int) -> DataFrame:
    return pairs.orderBy(F.round("sim", 9).desc(), "a_id", "b_id").limit(k)


ABLATION = {
    "prefix": {"prefix"},
    "size": {"prefix", "size"},
    "suffix": {"prefix", "suffix"},
    "positional": {"prefix", "positional"},
    "all": {"prefix", "size", "suffix", "positional"},
}


#: other forms of the suffix and positional filters
FORMS = {
    "suffix_plain": {"prefix", "suffix_plain"},
    "positional_exact": {"prefix", "positional_exact"},
    "plain_and_exact": {"prefix", "size", "suffix_plain", "positional_exact"},
}


def by_sums(side: DataFrame) -> DataFrame:
    """A prepared side with its running sums over weights instead of squared weights."""
    return running(side.select("rec_id", "key", "w"), 1)


def prefix_bounds(p: Prepared, tau: float) -> DataFrame:
    """``(bound, entries)``: index entries of cosine prefixes under the bound on sums and that on squares."""
    row = lambda name, kept: kept.agg(F.lit(name).alias("bound"), F.count("*").alias("entries"))
    return row("sum", by_sums(p.b).where(F.col("suf") >= tau - SLACK)).unionAll(row("square", p.b.where(F.col("suf") >= tau * tau - SLACK)))


def cosine_join_by_sums(p: Prepared, tau: float) -> DataFrame:
    """Cosine join whose prefixes end where the summed weights left fall short of ``tau``, as weights of unit sets are at most 1."""
    a, b = (by_sums(x).where(F.col("suf") >= tau - SLACK).select("key", F.col("rec_id").alias(n)) for x, n in ((p.a, "a_id"), (p.b, "b_id")))
    met = a.join(b, "key")
    met = (met.where("a_id < b_id") if p.dedup else met).select("a_id", "b_id").distinct()
    return conditions(verify(met, arrays(p.a, "a"), arrays(p.b, "b"), p.measure), tau, 0.0, None)


def filter_counts(p: Prepared, tau: float, sets: dict = ABLATION) -> DataFrame:
    """``(filters, entries)``: list entries that survive each set of filters at one threshold."""
    m = MEASURES[p.measure]
    probe = p.a.withColumn("t", F.lit(float(tau)))
    out = None
    for name, filters in sets.items():
        row = pre_candidates(probe, p.b, m, frozenset(filters), p.dedup).agg(F.lit(name).alias("filters"), F.count("*").alias("entries"))
        out = row if out is None else out.unionAll(row)
    return out


def counts_at_kth(p: Prepared, k: int, low: float, sets: dict = ABLATION) -> DataFrame:
    """``(filters, entries, pairs)`` of a nearest-k join whose probes have reached their last threshold.

    That is the similarity of the k-th best partner, and at least ``low``. Counted are the list
    entries that each set of filters leaves and the different pairs among them.
    """
    from pyspark.sql import Window

    from .plans.stages import cut

    order = Window.partitionBy("a_id").orderBy(F.desc("sim"))
    kth = scored_pairs(p).withColumn("_n", F.row_number().over(order)).where(F.col("_n") == k).select(F.col("a_id").alias("rec_id"), F.col("sim").alias("_kth"))
    probe = p.a.join(cut(kth, "kth"), "rec_id", "left").withColumn("t", F.greatest(F.coalesce("_kth", F.lit(0.0)), F.lit(float(low)))).drop("_kth")
    out = None
    for name, filters in sets.items():
        met = pre_candidates(probe, p.b, MEASURES[p.measure], frozenset(filters), p.dedup, low).groupBy("rec_id", "b_id").agg(F.count("*").alias("n"))
        row = met.agg(F.lit(name).alias("filters"), F.coalesce(F.sum("n"), F.lit(0)).alias("entries"), F.count("*").alias("pairs"))
        out = row if out is None else out.unionAll(row)
    return out


def partitioned_counts(p: Prepared, tau: float) -> DataFrame:
    """Entries left by the suffix bounds with the exact prefix, the list's and the half-list's least one."""
    from pyspark.sql import Window

    from .cutoff import half_lists

    m, t = MEASURES[p.measure], F.lit(float(tau))
    kept = p.b.where(F.col("suf") >= m.sigma(F.col("total"), t))
    post = half_lists(kept).withColumn("whole_min", F.min("p_b").over(Window.partitionBy("key")))
    met = p.a.where(F.col("suf") >= m.sigma(F.col("total"), t)).join(post.drop("pos", "w"), "key")
    if p.dedup:
        met = met.where("rec_id <> b_id")

    def passes(prefix: str):
        out = F.col("s_b") >= m.suffix_low(t, F.col("total"), F.col("suf"), F.col(prefix))
        high = m.suffix_high(t, F.col("suf"), F.col("pre"), F.col(prefix))
        return F.count_if(out if high is None else out & (F.col("s_b") <= high))

    return met.agg(F.count("*").alias("prefix"), passes("whole_min").alias("list_min"), passes("list_min_prefix").alias("half_list_min"), passes("p_b").alias("exact"))
