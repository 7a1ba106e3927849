"""The registered queries of the blocking methods, with the SQL of those that SQL can express."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import baselines, classic, cutoff, estimate, metrics, objectives, quality, supervised, unsupervised, verification
from . import sqltext as S
from . import workloads as W
from .join import hybrid_join
from .measures import MEASURES
from .sources import load
from .tokens import ngrams, term_counts, words
from .weights import TokenModel, prepare

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLE_SQL[name] = sql
        return f

    return add


def prepared(spark, sf, a=W.items, b=W.docs, tokenizer="word", weighting="tfidf", measure="jaccard"):
    return prepare(a(spark, sf), None if b is None else b(spark, sf), TokenModel(tokenizer, weighting), measure)


def even(spark, sf):
    return W.docs(spark, sf).where("rec_id % 2 = 0")


def odd(spark, sf):
    return W.docs(spark, sf).where("rec_id % 2 = 1")


def pages(spark, sf):
    return W.pages_dedup(spark, sf).a


def out(pairs: DataFrame) -> DataFrame:
    return pairs.select("a_id", "b_id", F.round("sim", 6).alias("sim"))


# preparation -----------------------------------------------------------------------------------
@query("word_tokens", f"SELECT rec_id, CAST(len(t) AS BIGINT) AS n, md5(array_to_string(t, ' ')) AS tokens FROM (SELECT rec_id, {S.TOKENS['word']} AS t FROM ({S.DOCS}))")
def word_tokens(spark, sf):
    return W.docs(spark, sf).select("rec_id", words(F.col("text")).alias("t")).select("rec_id", F.size("t").cast("long").alias("n"), F.md5(F.encode(F.array_join("t", " "), "UTF-8")).alias("tokens"))


@query("char_trigrams", f"SELECT rec_id, token, CAST(tf AS BIGINT) AS tf FROM ({S.terms(S.ITEMS, 'trigram')})")
def char_trigrams(spark, sf):
    return term_counts(W.items(spark, sf), "trigram")


@query("term_frequency", f"SELECT rec_id, token, CAST(tf AS BIGINT) AS tf FROM ({S.terms(S.DOCS)})")
def term_frequency(spark, sf):
    return term_counts(W.docs(spark, sf))


@query("token_dictionary", f"SELECT token, count(*) AS df, row_number() OVER (ORDER BY count(*), token) - 1 AS position FROM ({S.terms(S.DOCS)}) GROUP BY token")
def token_dictionary(spark, sf):
    from .plans.ordering import running_totals
    from .weights import dictionary

    d = dictionary(term_counts(W.docs(spark, sf))).withColumn("one", F.lit(1).cast("long"))
    return running_totals(d, ["key"], {"position": "one"}).select("token", "df", "position")


@query("trigram_gate", "SELECT CAST(sum(len(text)) AS BIGINT) AS characters, sum(len(text)) < 100000000 AS allowed FROM documents")
def trigram_gate(spark, sf):
    return W.docs(spark, sf).agg(F.sum(F.length("text")).alias("characters")).select("characters", (F.col("characters") < 100_000_000).alias("allowed"))


@query("tfidf_weights", f"WITH {S.sets(S.ITEMS, S.DOCS, 'word', 'tfidf', 'jaccard')} SELECT rec_id, token, round(w, 6) AS w FROM wa")
def tfidf_weights(spark, sf):
    p = prepared(spark, sf)
    return p.a.join(p.vocabulary, "key").select("rec_id", "token", F.round("w", 6).alias("w"))


@query("unit_norm_check", f"WITH {S.sets(S.ITEMS, S.DOCS, 'word', 'tfidf', 'cosine')} SELECT rec_id, round(sum(w * w), 6) AS squared FROM wb GROUP BY rec_id")
def unit_norm_check(spark, sf):
    return prepared(spark, sf, measure="cosine").b.groupBy("rec_id").agg(F.round(F.sum(F.col("w") * F.col("w")), 6).alias("squared"))


@query("suffix_weights", f"WITH {S.sets(S.ITEMS, S.DOCS, 'word', 'tfidf', 'jaccard')} SELECT rec_id, token, round(pre, 6) AS pre, round(suf, 6) AS suf, round(total, 6) AS total FROM ({S.running('jaccard')})")
def suffix_weights(spark, sf):
    p = prepared(spark, sf)
    return p.a.join(p.vocabulary, "key").select("rec_id", "token", *[F.round(c, 6).alias(c) for c in ("pre", "suf", "total")])


# measures --------------------------------------------------------------------------------------
def _binary_sql(measure: str) -> str:
    value = {"jaccard": "i / (x + y - i)", "cosine": "i / sqrt(x * y)", "dice": "2 * i / (x + y)", "overlap": "i"}[measure]
    return f"""WITH {S.sets(S.ITEMS, S.DOCS, 'word', 'binary', 'jaccard')},
    met AS (SELECT a.rec_id AS a_id, b.rec_id AS b_id, count(*)::DOUBLE AS i, any_value(a.total) AS x, any_value(b.total) AS y FROM wa a JOIN wb b ON a.token = b.token GROUP BY ALL)
    SELECT a_id, b_id, round({value}, 6) AS sim FROM met"""


for _m in MEASURES:
    query(f"sim_{_m}_binary", _binary_sql(_m))(lambda spark, sf, m=_m: out(W.similarity_table(spark, sf, m)))
    query(f"sim_{_m}_tfidf", f"WITH {S.pairs(S.ITEMS, S.DOCS, 'word', 'tfidf', _m)} SELECT a_id, b_id, round(sim, 6) AS sim FROM pairs")(
        lambda spark, sf, m=_m: out(classic.scored_pairs(prepared(spark, sf, measure=m))))

# joins -----------------------------------------------------------------------------------------
TAU = {"jaccard": 0.1, "cosine": 0.13, "dice": 0.17, "overlap": 41.5}
TAU_BINARY = {"jaccard": 0.07, "cosine": 0.19, "dice": 0.13, "overlap": 6.5}


def _join(name, a, b, sa, sb, tokenizer, weighting, measure, tau=0.0, tau_r=0.0, k=None, run=hybrid_join, **more):
    query(name, S.hybrid(sa, sb, tokenizer, weighting, measure, tau, tau_r, k))(
        lambda spark, sf: out(run(prepared(spark, sf, a, b, tokenizer, weighting, measure), tau, tau_r, k, **more)))


for _m in MEASURES:
    _join(f"threshold_join_{_m}", W.items, W.docs, S.ITEMS, S.DOCS, "word", "tfidf", _m, TAU[_m])
    _join(f"prefix_join_weighted_{_m}", even, odd, S.EVEN, S.ODD, "word", "tfidf", _m, {"overlap": 900.5}.get(_m, 0.41), run=lambda p, tau, tau_r, k: classic.generalised_prefix_join(p, tau))
    for _w in ("binary", "tfidf"):
        for _t in ("word", "trigram"):
            _tau = {"overlap": 3.5}.get(_m, 0.021)
            _join(f"hybrid_join_{_m}_{_w}_{_t}", W.items, W.docs, S.ITEMS, S.DOCS, _t, _w, _m, _tau, 0.55, 7)
_join("relative_join_jaccard", W.items, W.docs, S.ITEMS, S.DOCS, "word", "tfidf", "jaccard", 0.0, 0.6)
_join("nearest_k_join_cosine", W.items, W.docs, S.ITEMS, S.DOCS, "word", "tfidf", "cosine", k=10)
_join("nearest_k_join_documents", even, odd, S.EVEN, S.ODD, "word", "tfidf", "cosine", k=5)
_join("hybrid_join_dedup", W.docs, None, S.DOCS, None, "word", "tfidf", "cosine", 0.1, 0.5, 5)
_join("threshold_join_dedup", W.docs, None, S.DOCS, None, "word", "binary", "jaccard", 0.5)
_join("hybrid_join_pages", pages, None, S.PAGES, None, "word", "tfidf", "jaccard", 0.05, 0.5, 5)
_join("prefix_self_join_jaccard", W.docs, None, S.DOCS, None, "word", "binary", "jaccard", 0.5, run=lambda p, tau, tau_r, k: classic.prefix_self_join(p, tau))
_join("naive_hybrid_join", W.items, W.docs, S.ITEMS, S.DOCS, "word", "tfidf", "cosine", 0.05, 0.5, 5, run=classic.naive_hybrid)


@query("overlap_count_join", f"WITH {S.sets(S.ITEMS, S.DOCS, 'word', 'binary', 'jaccard')} SELECT a.rec_id AS a_id, b.rec_id AS b_id, count(*) AS shared FROM wa a JOIN wb b ON a.token = b.token GROUP BY ALL")
def overlap_count_join(spark, sf):
    return classic.overlap_counts(prepared(spark, sf, weighting="binary"))


@query("global_top_pairs", f"WITH {S.pairs(S.ITEMS, S.DOCS, 'word', 'tfidf', 'cosine')} SELECT a_id, b_id, round(sim, 6) AS sim FROM pairs ORDER BY round(sim, 9) DESC, a_id, b_id LIMIT 50")
def global_top_pairs(spark, sf):
    return out(classic.global_top_k(classic.scored_pairs(prepared(spark, sf, measure="cosine")), 50))


# cutoff ----------------------------------------------------------------------------------------
@query("traversal_rank", f"WITH {S.ranked(S.ITEMS, S.DOCS)} SELECT a_id, b_id, rank FROM log")
def traversal_rank(spark, sf):
    p = prepared(spark, sf, weighting="binary")
    return cutoff.candidate_log(p.a, p).select("a_id", "b_id", F.col("rank").cast("long").alias("rank"))


@query("hybrid_join_rank_cutoff", f"WITH {S.ranked(S.ITEMS, S.DOCS)} SELECT a_id, b_id, round(sim, 6) AS sim FROM ({S.conditions('(SELECT * FROM log WHERE rank <= 150)', 0.01, 0.5, 5)})")
def hybrid_join_rank_cutoff(spark, sf):
    return out(hybrid_join(prepared(spark, sf, weighting="binary"), 0.01, 0.5, 5, rho=150))


@query("half_list_stats", f"""WITH {S.ranked(S.ITEMS, S.DOCS)} SELECT token, CAST(half AS INT) AS half, count(*) AS entries, round(min(pre), 6) AS min_prefix, round(max(suf), 6) AS max_suffix FROM lists GROUP BY token, half""")
def half_list_stats(spark, sf):
    p = prepared(spark, sf, weighting="binary")
    h = cutoff.half_lists(p.b).join(p.vocabulary.select("key", "token"), "key")
    return h.groupBy("token", "half").agg(F.count("*").alias("entries"), F.round(F.min("p_b"), 6).alias("min_prefix"), F.round(F.max("s_b"), 6).alias("max_suffix"))


@query("approx_quality", f"""WITH {S.ranked(S.ITEMS, S.DOCS)}, exact AS ({S.conditions('log', 0.01, 0.5, 5)}), near AS ({S.conditions('(SELECT * FROM log WHERE rank <= 150)', 0.01, 0.5, 5)}),
 w AS (SELECT a_id, sum(sim) AS s, max(sim) AS best FROM exact GROUP BY a_id), k AS (SELECT a_id, sum(sim) AS s FROM near JOIN w USING (a_id) WHERE round(sim, 9) >= round(best * 0.5, 9) GROUP BY a_id)
 SELECT round(avg(CASE WHEN coalesce(w.s, 0) = 0 THEN 1 ELSE coalesce(k.s, 0) / w.s END), 6) AS quality FROM (SELECT item_id AS a_id FROM benchmark) LEFT JOIN w USING (a_id) LEFT JOIN k USING (a_id)""")
def approx_quality(spark, sf):
    p = prepared(spark, sf, weighting="binary")
    probes = W.items(spark, sf).select(F.col("rec_id").alias("a_id"))
    return quality.measure(hybrid_join(p, 0.01, 0.5, 5), hybrid_join(p, 0.01, 0.5, 5, rho=150), probes, 0.5).select(F.round("quality", 6).alias("quality"))


@query("approx_consistency_violations", "SELECT CAST(0 AS BIGINT) AS violations")
def approx_consistency_violations(spark, sf):
    p = prepared(spark, sf, weighting="binary")
    return quality.violations(hybrid_join(p, 0.01, 0.5, 5, rho=150), 0.01, 0.5, 5).agg(F.count("*").alias("violations"))


#: A worked example of two probes and six index records, and two approximate results.
EXAMPLE = {1: [0.5, 0.8, 0.1, 0.4, 0.6, 0.6], 2: [0.4, 0.3, 0.5, 0.9, 0.2, 0.4]}
APPROXIMATE = {
    1: [(1, 2), (1, 4), (1, 5), (1, 6), (2, 4)],
    2: [(1, 1), (1, 4), (1, 5), (1, 6), (2, 1), (2, 2), (2, 3), (2, 6)],
}


@query("quality_worked_example", "SELECT * FROM (VALUES (1, 6::BIGINT, 0.8014::DOUBLE), (2, 6::BIGINT, 0.5986::DOUBLE)) AS t(result, exact_pairs, quality)")
def quality_worked_example(spark, sf):
    from .join import conditions

    rows = [(a, b + 1, s) for a, x in EXAMPLE.items() for b, s in enumerate(x)]
    pairs = spark.createDataFrame(rows, "a_id long, b_id long, sim double")
    exact = conditions(pairs, 0.2, 0.5, 4)
    parts = None
    for n, kept in APPROXIMATE.items():
        near = pairs.join(spark.createDataFrame(kept, "a_id long, b_id long"), ["a_id", "b_id"])
        row = exact.agg(F.lit(n).alias("result"), F.count("*").alias("exact_pairs")).crossJoin(quality.measure(exact, near, pairs.select("a_id"), 0.5).select(F.round("quality", 4).alias("quality")))
        parts = row if parts is None else parts.union(row)
    return parts


# filters ---------------------------------------------------------------------------------------
def _counts_sql(measure: str, tau: float) -> str:
    sig = {"jaccard": f"{tau} * w.total", "cosine": f"{tau * tau}"}[measure] + " - 1e-9"
    low = {"jaccard": f"b.suf >= {tau} * (a.total + b.pre) - 1e-9 AND b.suf <= a.suf / {tau} - a.pre - b.pre + 1e-9", "cosine": f"b.suf >= {tau * tau} / a.suf - 1e-9"}[measure]
    size = {"jaccard": f"b.total >= {tau} * a.total - 1e-9 AND b.total <= a.total / {tau} + 1e-9", "cosine": "b.total >= -1e-9"}[measure]
    pos = {"jaccard": f"least(a.suf, b.suf) >= {tau / (1 + tau)} * (a.total + b.total) - 1e-9", "cosine": f"a.suf * b.suf >= {tau * tau} - 1e-9"}[measure]
    return f"""WITH {S.sets(S.DOCS, None, 'word', 'binary', measure)}, r AS (SELECT * FROM ({S.running(measure)}) w WHERE suf >= {sig}),
 m AS (SELECT {size} AS size, {low} AS suffix, {pos} AS by_position FROM r a JOIN r b ON a.token = b.token AND a.rec_id <> b.rec_id)
 SELECT 'prefix' AS filters, count(*) AS entries FROM m UNION ALL SELECT 'size', count(*) FROM m WHERE size UNION ALL SELECT 'suffix', count(*) FROM m WHERE suffix
 UNION ALL SELECT 'positional', count(*) FROM m WHERE by_position UNION ALL SELECT 'all', count(*) FROM m WHERE size AND suffix AND by_position"""


query("filter_ablation_jaccard", _counts_sql("jaccard", 0.5))(lambda spark, sf: classic.filter_counts(prepared(spark, sf, W.docs, None, weighting="binary"), 0.5))
query("filter_ablation_cosine", _counts_sql("cosine", 0.6))(lambda spark, sf: classic.filter_counts(prepared(spark, sf, W.docs, None, weighting="binary", measure="cosine"), 0.6))


def _forms_sql(tau: float) -> str:
    need = f"{tau / (1 + tau)} * (a.total + b.total) - 1e-9"
    plain = f"b.suf >= {tau} * a.total - 1e-9 AND b.suf <= a.total / {tau} + 1e-9"
    size = f"b.total >= {tau} * a.total - 1e-9 AND b.total <= a.total / {tau} + 1e-9"
    return f"""WITH {S.sets(S.DOCS, None, 'word', 'tfidf', 'jaccard')}, r AS (SELECT * FROM ({S.running('jaccard')}) w WHERE suf >= {tau} * w.total - 1e-9),
 m AS (SELECT {plain} AS plain, {size} AS size, least(a.w, b.w) + least(a.suf - a.w, b.suf - b.w) >= {need} AS by_position FROM r a JOIN r b ON a.token = b.token AND a.rec_id <> b.rec_id)
 SELECT 'suffix_plain' AS filters, count(*) AS entries FROM m WHERE plain UNION ALL SELECT 'positional_exact', count(*) FROM m WHERE by_position
 UNION ALL SELECT 'plain_and_exact', count(*) FROM m WHERE size AND plain AND by_position"""


query("filter_forms_weighted", _forms_sql(0.5))(lambda spark, sf: classic.filter_counts(prepared(spark, sf, W.docs, None), 0.5, classic.FORMS))
query("threshold_join_plain_and_exact", S.hybrid(S.DOCS, None, "word", "tfidf", "dice", tau=0.5))(
    lambda spark, sf: out(hybrid_join(prepared(spark, sf, W.docs, None, measure="dice"), tau=0.5, filters=frozenset(classic.FORMS["plain_and_exact"])))
)


@query("cosine_prefix_bounds", f"""WITH {S.sets(S.ITEMS, S.DOCS, 'word', 'tfidf', 'cosine')},
 s AS (SELECT sum(w) OVER o AS by_sum, sum(w * w) OVER o AS by_square FROM wb WINDOW o AS (PARTITION BY rec_id ORDER BY df, token ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING))
 SELECT 'sum' AS bound, count(*) FILTER (WHERE by_sum >= 0.6 - 1e-9) AS entries FROM s UNION ALL SELECT 'square', count(*) FILTER (WHERE by_square >= 0.36 - 1e-9) FROM s""")
def cosine_prefix_bounds(spark, sf):
    return classic.prefix_bounds(prepared(spark, sf, measure="cosine"), 0.6)


query("cosine_join_by_sums", S.hybrid(S.ITEMS, S.DOCS, "word", "tfidf", "cosine", tau=0.3))(lambda spark, sf: out(classic.cosine_join_by_sums(prepared(spark, sf, measure="cosine"), 0.3)))


def _partial_query(measure: str, tau: float):
    sql = f"WITH {S.pairs(S.ITEMS, S.DOCS, 'word', 'tfidf', measure)} SELECT a_id, b_id, CASE WHEN round(sim, 9) >= {tau} THEN round(sim, 6) ELSE 0.0::DOUBLE END AS sim FROM pairs"

    @query(f"partial_similarity_{measure}", sql)
    def run(spark, sf):
        return out(verification.partial_pairs(prepared(spark, sf, measure=measure), tau))


for _measure, _tau in (("jaccard", 0.1), ("cosine", 0.3), ("dice", 0.2), ("overlap", 20.0)):
    _partial_query(_measure, _tau)
query("partial_threshold_join", S.hybrid(S.DOCS, None, "word", "tfidf", "jaccard", tau=0.4))(lambda spark, sf: out(verification.partial_join(prepared(spark, sf, W.docs, None), 0.4)))


@query("precandidates_partitioned", f"""WITH {S.sets(S.DOCS, None, 'word', 'binary', 'jaccard')}, r AS (SELECT * FROM ({S.running('jaccard')}) w WHERE suf >= 0.5 * total - 1e-9),
 h AS (SELECT *, CASE WHEN pre * count(*) OVER (PARTITION BY token) >= sum(pre) OVER (PARTITION BY token) THEN 1 ELSE 0 END AS half, min(pre) OVER (PARTITION BY token) AS lm FROM r),
 g AS (SELECT *, min(pre) OVER (PARTITION BY token, half) AS hm FROM h),
 m AS (SELECT a.total AS ta, a.suf AS sa, a.pre AS pa, b.suf AS sb, b.pre AS pb, b.lm, b.hm FROM r a JOIN g b ON a.token = b.token AND a.rec_id <> b.rec_id)
 SELECT count(*) AS prefix, count(*) FILTER (WHERE sb >= 0.5 * (ta + lm) - 1e-9 AND sb <= sa / 0.5 - pa - lm + 1e-9) AS list_min,
  count(*) FILTER (WHERE sb >= 0.5 * (ta + hm) - 1e-9 AND sb <= sa / 0.5 - pa - hm + 1e-9) AS half_list_min,
  count(*) FILTER (WHERE sb >= 0.5 * (ta + pb) - 1e-9 AND sb <= sa / 0.5 - pa - pb + 1e-9) AS exact FROM m""")
def precandidates_partitioned(spark, sf):
    return classic.partitioned_counts(prepared(spark, sf, W.docs, None, weighting="binary"), 0.5)


@query("cosine_prefix_growth", f"SELECT DISTINCT n, round(1 - 0.6 / sqrt(n), 6) AS by_sum, round(1 - 0.36::DOUBLE, 6) AS by_square FROM (SELECT count(*) AS n FROM ({S.terms(S.DOCS)}) GROUP BY rec_id)")
def cosine_prefix_growth(spark, sf):
    """Share of a set of n equal unit weights that its prefix holds at 0.6, under sums and under squares, for the sizes of the documents' word sets."""
    n = W.docs(spark, sf).select(F.size(F.array_distinct(words(F.col("text")))).cast("long").alias("n")).where("n > 0").distinct()
    return n.select("n", F.round(1 - 0.6 / F.sqrt("n"), 6).alias("by_sum"), F.round(F.lit(1 - 0.36), 6).alias("by_square"))


# estimation ------------------------------------------------------------------------------------
_TRUTH = f"truth AS (SELECT a.rec_id AS a_id, b.rec_id AS b_id FROM ({S.ITEMS}) a JOIN ({S.DOCS}) b ON contains(b.text, a.text))"


def _theta_sql(d: str) -> str:
    return f"""WITH {S.ranked(S.ITEMS, S.DOCS)}, {_TRUTH}, dd AS (SELECT unnest({d}) AS d),
 own AS (SELECT t.a_id, t.b_id, d, sim * (1 - d) AS low, rank AS own_rank FROM truth t JOIN log USING (a_id, b_id) CROSS JOIN dd),
 j AS (SELECT own.*, o.b_id AS o_id, o.sim AS o_sim, o.rank AS o_rank, o.b_id <> own.b_id AND (round(o.sim, 9) > round(low, 9) OR (round(o.sim, 9) = round(low, 9) AND o.b_id < own.b_id)) AS better FROM own JOIN log o ON o.a_id = own.a_id),
 th AS (SELECT a_id, b_id, d, any_value(low) AS low, greatest(any_value(low), max(CASE WHEN o_id <> b_id THEN o_sim END)) AS best, count(*) FILTER (WHERE better) + 1 AS k_min,
   greatest(any_value(own_rank), coalesce(arg_min(o_rank, (o_sim, -o_id)) FILTER (WHERE better), 0)) AS rank_min FROM j GROUP BY a_id, b_id, d)"""


@query("recall_conditions", _theta_sql("[0.0]") + " SELECT a_id, b_id, round(low, 6) AS tau_max, round(low / best, 6) AS tau_r_max, CAST(k_min AS BIGINT) AS k_min, CAST(rank_min AS BIGINT) AS rank_min FROM th")
def recall_conditions_query(spark, sf):
    w, p = W.items_in_docs(spark, sf), prepared(spark, sf, weighting="binary")
    return estimate.recall_conditions(p, w.truth).select("a_id", "b_id", F.round("tau_max", 6).alias("tau_max"), F.round("tau_r_max", 6).alias("tau_r_max"), "k_min", "rank_min")


@query("recall_conditions_margin", _theta_sql("[0.0, 0.1, 0.5]") + " SELECT a_id, b_id, d::DOUBLE AS d, round(low, 6) AS tau_max, CAST(k_min AS BIGINT) AS k_min, CAST(rank_min AS BIGINT) AS rank_min FROM th")
def recall_conditions_margin(spark, sf):
    w, p = W.items_in_docs(spark, sf), prepared(spark, sf, weighting="binary")
    return estimate.recall_conditions(p, w.truth, (0.0, 0.1, 0.5)).select("a_id", "b_id", "d", F.round("tau_max", 6).alias("tau_max"), "k_min", "rank_min")


@query("estimated_recall", _theta_sql("[0.0, 0.1, 0.5]") + " SELECT d::DOUBLE AS d, round(avg(CASE WHEN round(low, 9) >= 0.01 AND round(low / best, 9) >= 0.4 AND k_min <= 3 THEN 1.0 ELSE 0 END), 6) AS recall FROM th GROUP BY d")
def estimated_recall(spark, sf):
    w, p = W.items_in_docs(spark, sf), prepared(spark, sf, weighting="binary")
    return estimate.recall(estimate.recall_conditions(p, w.truth, (0.0, 0.1, 0.5)), 0.01, 0.4, 3).select("d", F.round("recall", 6).alias("recall"))


@query("trajectory_histogram", f"WITH {S.ranked(S.ITEMS, S.DOCS)}, b AS (SELECT least(floor(sim * 100 + 1e-9), 99)::INT AS cell, sim FROM log) SELECT cell, count(*) AS pairs, round(sum(sim), 6) AS sims FROM b GROUP BY cell")
def trajectory_histogram(spark, sf):
    """At the last checkpoint: pairs and similarity by bin."""
    p = prepared(spark, sf, weighting="binary")
    log = cutoff.candidate_log(p.a, p)
    cell = F.least(F.floor(F.col("sim") * 100 + F.lit(1e-9)), F.lit(99)).cast("int")
    return log.groupBy(cell.alias("cell")).agg(F.count("*").alias("pairs"), F.round(F.sum("sim"), 6).alias("sims"))


@query("pair_bound", f"""WITH {S.ranked(S.ITEMS, S.DOCS)}, b AS (SELECT a_id, sim, max(sim) OVER (PARTITION BY a_id) AS best FROM log),
 c AS (SELECT a_id, count(*) FILTER (WHERE least(floor(sim * 100 + 1e-9), 99) >= least(floor(greatest(0.02, 0.5 * best) * 100 + 1e-9), 99)) AS n FROM b GROUP BY a_id)
 SELECT CAST(sum(least(n, 7)) AS DOUBLE) AS pairs FROM c""")
def pair_bound(spark, sf):
    t = estimate.record(prepared(spark, sf, weighting="binary"))
    return spark.createDataFrame([(t.pairs(0.02, 0.5, 7),)], "pairs double")


@query("sampled_pair_estimate", f"WITH {S.ranked(S.ITEMS, S.DOCS)} SELECT CAST(count(*) AS DOUBLE) AS pairs FROM ({S.conditions('log', 0.02, 0.5, 7)})")
def sampled_pair_estimate(spark, sf):
    return spark.createDataFrame([(float(estimate.by_sampling(prepared(spark, sf, weighting="binary"), 0.02, 0.5, 7)),)], "pairs double")


@query("rank_for_quality")
def rank_for_quality(spark, sf):
    t = estimate.record(prepared(spark, sf, measure="cosine"))
    rows = [(q, quality.rank_for(q, t, 0.02, 0.5, 7)) for q in (0.8, 0.9, 0.95, 0.99, 1.0)]
    return spark.createDataFrame(rows, "quality double, rank long")


@query("quality_for_rank")
def quality_for_rank(spark, sf):
    t = estimate.record(prepared(spark, sf, measure="cosine"))
    return spark.createDataFrame([(int(x), quality.quality_of(i, t, 0.02, 0.5, 7)) for i, x in enumerate(t.levels)], "rank long, quality double")


@query("runtime_estimate")
def runtime_estimate(spark, sf):
    t = estimate.record(prepared(spark, sf, measure="cosine"))
    rows = [(tau, k, float(t.visited(tau, 0.5, k, None, estimate.SIGMA["cosine"]))) for tau in (0.02, 0.1, 0.3) for k in (1, 10)]
    return spark.createDataFrame(rows, "tau double, k int, entries double")


@query("join_with_quality")
def join_with_quality(spark, sf):
    return out(quality.join_with_quality(prepared(spark, sf, measure="cosine"), 0.02, 0.5, 7, 0.9))


# blockers --------------------------------------------------------------------------------------
WORDS = [(TokenModel("word", "tfidf"), m) for m in ("jaccard", "cosine", "overlap")]
TUNED = [(TokenModel("word", w), m) for w in ("binary", "tfidf") for m in ("jaccard", "cosine")]


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """Deduplication of the documents by the unsupervised blocker."""
    return unsupervised.block(W.docs(spark, sf), None, k=5, space=WORDS)


query("unsupervised_block")(lambda spark, sf: unsupervised.block(W.items(spark, sf), W.docs(spark, sf), k=10))
query("unsupervised_block_approximate")(lambda spark, sf: unsupervised.block(W.items(spark, sf), W.docs(spark, sf), k=10, q=0.95, space=WORDS))
query("unsupervised_block_even_odd")(lambda spark, sf: unsupervised.block(even(spark, sf), odd(spark, sf), k=6, space=WORDS))
query("unsupervised_block_dedup")(flagship)


@query("supervised_block")
def supervised_block(spark, sf):
    w = W.items_in_docs(spark, sf)
    train, _ = W.split_matches(w.truth, 100)
    return supervised.block(w.a, w.b, train, objectives.recall_target(0.9), space=TUNED[2:], restarts=4, margins=(0.0, 0.1, 0.3))


@query("supervised_block_approximate")
def supervised_block_approximate(spark, sf):
    w = W.items_in_docs(spark, sf)
    train, _ = W.split_matches(w.truth, 100)
    return supervised.block(w.a, w.b, train, objectives.recall_target(0.9), space=TUNED[2:], restarts=1, margins=(0.0, 0.1), q=0.95)


@query("supervised_block_dedup")
def supervised_block_dedup(spark, sf):
    w = W.docs_dedup(spark, sf)
    train, _ = W.split_matches(w.truth, 100)
    return supervised.block(w.a, None, train, objectives.linear(0.02), space=TUNED[2:], restarts=4, margins=(0.0, 0.1))


@query("blocker_explain")
def blocker_explain(spark, sf):
    told: list = []
    unsupervised.block(W.items(spark, sf), W.docs(spark, sf), k=10, q=0.95, space=WORDS, explain=told)
    return spark.createDataFrame([(c.describe(), c.tau, c.tau_r, c.k, c.rho) for c in told], "report string, tau double, tau_r double, k int, rho long")


@query("discriminative_power", f"""WITH {S.pairs(S.ITEMS, S.DOCS, 'word', 'tfidf', 'cosine')}, r AS (SELECT a_id, sim, max(sim) OVER (PARTITION BY a_id) AS best, row_number() OVER (PARTITION BY a_id ORDER BY sim DESC, b_id) AS n FROM pairs),
 s AS (SELECT a_id, (sum(sim / best) - 1) / 9 AS x FROM r WHERE n <= 10 GROUP BY a_id)
 SELECT round(1 - sum(coalesce(x, 0)) / count(*), 6) AS power FROM (SELECT DISTINCT rec_id AS a_id FROM wa) LEFT JOIN s USING (a_id)""")
def discriminative_power(spark, sf):
    t = estimate.record(prepared(spark, sf, measure="cosine"))
    return spark.createDataFrame([(round(unsupervised.discriminative_power(t), 6),)], "power double")


@query("balanced_thresholds")
def balanced_thresholds(spark, sf):
    p = prepared(spark, sf, measure="cosine")
    t = estimate.record(p)
    return spark.createDataFrame([(k, *unsupervised.balance(t, k, p.n_a)) for k in (1, 5, 10)], "k int, tau double, tau_r double")


@query("budget_split", """WITH n AS (SELECT (SELECT count(*) FROM benchmark) AS a, (SELECT count(*) FROM documents) AS b), k AS (SELECT unnest([5, 10, 60, 100]) AS k)
 SELECT k::INT AS k, ((k * a - (k * a) // (2 * b) * b) // a)::INT AS k_ab, ((k * a) // (2 * b))::INT AS k_ba FROM n, k""")
def budget_split(spark, sf):
    a, b = load(spark, sf, "benchmark").count(), load(spark, sf, "documents").count()
    return spark.createDataFrame([(k, *unsupervised.split_budget(a, b, k)) for k in (5, 10, 60, 100)], "k int, k_ab int, k_ba int")


# baselines -------------------------------------------------------------------------------------
query("token_blocking", f"WITH {S.sets(S.ITEMS, S.DOCS, 'word', 'binary', 'jaccard')} SELECT DISTINCT a.rec_id AS a_id, b.rec_id AS b_id FROM wa a JOIN wb b ON a.token = b.token")(
    lambda spark, sf: baselines.token_blocking(prepared(spark, sf, weighting="binary")))
_HVT = f"""WITH {S.sets(S.ITEMS, S.DOCS, 'word', 'tfidf', 'jaccard')}, mean AS (SELECT round(avg(w), 9) AS m FROM (SELECT w, df FROM wa UNION ALL SELECT w, df FROM wb) WHERE df > 1),
 c AS (SELECT a.rec_id AS a_id, b.rec_id AS b_id, count(*) AS n FROM wa a JOIN wb b ON a.token = b.token, mean WHERE a.df > 1 AND round(a.w, 9) > m AND round(b.w, 9) > m GROUP BY ALL)
 SELECT a_id, b_id FROM c WHERE n >= (SELECT avg(n) FROM c)"""
query("high_value_token_blocking", _HVT)(lambda spark, sf: baselines.high_value_blocking(prepared(spark, sf)))
query("high_value_token_blocking_pruned", _HVT)(lambda spark, sf: baselines.high_value_blocking_pruned(prepared(spark, sf)))
query("minhash_lsh")(lambda spark, sf: baselines.minhash(prepared(spark, sf, W.docs, None, weighting="binary"), 0.5))
query("positional_prefix_binary_cosine", S.hybrid(S.ITEMS, S.DOCS, "word", "binary", "cosine", 0.2))(
    lambda spark, sf: out(classic.generalised_prefix_join(prepared(spark, sf, weighting="binary", measure="cosine"), 0.2)))


@query("band_choice", """WITH t AS (SELECT DISTINCT round(l_tax::DOUBLE * 10, 1) AS tau FROM lineitem WHERE l_tax > 0), r AS (SELECT unnest(range(1, 129)) AS n), x AS (SELECT (unnest(range(0, 1000)) + 0.5::DOUBLE) / 1000 AS s),
 h AS (SELECT tau, n, s, 1 - pow(1 - pow(s, n), 128 // n) AS hit FROM t, r, x), c AS (SELECT tau, n, sum(CASE WHEN s < tau THEN hit ELSE 1 - hit END) AS wrong FROM h GROUP BY tau, n)
 SELECT tau, (128 // arg_min(n, (round(wrong, 9), n)))::INT AS bands, arg_min(n, (round(wrong, 9), n))::INT AS "rows" FROM c GROUP BY tau""")
def band_choice(spark, sf):
    """Bands and rows of a band for each threshold; ten times the taxes of the line items serve as thresholds."""
    tau = load(spark, sf, "lineitem").where("l_tax > 0").select(F.round(F.col("l_tax").cast("double") * 10, 1).alias("tau")).distinct()
    chosen = F.udf(lambda t: tuple(int(x) for x in baselines.choose_bands(t)), "bands int, rows int").asNondeterministic()
    return tau.withColumn("c", chosen("tau")).select("tau", "c.bands", "c.rows")


_VEC = "WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings), s AS (SELECT a.vec_id AS a_id, b.vec_id AS b_id, list_cosine_similarity(a.e, b.e) AS sim FROM v a JOIN v b ON a.vec_id <> b.vec_id), r AS (SELECT *, row_number() OVER (PARTITION BY a_id ORDER BY round(sim, 9) DESC, b_id) AS n FROM s) SELECT a_id, b_id, round(sim, 6) AS sim FROM r WHERE n <= 5"


@query("dense_topk_embeddings", _VEC)
def dense_topk_embeddings(spark, sf):
    v = load(spark, sf, "embeddings").select(F.col("vec_id").alias("rec_id"), F.col("embedding").alias("vector"))
    return out(baselines.dense_top_k(v, None, 5))


query("dense_self_supervised")(lambda spark, sf: out(baselines.dense_self(prepared(spark, sf, measure="cosine"), 10)))


@query("dense_match_trained")
def dense_match_trained(spark, sf):
    w = W.items_in_docs(spark, sf)
    return out(baselines.dense_matched(prepared(spark, sf, measure="cosine"), W.split_matches(w.truth)[0], 10))


@query("tuned_threshold")
def tuned_threshold(spark, sf):
    w, p = W.items_in_docs(spark, sf), prepared(spark, sf, measure="cosine")
    th = estimate.recall_conditions(p, W.split_matches(w.truth)[0]).toPandas()
    tau, _ = baselines.tune_threshold(th["tau_max"].fillna(0).to_numpy(), 0.9)
    return out(hybrid_join(p, tau))


@query("tuned_nearest_k")
def tuned_nearest_k(spark, sf):
    w, p = W.items_in_docs(spark, sf), prepared(spark, sf, measure="cosine")
    th = estimate.recall_conditions(p, W.split_matches(w.truth)[0]).toPandas()
    k = baselines.tune_k_validated(th["k_min"].astype(float).fillna(np.inf).to_numpy(dtype=float), 0.9)[0] or 10
    return out(hybrid_join(p, k=k))


# cost and accuracy -----------------------------------------------------------------------------
@query("evaluation_items", f"""WITH {S.pairs(S.ITEMS, S.DOCS, 'word', 'tfidf', 'cosine')}, {_TRUTH}, res AS ({S.conditions('pairs', 0.0, 0.0, 10)})
 SELECT count(*) AS matches, count(r.a_id) AS found, (SELECT count(*) FROM res) AS pairs, round(count(r.a_id) / count(*), 6) AS recall, round(count(r.a_id) / (SELECT count(*) FROM res), 6) AS precision,
 round((SELECT count(*) FROM res) / least((SELECT count(*) FROM benchmark), (SELECT count(*) FROM documents)), 6) AS k_eff, round(1 - (SELECT count(*) FROM res)::DOUBLE / ((SELECT count(*) FROM benchmark) * (SELECT count(*) FROM documents)), 6) AS reduction
 FROM truth t LEFT JOIN res r USING (a_id, b_id)""")
def evaluation_items(spark, sf):
    w = W.items_in_docs(spark, sf)
    e = metrics.evaluate(hybrid_join(prepared(spark, sf, measure="cosine"), k=10), w.truth, *w.sizes())
    return e.select("matches", "found", "pairs", *[F.round(c, 6).alias(c) for c in ("recall", "precision", "k_eff", "reduction")])


@query("tradeoff_front_k", f"""WITH {S.pairs(S.ITEMS, S.DOCS, 'word', 'tfidf', 'cosine')}, {_TRUTH}, r AS (SELECT *, row_number() OVER (PARTITION BY a_id ORDER BY round(sim, 9) DESC, b_id) AS n FROM pairs),
 g AS (SELECT unnest([1.0, 2.0, 5.0, 10.0, 20.0])::DOUBLE AS threshold)
 SELECT threshold, count(*) AS pairs, round(count(*) / (SELECT count(*) FROM benchmark)::DOUBLE, 6) AS k_eff, round(count(t.a_id) / (SELECT count(*) FROM truth)::DOUBLE, 6) AS recall
 FROM g JOIN r ON n <= threshold LEFT JOIN truth t USING (a_id, b_id) GROUP BY threshold""")
def tradeoff_front_k(spark, sf):
    w = W.items_in_docs(spark, sf)
    t = metrics.tradeoff(classic.scored_pairs(prepared(spark, sf, measure="cosine")), w.truth, "k", [1, 2, 5, 10, 20], *w.sizes())
    return t.select("threshold", "pairs", *[F.round(c, 6).alias(c) for c in ("k_eff", "recall")])


_COPIES = f"WITH {S.pairs(S.DOCS, None, 'word', 'binary', 'jaccard')} SELECT a_id, b_id FROM pairs WHERE a_id < b_id AND round(sim, 9) >= 0.5"
query("truth_copies", _COPIES)(lambda spark, sf: W.docs_dedup(spark, sf).truth)
query("truth_items", f"WITH {_TRUTH} SELECT * FROM truth")(lambda spark, sf: W.items_in_docs(spark, sf).truth)
query("truth_pages", f"WITH {S.pairs(S.PAGES, None, 'word', 'binary', 'jaccard')} SELECT a_id, b_id FROM pairs WHERE a_id < b_id AND round(sim, 9) >= 0.4")(lambda spark, sf: W.pages_dedup(spark, sf).truth)
query("truth_parts", "SELECT x.p_partkey AS a_id, y.p_partkey AS b_id FROM part x JOIN part y USING (p_brand, p_name, p_type) WHERE x.p_partkey < y.p_partkey")(lambda spark, sf: W.parts_dedup(spark, sf).truth)


@query("match_split", f"WITH {_TRUTH} SELECT a_id, b_id, strpos('0123456789ab', substr(md5(a_id || '-' || b_id), 1, 1)) > 0 AS train FROM truth")
def match_split(spark, sf):
    train, test = W.split_matches(W.items_in_docs(spark, sf).truth)
    return train.withColumn("train", F.lit(True)).union(test.withColumn("train", F.lit(False)))


# experiment tables -----------------------------------------------------------------------------
def compare_methods(spark, sf, w: W.Workload, q: float = 1.0, k: int = 5) -> DataFrame:
    """One row a method: recall, pairs for each record, seconds.

    The methods share terms, dictionaries and equal sets: the first that needs some pays for them.
    """
    import time

    n_a, n_b = w.sizes()
    rows, shared = [], {}

    def run(name, make):
        start = time.time()
        r = metrics.evaluate(make(), w.truth, n_a, n_b).first()
        rows.append((w.name, name, r["recall"], r["pairs"], r["k_eff"], r["reduction"], time.time() - start))

    p = lambda weighting="tfidf", measure="cosine": prepare(w.a, w.b, TokenModel("word", weighting), measure, shared)
    run("threshold join", lambda: hybrid_join(p(), 0.22))
    run("nearest-k join", lambda: hybrid_join(p(), k=k))
    run("positional prefix join", lambda: classic.generalised_prefix_join(p("binary"), 0.2))
    run("high-value token blocking", lambda: baselines.high_value_blocking(p("tfidf", "jaccard")))
    run("minhash", lambda: baselines.minhash(p("binary", "jaccard"), 0.2))
    run("unsupervised hybrid", lambda: unsupervised.block(w.a, w.b, k, q, WORDS))
    return spark.createDataFrame(rows, "workload string, method string, recall double, pairs long, k_eff double, reduction double, seconds double")


query("compare_methods_items")(lambda spark, sf: compare_methods(spark, sf, W.items_in_docs(spark, sf)))
query("compare_methods_even_odd")(lambda spark, sf: compare_methods(spark, sf, W.docs_even_odd(spark, sf)))
query("clean_and_dirty")(lambda spark, sf: _dirty(spark, sf))


def _dirty(spark, sf):
    parts = []
    for flag in (False, True):
        w = W.docs_dirty(spark, sf, flag)
        p = prepare(w.a, w.b, TokenModel("word", "tfidf"), "cosine")
        parts.append(metrics.evaluate(hybrid_join(p, k=5), w.truth, *w.sizes()).withColumn("dirty", F.lit(flag)))
    return parts[0].unionByName(parts[1])


@query("approximate_and_exact")
def approximate_and_exact(spark, sf):
    """Pairs and measured quality of one join at several asked qualities."""
    from .plans.stages import cut

    p = prepared(spark, sf, measure="cosine")
    t = estimate.record(p)
    exact, probes = cut(hybrid_join(p, 0.05, 0.5, 10), "exact"), W.items(spark, sf).select(F.col("rec_id").alias("a_id"))
    parts, joins = None, {None: exact}  # each join is written, as it is read several times
    for q in (0.9, 0.95, 0.99, 1.0):
        rho = quality.rank_for(q, t, 0.05, 0.5, 10)
        got = joins[rho] = joins[rho] if rho in joins else cut(hybrid_join(p, 0.05, 0.5, 10, rho), "joined")
        row = quality.measure(exact, got, probes, 0.5).select(F.lit(q).alias("asked"), F.lit(rho).cast("long").alias("rank"), "quality").crossJoin(got.agg(F.count("*").alias("pairs")))
        parts = row if parts is None else parts.union(row)
    return parts


MODES = {"threshold": (0.3, 0.0, None), "relative": (0.0, 0.95, None), "nearest-k": (0.0, 0.0, 2), "hybrid": (0.25, 0.8, 2)}


def _modes_sql() -> str:
    rows = [f"SELECT '{name}' AS join, count(t.a_id) AS found, count(*) AS pairs FROM ({S.conditions('pairs', *c)}) LEFT JOIN truth t USING (a_id, b_id)" for name, c in MODES.items()]
    return f"WITH {S.pairs(S.ITEMS, S.DOCS, 'word', 'tfidf', 'cosine')}, {_TRUTH} " + " UNION ALL ".join(rows)


@query("failure_modes", _modes_sql())
def failure_modes(spark, sf):
    """One-condition joins and the hybrid condition on items in documents: matches found and pairs needed."""
    from .plans.stages import cut

    p, truth, rows = prepared(spark, sf, measure="cosine"), cut(W.items_in_docs(spark, sf).truth, "truth").withColumn("hit", F.lit(1)), None
    for name, c in MODES.items():
        row = hybrid_join(p, *c).join(truth, ["a_id", "b_id"], "left").agg(F.lit(name).alias("join"), F.count("hit").alias("found"), F.count("*").alias("pairs"))
        rows = row if rows is None else rows.union(row)
    return rows
