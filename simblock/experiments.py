"""The experiments: methods over workloads, one row a setting with its accuracy and cost.

Rows that hold seconds or memory have no SQL; what is exact in them is also a query of its own that has.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import baselines, classic, estimate, metrics, objectives, supervised, unsupervised
from . import sqltext as S
from . import workloads as W
from .join import JoinConfig, directed_join, hybrid_join
from .plans.stages import cut
from .plans.usage import measured
from .queries import _TRUTH, TUNED, WORDS, even, odd, prepared, query
from .sources import load
from .weights import TokenModel, prepare

TARGETS = (0.9, 0.98)
BUDGETS = {0.9: 5, 0.98: 10}  # pairs a record for the blocker that knows no matches
SIZES = (100, 1000, 10_000)
FRACTIONS = (0.25, 0.5, 1.0)
ROW = "workload string, target double, method string, setting string, recall double, pairs long, k_eff double, seconds double, peak_mb double"


# evaluation of single workloads ----------------------------------------------------------------
def _evaluation_sql(result: str, truth: str, smaller: str, lead: str = "") -> str:
    return f"""WITH {lead}res AS (SELECT DISTINCT a_id, b_id FROM ({result})), truth AS ({truth})
 SELECT count(*) AS matches, count(r.a_id) AS found, (SELECT count(*) FROM res) AS pairs, round(count(r.a_id)::DOUBLE / nullif(count(*), 0), 6) AS recall,
  round((SELECT count(*) FROM res)::DOUBLE / ({smaller}), 6) AS k_eff FROM truth t LEFT JOIN res r ON r.a_id = t.a_id AND r.b_id = t.b_id"""


def _evaluated(pairs: DataFrame, w: W.Workload) -> DataFrame:
    e = metrics.evaluate(pairs, w.truth, *w.sizes())
    return e.select("matches", "found", "pairs", F.round("recall", 6).alias("recall"), F.round("k_eff", 6).alias("k_eff"))


def _parity(src: str) -> str:
    return f"""WITH {S.pairs(src, None, 'word', 'binary', 'jaccard')} SELECT CASE WHEN a_id % 2 = 0 THEN a_id ELSE b_id END AS a_id, CASE WHEN a_id % 2 = 0 THEN b_id ELSE a_id END AS b_id
 FROM pairs WHERE a_id < b_id AND (a_id + b_id) % 2 = 1 AND round(sim, 9) >= 0.5"""


_LONG = S.DOCS + " WHERE n_chars >= 4000"
_PARTS = "SELECT p_partkey AS rec_id, concat_ws(' ', p_brand, p_name, p_type) AS text FROM part"


@query("long_documents", _evaluation_sql(S.hybrid(_LONG + " AND doc_id % 2 = 0", _LONG + " AND doc_id % 2 = 1", "word", "tfidf", "cosine", k=5), _parity(_LONG),
       f"SELECT least(count(*) FILTER (WHERE rec_id % 2 = 0), count(*) FILTER (WHERE rec_id % 2 = 1)) FROM ({_LONG})"))
def long_documents(spark, sf):
    w = W.long_docs(spark, sf)
    return _evaluated(hybrid_join(prepare(w.a, w.b, TokenModel(), "cosine"), k=5), w)


@query("short_strings", _evaluation_sql(S.hybrid(_PARTS, None, "word", "tfidf", "cosine", 0.5, k=3), "SELECT x.p_partkey AS a_id, y.p_partkey AS b_id FROM part x JOIN part y USING (p_brand, p_name, p_type) WHERE x.p_partkey < y.p_partkey", "SELECT count(*) FROM part"))
def short_strings(spark, sf):
    """Long lists and many ties: equal strings tie, and only the first k of them by id stay."""
    w = W.parts_dedup(spark, sf)
    return _evaluated(hybrid_join(prepare(w.a, None, TokenModel(), "cosine"), 0.5, k=3), w)


# fronts ----------------------------------------------------------------------------------------
_GRID = [0.02, 0.05, 0.1, 0.15, 0.2]
_K_GRID = [1, 2, 5, 10, 20]


@query("tradeoff_front_tau", f"""WITH {S.pairs(S.ITEMS, S.DOCS, 'word', 'tfidf', 'cosine')}, {_TRUTH}, g AS (SELECT unnest({_GRID})::DOUBLE AS threshold)
 SELECT threshold, count(p.a_id) AS pairs, round(count(p.a_id) / (SELECT count(*) FROM benchmark)::DOUBLE, 6) AS k_eff, round(count(t.a_id) / (SELECT count(*) FROM truth)::DOUBLE, 6) AS recall
 FROM g LEFT JOIN pairs p ON round(sim, 9) >= threshold LEFT JOIN truth t ON t.a_id = p.a_id AND t.b_id = p.b_id GROUP BY threshold""")
def tradeoff_front_tau(spark, sf):
    w = W.items_in_docs(spark, sf)
    t = metrics.tradeoff(classic.scored_pairs(prepared(spark, sf, measure="cosine")), w.truth, "tau", _GRID, *w.sizes())
    return t.select("threshold", "pairs", *[F.round(c, 6).alias(c) for c in ("k_eff", "recall")])


@query("linear_objective_front", f"""WITH {S.pairs(S.ITEMS, S.DOCS, 'word', 'tfidf', 'cosine')}, {_TRUTH}, r AS (SELECT *, row_number() OVER (PARTITION BY a_id ORDER BY round(sim, 9) DESC, b_id) AS n FROM pairs),
 g AS (SELECT unnest({_K_GRID})::DOUBLE AS threshold), c AS (SELECT unnest([0.001, 0.01, 0.05, 0.2])::DOUBLE AS c_k),
 f AS (SELECT threshold, count(*) / (SELECT count(*) FROM benchmark)::DOUBLE AS k_eff, count(t.a_id) / (SELECT count(*) FROM truth)::DOUBLE AS recall FROM g JOIN r ON n <= threshold LEFT JOIN truth t USING (a_id, b_id) GROUP BY threshold),
 o AS (SELECT *, row_number() OVER (PARTITION BY c_k ORDER BY round(recall - c_k * k_eff, 9) DESC, k_eff, threshold) AS place FROM f, c)
 SELECT c_k, threshold, round(k_eff, 6) AS k_eff, round(recall, 6) AS recall FROM o WHERE place = 1""")
def linear_objective_front(spark, sf):
    """Nearest-k joins: the k that recall less the cost of pairs asks for, by that cost."""
    w = W.items_in_docs(spark, sf)
    front = metrics.tradeoff(classic.scored_pairs(prepared(spark, sf, measure="cosine")), w.truth, "k", _K_GRID, *w.sizes())
    return metrics.best_by_cost(front, [0.001, 0.01, 0.05, 0.2]).select("c_k", "threshold", *[F.round(c, 6).alias(c) for c in ("k_eff", "recall")])


@query("supervised_cost_front")
def supervised_cost_front(spark, sf):
    """The supervised blocker under the linear objective, by the cost of a pair a record; seconds count a hundredth."""
    w = W.items_in_docs(spark, sf)
    train, test = (cut(x, "matches") for x in W.split_matches(w.truth))
    n_a, n_b = w.sizes()
    rows = []
    for c in (0.001, 0.05):
        u = measured(spark, lambda c=c: cut(supervised.block(w.a, w.b, train, objectives.linear(c), space=TUNED[3:], restarts=4, margins=(0.0, 0.1)), "pairs"))
        e = metrics.evaluate(u.result, test, n_a, n_b).first()
        rows.append((c, e["recall"], e["pairs"], e["k_eff"], u.seconds, objectives.cost(e["k_eff"], u.seconds)))
    return spark.createDataFrame(rows, "c_k double, recall double, pairs long, k_eff double, seconds double, cost double")


# recall by both directions, shared defaults ------------------------------------------------------
@query("union_recall", f"""WITH {S.pairs(S.ITEMS, S.DOCS, 'word', 'binary', 'jaccard')}, {_TRUTH},
 r AS (SELECT *, row_number() OVER (PARTITION BY a_id ORDER BY round(sim, 9) DESC, b_id) AS n_a, row_number() OVER (PARTITION BY b_id ORDER BY round(sim, 9) DESC, a_id) AS n_b,
  sim / max(sim) OVER (PARTITION BY a_id) AS r_a, sim / max(sim) OVER (PARTITION BY b_id) AS r_b FROM pairs),
 m AS (SELECT coalesce(round(sim, 9) >= 0.02 AND round(r_a, 9) >= 0.5 AND n_a <= 1, false) AS f, coalesce(round(sim, 9) >= 0.01 AND round(r_b, 9) >= 0.9 AND n_b <= 1, false) AS b FROM truth t LEFT JOIN r ON r.a_id = t.a_id AND r.b_id = t.b_id)
 SELECT 0.0::DOUBLE AS d, round(avg(CASE WHEN f OR b THEN 1.0 ELSE 0 END), 6) AS recall FROM m""")
def union_recall(spark, sf):
    w, p = W.items_in_docs(spark, sf), prepared(spark, sf, weighting="binary")
    turned = w.truth.select(F.col("b_id").alias("a_id"), F.col("a_id").alias("b_id"))
    forward, backward = estimate.recall_conditions(p, w.truth), estimate.recall_conditions(p.flipped(), turned)
    return estimate.union_recall(forward, backward, (0.02, 0.5, 1), (0.01, 0.9, 1)).select("d", F.round("recall", 6).alias("recall"))


def _ranked_truth(pairs: str, truth: str, name: str) -> str:
    return f"""SELECT '{name}' AS w, p.sim, p.n FROM ({truth}) t LEFT JOIN (SELECT *, row_number() OVER (PARTITION BY a_id ORDER BY round(sim, 9) DESC, b_id) AS n FROM (WITH {pairs} SELECT * FROM pairs)) p ON p.a_id = t.a_id AND p.b_id = t.b_id"""


_DEFAULTS = f"""WITH m AS ({_ranked_truth(S.pairs(S.ITEMS, S.DOCS, 'word', 'tfidf', 'cosine'), f'WITH {_TRUTH} SELECT * FROM truth', 'items')}
 UNION ALL {_ranked_truth(S.pairs(S.EVEN, S.ODD, 'word', 'tfidf', 'cosine'), _parity(S.DOCS), 'even_odd')}),
 x AS (SELECT unnest([0.9, 0.98])::DOUBLE AS target), i AS (SELECT unnest(range(0, 101)) AS i),
 tau AS (SELECT target, i FROM (SELECT target, i, w, avg(CASE WHEN round(sim, 9) >= round(i / 100.0::DOUBLE, 9) THEN 1.0 ELSE 0 END) AS recall FROM m, x, i GROUP BY ALL) GROUP BY target, i HAVING min(recall) >= target - 1e-12),
 k AS (SELECT target, i FROM (SELECT target, i, w, avg(CASE WHEN n <= i THEN 1.0 ELSE 0 END) AS recall FROM m, x, i WHERE i > 0 GROUP BY ALL) GROUP BY target, i HAVING min(recall) >= target - 1e-12)
 SELECT target, (SELECT max(i) / 100.0::DOUBLE FROM tau WHERE tau.target = x.target) AS tau, (SELECT min(i)::DOUBLE FROM k WHERE k.target = x.target) AS k FROM x"""


@query("global_default_settings", _DEFAULTS)
def global_default_settings(spark, sf):
    """The highest threshold (in hundredths) and the lowest k (up to 100) that reach a recall on two workloads at once."""
    tau, k = {}, {}
    for w in (W.items_in_docs(spark, sf), W.docs_even_odd(spark, sf)):
        theta = cut(estimate.recall_conditions(prepare(w.a, w.b, TokenModel(), "cosine"), w.truth), "theta")
        tau[w.name] = baselines.recall_curve(theta, "tau_max", [i / 100 for i in range(100, -1, -1)])
        k[w.name] = baselines.recall_curve(theta, "k_min", list(range(1, 101)))
    return spark.createDataFrame([(t, baselines.global_default(tau, t), baselines.global_default(k, t)) for t in TARGETS], "target double, tau double, k double")


# tuned baselines -------------------------------------------------------------------------------
def _sims(p, matches) -> np.ndarray:
    return estimate.recall_conditions(p, matches).select("tau_max").toPandas()["tau_max"].fillna(0).to_numpy()


@query("tuned_minhash")
def tuned_minhash(spark, sf):
    w, p = W.items_in_docs(spark, sf), prepared(spark, sf, weighting="binary")
    tau, bands = baselines.tuned_bands(_sims(p, W.split_matches(w.truth)[0]), 0.9)
    return baselines.minhash(p, tau, bands=bands)


@query("tuned_threshold_over_models")
def tuned_threshold_over_models(spark, sf):
    """Word models: the weighting, measure and threshold that reach the recall with fewest pairs."""
    w = W.items_in_docs(spark, sf)
    _, _, _, tau, p = baselines.tuned_threshold_join(w.a, w.b, W.split_matches(w.truth)[0], 0.9, TUNED)
    return hybrid_join(p, tau).select("a_id", "b_id", F.round("sim", 6).alias("sim"))


@query("tuned_dense")
def tuned_dense(spark, sf):
    w, p = W.items_in_docs(spark, sf), prepared(spark, sf, measure="cosine")
    return baselines.dense_tuned(baselines.encode_self(p), W.split_matches(w.truth)[0], 0.9)[0].select("a_id", "b_id", F.round("sim", 6).alias("sim"))


# tables ----------------------------------------------------------------------------------------
def results_by_target(spark: SparkSession, w: W.Workload, targets: tuple = TARGETS, most: int | None = None, runs: int = 1, restarts: int = 4) -> DataFrame:
    """Each method set up for a recall: on test matches its recall, and pairs, mean seconds and peak memory.

    Tuned methods and the supervised blocker see training matches only (``most`` of them); seconds are
    of tuning and running, with terms and dictionaries made anew for each. The unsupervised blocker gets a budget.
    """
    train, test = (cut(x, "matches") for x in W.split_matches(w.truth, most))
    n_a, n_b = w.sizes()
    sets = lambda weighting="tfidf", measure="cosine": prepare(w.a, w.b, TokenModel("word", weighting), measure)

    def threshold(target):
        p = sets()
        tau, _ = baselines.tune_threshold(_sims(p, train), target)
        return hybrid_join(p, tau), f"tau {tau:.4f}"

    def nearest(target):
        p = sets()
        ranks = estimate.recall_conditions(p, train).select(F.col("k_min").cast("double")).toPandas()["k_min"].fillna(np.inf).to_numpy()
        k = baselines.tune_k_validated(ranks, target)[0] or int(np.max(ranks[np.isfinite(ranks)], initial=1))
        return hybrid_join(p, k=k), f"k {k}"

    def minhash(target):
        p = sets("binary", "jaccard")
        tau, bands = baselines.tuned_bands(_sims(p, train), target)
        return baselines.minhash(p, tau, bands=bands), f"bands {bands[0]} of {bands[1]}"

    def dense(encode):
        def run(target):
            pairs, k = baselines.dense_tuned(encode(sets()), train, target)
            return pairs, f"k {k}"

        return run

    def blocker(target):
        return unsupervised.block(w.a, w.b, BUDGETS.get(target, 10), space=WORDS), f"budget {BUDGETS.get(target, 10)}"

    def tuned(target):
        told: list = []
        pairs = supervised.block(w.a, w.b, train, objectives.recall_target(target), space=TUNED[2:], restarts=restarts, margins=(0.0, 0.1, 0.3), explain=told)
        return pairs, "; ".join(c.describe() for c in told)

    methods = {
        "threshold join, tuned": threshold, "nearest-k join, tuned": nearest, "minhash, tuned": minhash, "high-value token blocking": lambda t: (baselines.high_value_blocking_pruned(sets("tfidf", "jaccard")), "none"),
        "dense self-supervised stand-in, tuned": dense(baselines.encode_self), "dense match-trained stand-in, tuned": dense(lambda p: baselines.encode_matched(p, train)),
        "unsupervised hybrid": blocker, "supervised hybrid": tuned,
    }
    rows = []
    for target in targets:
        for name, method in methods.items():
            def work(method=method, target=target):
                pairs, setting = method(target)
                return cut(pairs.select("a_id", "b_id"), "pairs"), setting

            u = measured(spark, work, runs)
            e = metrics.evaluate(u.result[0], test, n_a, n_b).first()
            rows.append((w.name, target, name, u.result[1], e["recall"], e["pairs"], e["k_eff"], u.seconds, u.peak_bytes / 1e6))
    return spark.createDataFrame(rows, ROW)


query("results_at_90")(lambda spark, sf: results_by_target(spark, W.items_in_docs(spark, sf), TARGETS[:1]))
query("results_at_98")(lambda spark, sf: results_by_target(spark, W.items_in_docs(spark, sf), TARGETS[1:]))


@query("training_sizes")
def training_sizes(spark, sf):
    """Recall on test matches and pairs by the number of training matches; a size beyond what there is repeats the last run."""
    w = W.docs_dedup(spark, sf)
    n_a, n_b = w.sizes()
    test, rows, last = cut(W.split_matches(w.truth)[1], "matches"), [], None
    for size in SIZES:
        train = cut(W.split_matches(w.truth, size)[0], "matches")
        given = train.count()
        if last is None or last[0] != given:
            u = measured(spark, lambda train=train: cut(supervised.block(w.a, None, train, objectives.recall_target(0.9), space=TUNED[3:], restarts=4, margins=(0.0, 0.1)), "pairs"))
            e = metrics.evaluate(u.result, test, n_a, n_b).first()
            last = (given, e["recall"], e["pairs"], e["k_eff"], u.seconds)
        rows.append((size, *last))
    return spark.createDataFrame(rows, "asked int, training long, recall double, pairs long, k_eff double, seconds double")


# scalability -----------------------------------------------------------------------------------
def _fraction_sql(part: float) -> str:
    src = f"{S.DOCS} WHERE CAST('0x' || substr(md5(doc_id::VARCHAR), 1, 8) AS BIGINT) < {int(part * (1 << 32))}"
    return f"SELECT {part}::DOUBLE AS part, (SELECT count(*) FROM ({src})) AS records, (SELECT count(*) FROM ({S.hybrid(src, None, 'word', 'binary', 'jaccard', 0.5)})) AS pairs"


@query("scalability_pairs", " UNION ALL ".join(_fraction_sql(x) for x in FRACTIONS))
def scalability_pairs(spark, sf):
    """Records and result pairs of the threshold join on growing shares of the documents."""
    out = None
    for part in FRACTIONS:
        df = W.fraction(W.docs(spark, sf), "rec_id", part)
        p = prepare(df, None, TokenModel("word", "binary"), "jaccard")
        row = hybrid_join(p, 0.5).agg(F.lit(part).alias("part"), F.lit(p.n_a).cast("long").alias("records"), F.count("*").alias("pairs"))
        out = row if out is None else out.unionAll(row)
    return out


@query("scalability")
def scalability(spark, sf):
    """Seconds and peak memory of each method on growing shares of the documents, sets made anew each time."""
    rows = []
    for part in FRACTIONS:
        df = W.fraction(W.docs(spark, sf), "rec_id", part)
        sets = lambda weighting="tfidf", measure="jaccard", df=df: prepare(df, None, TokenModel("word", weighting), measure)
        methods = {
            "threshold join": lambda: hybrid_join(sets("binary"), 0.5),
            "nearest-k join": lambda: hybrid_join(sets("tfidf", "cosine"), k=5),
            "token blocking": lambda: baselines.token_blocking(sets("binary")),
            "high-value token blocking": lambda: baselines.high_value_blocking(sets()),
            "high-value token blocking, pruned": lambda: baselines.high_value_blocking_pruned(sets()),
            "minhash": lambda: baselines.minhash(sets("binary"), 0.5),
            "unsupervised hybrid": lambda df=df: unsupervised.block(df, None, 5),
        }
        records = df.count()
        for name, make in methods.items():
            u = measured(spark, lambda make=make: make().count())
            rows.append((name, part, records, u.result, u.seconds, u.peak_bytes / 1e6))
    return spark.createDataFrame(rows, "method string, part double, records long, pairs long, seconds double, peak_mb double")


# filters ---------------------------------------------------------------------------------------
def _kth_sql(k: int, low: float) -> str:
    size, prefix = "b.total >= t * a.total - 1e-9 AND b.total <= a.total / t + 1e-9", "a.suf >= t * a.total - 1e-9 AND b.suf >= t * b.total - 1e-9"
    suffix = "b.suf >= t * (a.total + b.pre) - 1e-9 AND b.suf <= a.suf / t - a.pre - b.pre + 1e-9"
    place = "least(a.suf, b.suf) >= t / (1 + t) * (a.total + b.total) - 1e-9"
    tests = {"prefix": "true", "size": size, "suffix": suffix, "positional": place, "all": f"{size} AND {suffix} AND {place}"}
    flags = ", ".join(f"{test} AS f_{name}" for name, test in tests.items())
    rows = " UNION ALL ".join(f"SELECT '{name}' AS filters, count(*) AS entries, count(DISTINCT (a_id, b_id)) AS pairs FROM m WHERE f_{name}" for name in tests)
    return f"""WITH {S.pairs(S.ITEMS, S.DOCS, 'word', 'binary', 'jaccard')}, kth AS (SELECT a_id, sim FROM (SELECT *, row_number() OVER (PARTITION BY a_id ORDER BY sim DESC) AS n FROM pairs) WHERE n = {k}),
 ra AS (SELECT w.*, greatest(coalesce(kth.sim, 0), {low}::DOUBLE) AS t FROM ({S.running('jaccard', 'a')}) w LEFT JOIN kth ON kth.a_id = w.rec_id), rb AS ({S.running('jaccard', 'b')}),
 m AS (SELECT a.rec_id AS a_id, b.rec_id AS b_id, {flags} FROM ra a JOIN rb b ON a.token = b.token AND {prefix}) {rows}"""


@query("filter_ablation_nearest_k", _kth_sql(5, 0.01))
def filter_ablation_nearest_k(spark, sf):
    return classic.counts_at_kth(prepared(spark, sf, weighting="binary"), 5, 0.01)


def filter_seconds(spark: SparkSession, sf: str, measures: tuple = ("jaccard", "cosine")) -> DataFrame:
    """Threshold and nearest-k joins under each set of filters: the same pairs, in which time."""
    rows = []
    for measure in measures:
        p = prepared(spark, sf, weighting="binary", measure=measure)
        for join, options in (("threshold", {"tau": 0.1 if measure == "jaccard" else 0.25}), ("nearest-k", {"k": 5})):
            for name, filters in classic.ABLATION.items():
                u = measured(spark, lambda: directed_join(p, JoinConfig(**options, filters=frozenset(filters))).count())
                rows.append((measure, join, name, u.result, u.seconds))
    return spark.createDataFrame(rows, "measure string, join string, filters string, pairs long, seconds double")


for _m in ("jaccard", "cosine"):
    query(f"filter_ablation_seconds_{_m}")(lambda spark, sf, m=_m: filter_seconds(spark, sf, (m,)))
