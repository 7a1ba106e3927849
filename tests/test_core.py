import numpy as np
from pyspark.sql import functions as F

from simblock.baselines import choose_bands, tune_k
from simblock.estimate import checkpoint_levels
from simblock.unsupervised import split_budget


def test_budget_split():
    assert split_budget(1363, 3226, 10) == (5, 2)
    assert split_budget(40, 1000, 10) == (10, 0)
    assert split_budget(500, 500, 10) == (5, 5)


def test_checkpoint_levels():
    assert checkpoint_levels(33) == [*range(1, 12), 13, 15, 17, 19, 21, 24, 27, 30, 33]


def test_bands_fit_the_permutations():
    for tau in (0.1, 0.5, 0.8):
        b, r = choose_bands(tau)
        assert b * r <= 128


def test_tune_k():
    import numpy as np

    assert tune_k(np.array([1, 1, 2, 9, np.inf]), 0.8) == 9


def test_ngrams_count_code_points(spark):
    from simblock.tokens import ngrams

    texts = [None, "", " ", "a", "ABC", "a  b\tC d", "zß😀日本語", "x" * 50_000]
    rows = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "rec_id int, text string")
    got = dict(rows.select("rec_id", ngrams(rows.text)).collect())
    for i, t in enumerate(texts):
        c = " ".join((t or "").lower().split())
        want = [] if not c else [c] if len(c) <= 3 else [c[j : j + 3] for j in range(len(c) - 2)]
        assert got[i] == want


def test_shared_preparation_changes_nothing(spark):
    from simblock.weights import TokenModel, prepare

    a = spark.createDataFrame([(1, "red blue blue"), (2, "green red"), (3, None)], "rec_id long, text string")
    b = spark.createDataFrame([(7, "blue sky"), (8, "")], "rec_id long, text string")
    shared = {}
    for measure in ("jaccard", "cosine", "overlap"):
        one, two = prepare(a, b, TokenModel(), measure, shared), prepare(a, b, TokenModel(), measure)
        for x, y in ((one.a, two.a), (one.b, two.b)):
            assert sorted(x.drop("key").collect()) == sorted(y.drop("key").collect())
        assert (one.n_a, one.n_b, one.measure) == (3, 2, measure)


def test_dense_neighbours_against_brute_force(spark):
    import numpy as np

    from simblock.baselines import dense_top_k

    rng = np.random.default_rng(5)
    x = rng.normal(size=(60, 8))
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "rec_id long, vector array<double>")
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    sims = np.round(unit @ unit.T, 9)
    np.fill_diagonal(sims, -2)
    want = {(i, int(j)) for i in range(60) for j in np.lexsort((np.arange(60), -sims[i]))[:3]}
    assert {(r.a_id, r.b_id) for r in dense_top_k(df, None, 3, block=25).collect()} == want
    left, right = df.where("rec_id < 20"), df.where("rec_id >= 20")
    want = {(i, 20 + int(j)) for i in range(20) for j in np.lexsort((np.arange(40), -sims[i, 20:]))[:3]}
    assert {(r.a_id, r.b_id) for r in dense_top_k(left, right, 3, block=25).collect()} == want


def test_hybrid_join_equals_conditions_over_all_pairs(spark, sf):
    from simblock import workloads as W
    from simblock.classic import naive_hybrid
    from simblock.join import hybrid_join
    from simblock.weights import TokenModel, prepare

    for model, measure in ((TokenModel("word", "tfidf"), "cosine"), (TokenModel("trigram", "binary"), "dice")):
        p = prepare(W.items(spark, sf), W.docs(spark, sf), model, measure)
        pairs = [{(r.a_id, r.b_id) for r in f(p, 0.02, 0.6, 3).collect()} for f in (hybrid_join, naive_hybrid)]
        assert pairs[0] == pairs[1] and pairs[0]


def test_candidate_bound_loses_no_pair(spark, sf):
    from simblock import workloads as W
    from simblock.classic import naive_hybrid
    from simblock.join import hybrid_join
    from simblock.weights import TokenModel, prepare

    dedup = prepare(W.docs(spark, sf), None, TokenModel("word", "tfidf"), "jaccard")
    cross = prepare(W.items(spark, sf), W.docs(spark, sf), TokenModel("word", "tfidf"), "overlap")
    for p, options in ((dedup, {"tau": 0.3}), (cross, {"k": 4}), (cross, {"tau_r": 0.7})):
        got, want = ({(r.a_id, r.b_id): round(r.sim, 6) for r in f(p, **options).collect()} for f in (hybrid_join, naive_hybrid))
        assert got == want and want


def test_trajectories_follow_the_whole_walk(spark, sf, monkeypatch):
    import inspect

    from simblock import estimate
    from simblock.cutoff import candidate_log
    from simblock.queries import prepared

    assert inspect.signature(estimate.record).parameters["rank_cap"].default is None
    p = prepared(spark, sf, measure="cosine")
    monkeypatch.setattr(estimate, "KEPT", 3)
    t = estimate.record(p, 20)
    log = candidate_log(estimate.sample_probes(p.a, 20), p).groupBy("a_id").agg({"sim": "sum", "*": "count"}).collect()
    whole, many = ({r["a_id"]: r[c] for r in log} for c in ("sum(sim)", "count(1)"))
    assert max(many.values()) > 3
    for i, s in zip(t.probes, t.exact_sums(0.0, 0.0, None)):
        assert abs(s - whole.get(i, 0)) < 1e-6


def test_sum_bounds_count_bins_from_the_threshold_on(spark, sf):
    from simblock import estimate
    from simblock.cutoff import candidate_log
    from simblock.queries import prepared

    p = prepared(spark, sf, measure="cosine")
    t = estimate.record(p, 20)
    log = candidate_log(estimate.sample_probes(p.a, 20), p).select("a_id", "sim").toPandas()
    last = len(t.levels) - 1
    for tau in (0.0, 0.05, 0.105):
        edge = 0.11 if tau == 0.105 else tau
        want = log[log["sim"] >= edge - 1e-11].groupby("a_id")["sim"].sum()
        for i, s in zip(t.probes, t.sum_bounds(tau, 0.0, None, last)):
            assert abs(s - want.get(i, 0.0)) < 1e-6


def test_pruned_high_value_blocking_gives_the_same_pairs(spark, sf):
    from simblock.baselines import high_value_blocking, high_value_blocking_pruned
    from simblock.queries import prepared

    p = prepared(spark, sf, measure="jaccard")
    plain, pruned = ({tuple(r) for r in f(p).collect()} for f in (high_value_blocking, high_value_blocking_pruned))
    assert plain == pruned and plain


def test_sql_ngrams_are_those_of_the_tokeniser(spark):
    from simblock import functions
    from simblock.tokens import ngrams

    functions.register(spark)
    df = spark.createDataFrame([("A  b\tcd",), (" ",), ("",), (None,), ("ab",), ("  Spark  joins ",)], "t string")
    got = df.select(F.expr("token_ngrams(t, 3)").alias("x"), ngrams(F.col("t")).alias("y")).collect()
    assert all(r["x"] == r["y"] for r in got)


def test_weighted_kernel_with_large_keys_and_empty_sets(spark):
    from simblock.join import verify

    rng = np.random.default_rng(4)
    sets = [({}, 1.0)] + [({int(k): float(w) for k, w in zip(np.sort(rng.choice(40, 12, replace=False)) * (1 << 56 if i % 2 else 1), rng.random(12))}, 1.0) for i in range(9)]
    rows = [(i, list(s), list(s.values()), float(sum(s.values()))) for i, (s, _) in enumerate(sets)]
    side = lambda x: spark.createDataFrame(rows, f"{x}_id long, {x}_keys array<long>, {x}_ws array<double>, {x}_total double")
    pairs = spark.createDataFrame([(i, j) for i in range(10) for j in range(10) if i + j], "a_id long, b_id long")
    for r in verify(pairs, side("a"), side("b"), "overlap").collect():
        a, b = sets[r.a_id][0], sets[r.b_id][0]
        assert abs(r.sim - sum(min(w, b[k]) for k, w in a.items() if k in b)) < 1e-9


def test_partial_similarity_equals_brute_force(spark):
    """Every measure, sets longer than a stride, disjoint sets, and thresholds that stop early or never."""
    import random

    from simblock import verification
    from simblock.join import arrays
    from simblock.weights import TokenModel, prepare

    draw = random.Random(3)
    vocabulary = [f"w{i}" for i in range(120)]
    texts = [" ".join(draw.choices(vocabulary, k=n)) for n in (1, 3, 40, 90, 150, 60, 60)] + ["solo", "", None]
    texts.append(texts[3])
    a = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "rec_id long, text string")
    for measure in ("jaccard", "cosine", "dice", "overlap"):
        p = prepare(a, None, TokenModel("word", "tfidf"), measure)
        sets = {}
        for r in p.a.collect():
            sets.setdefault(r["rec_id"], {})[r["key"]] = (r["w"], r["total"])
        want = {}
        for i, x in sets.items():
            for j, y in sets.items():
                if i < j and x.keys() & y.keys():
                    inter = sum(x[k][0] * y[k][0] if measure == "cosine" else min(x[k][0], y[k][0]) for k in x.keys() & y.keys())
                    tx, ty = next(iter(x.values()))[1], next(iter(y.values()))[1]
                    want[i, j] = {"jaccard": inter / (tx + ty - inter), "dice": 2 * inter / (tx + ty)}.get(measure, inter)
        for tau in (0.0, 0.25, 0.6, 1e9):
            got = verification.partial_similarity(verification.first_shared(p), arrays(p.a, "a"), arrays(p.b, "b"), measure, tau).collect()
            assert {(r["a_id"], r["b_id"]) for r in got} == set(want)
            for r in got:
                s = want[r["a_id"], r["b_id"]]
                assert abs(r["sim"] - (s if round(s, 9) >= tau else 0.0)) < 1e-9


def test_k_margin_and_margins_are_the_least_that_hold():
    from simblock.baselines import tune_k_validated, tune_threshold

    assert tune_k_validated(np.ones(30), 0.9) == (1, 0)
    assert tune_k_validated(np.array([1.0, 2.0]), 0.5) == (1, 0)
    assert tune_k_validated(np.full(9, np.inf), 0.9)[0] is None
    spread = np.arange(1, 61, dtype=float)
    k, d = tune_k_validated(spread, 0.9)
    assert d > 0 and k == 54 + d
    assert tune_threshold(np.full(30, 0.5), 0.9) == (0.5, 0.0)


def test_supervised_evaluation_against_counting():
    """One side, one configuration: recall from conditions, pairs from the trajectories, no seconds at cost 0.

    Pairs are an upper bound by whole bins: at 0.99 of 0.505 the bin from 0.49 on counts, with 0.495 in it.
    """
    import pandas as pd

    from simblock.estimate import Trajectories
    from simblock.supervised import Point, Side, evaluate

    sims = np.array([[0.905, 0.305, 0.0], [0.505, 0.495, 0.105]])
    cells = np.zeros((2, 1, 100))
    for i, row in enumerate(sims):
        for s in row[row > 0]:
            cells[i, 0, int(s * 100)] += 1
    counts = np.cumsum(cells[:, :, ::-1], axis=2)[:, :, ::-1]
    t = Trajectories([1, 2], 1.0, 1.0, np.array([5]), counts, counts * 0, sims, [(np.zeros(1), np.ones(1), 5.0)] * 2, np.ones(2), "jaccard")
    theta = pd.DataFrame({"a_id": [1, 2, 2], "b_id": [7, 8, 9], "d": 0.0, "tau_max": [0.905, 0.495, np.nan], "tau_r_max": [1.0, 0.98, np.nan], "k_min": [1, 2, np.nan], "rank_min": [1, 4, np.nan]})
    side = Side([None], [t], [theta])
    for point, want in (((0.3, 0.0, 5, None), (2 / 3, 4)), ((0.3, 0.0, 1, None), (1 / 3, 2)), ((0.3, 0.99, 5, None), (1 / 3, 3)), ((0.3, 0.0, 5, 3), (1 / 3, None)), ((0.0, 0.0, 0, None), (0.0, 0))):
        recall, k_eff, seconds = evaluate([side], (Point(0, *point),), np.arange(3), 0.0, 2, 0.0)
        assert abs(recall - want[0]) < 1e-12 and seconds == 0
        assert want[1] is None or k_eff == want[1] / 2


def test_supervised_blocker_tunes_a_finite_rank_and_measures_seconds(spark, sf):
    from simblock import objectives, supervised
    from simblock import workloads as W
    from simblock.queries import TUNED

    w, told = W.items_in_docs(spark, sf), []
    # an objective that only seconds decide once a match is found asks for the shortest walk
    objective = lambda recall, k_eff, seconds: (recall > 0, -seconds)
    pairs = supervised.block(w.a, w.b, w.truth, objective, space=TUNED[3:], restarts=2, margins=(0.0,), q=0.5, seconds_per_entry=1e-3, explain=told).collect()
    assert pairs and all(c.rho is None or c.rho >= 1 for c in told)
    assert any(c.rho is not None for c in told)
    p = objectives.linear(0.1)
    assert p(0.9, 2.0, 0.0) == 0.9 - 0.2


def test_usage_sees_stage_memory_and_mean_seconds(spark):
    from simblock.plans.usage import measured

    u = measured(spark, lambda: spark.range(200_000).groupBy((F.col("id") % 50_000).alias("g")).count().orderBy("count", "g").count(), runs=2)
    assert u.result == 50_000 and u.runs == 2 and u.seconds > 0 and u.peak_bytes > 0


def test_dense_tuned_finds_the_least_k(spark):
    from simblock.baselines import dense_tuned

    rng = np.random.default_rng(8)
    x = rng.normal(size=(40, 6))
    y = x + rng.normal(size=x.shape) * 0.01
    frame = lambda m: spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(m)], "rec_id long, vector array<double>")
    matches = spark.createDataFrame([(i, i) for i in range(40)], "a_id long, b_id long")
    pairs, k = dense_tuned((frame(x), frame(y)), matches, 0.9)
    assert k == 1 and {(r.a_id, r.b_id) for r in pairs.collect()} == {(i, i) for i in range(40)}
    shifted = spark.createDataFrame([(2 * i, 2 * i + 1) for i in range(20)], "a_id long, b_id long")
    both = np.empty((40, 6))
    both[0::2], both[1::2] = x[:20], y[:20]
    pairs, k = dense_tuned((frame(both), None), shifted, 0.9)
    assert k == 1 and {(2 * i, 2 * i + 1) for i in range(20)} <= {(r.a_id, r.b_id) for r in pairs.collect()}


def test_points_by_cost(spark):
    from simblock.metrics import best_by_cost

    front = spark.createDataFrame([(1.0, 1.0, 0.5), (2.0, 2.0, 0.8), (5.0, 5.0, 0.9), (9.0, 5.0, 0.9)], "threshold double, k_eff double, recall double")
    got = {r.c_k: r.threshold for r in best_by_cost(front, [0.0, 0.1, 1.0]).collect()}
    assert got == {0.0: 5.0, 0.1: 2.0, 1.0: 1.0}


def test_every_option_of_the_join_on_ties_and_swapped_sides(spark):
    """Relative threshold 1, ties at k, k of 0, and both directions, against all pairs."""
    from simblock.classic import naive_hybrid
    from simblock.join import hybrid_join
    from simblock.weights import TokenModel, prepare

    texts = ["red blue"] * 4 + ["red blue green", "green", "", None, "blue sky red"]
    a = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "rec_id long, text string")
    b = spark.createDataFrame([(100 + i, t) for i, t in enumerate(texts[::-1] + ["sky", "red"])], "rec_id long, text string")
    p = prepare(a, b, TokenModel("word", "binary"), "jaccard")
    for side, options in ((p, {"tau_r": 1.0}), (p, {"tau": 0.5, "tau_r": 0.9, "k": 3}), (p.flipped(), {"tau": 1.0}), (p.flipped(), {"k": 2})):
        got, want = ({(r.a_id, r.b_id): round(r.sim, 6) for r in f(side, **options).collect()} for f in (hybrid_join, naive_hybrid))
        assert got == want and got
    assert hybrid_join(p, k=0).count() == 0
    best = sorted((r.a_id, r.b_id) for r in hybrid_join(p, tau=0.9, k=2).where("a_id = 0").collect())
    assert best == [(0, 105), (0, 106)]  # four partners tie at similarity 1


def test_lone_tokens_have_keys_of_their_own_in_order(spark, monkeypatch):
    """Both ways of coding give the same weights, order and sums, and a key stands for one token on both sides."""
    from simblock import weights

    a = spark.createDataFrame([(1, "red zebra apple blue"), (2, "red kiwi éclair zoo"), (3, None)], "rec_id long, text string").repartition(2)
    b = spark.createDataFrame([(1, "blue sky moon"), (2, "owl")], "rec_id long, text string")
    found = []
    for most in (weights.VOCABULARY, 0):
        monkeypatch.setattr(weights, "VOCABULARY", most)
        p = weights.prepare(a, b, weights.TokenModel(), "jaccard")
        assert p.vocabulary.count() == p.vocabulary.select("key").distinct().count() == p.vocabulary.select("token").distinct().count() == 10
        found.append([sorted((r.rec_id, r.token, r.pos, round(r.w, 9), round(r.pre, 9), round(r.suf, 9), r.df) for r in x.join(p.vocabulary, "key").collect()) for x in (p.a, p.b)])
        assert len(found[-1][0]) == 8 and len(found[-1][1]) == 4
    assert found[0] == found[1]


def test_small_side_and_blocks_give_the_same_pairs(spark, sf, monkeypatch):
    """A side sent to every task, blocks of few tokens and chunks of few pairs lose and add nothing."""
    from simblock import join, verification
    from simblock import workloads as W
    from simblock.classic import naive_hybrid
    from simblock.queries import prepared
    from simblock.weights import Prepared

    p = prepared(spark, sf, W.items, W.docs, measure="dice")
    pairs = lambda df: {(r.a_id, r.b_id): round(r.sim, 6) for r in df.collect()}
    want, wide = pairs(naive_hybrid(p, 0.02, 0.5, 4)), pairs(verification.partial_pairs(p, 0.1))
    monkeypatch.setattr(join, "CHUNK", 5_000)
    part = Prepared(p.a.where("rec_id % 2 = 0"), p.b, p.vocabulary, p.n_a, p.n_b, p.measure, False)
    assert join.smaller(part) is None and pairs(join.hybrid_join(part, 0.02, 0.5, 4)) == {k: s for k, s in want.items() if k[0] % 2 == 0}
    assert join.smaller(p) == "a" and pairs(join.hybrid_join(p, 0.02, 0.5, 4)) == want
    turned = p.flipped()
    assert pairs(join.hybrid_join(turned, 0.02, 0.5, 4)) == pairs(naive_hybrid(turned, 0.02, 0.5, 4))
    monkeypatch.setattr(join, "SMALL", 0)
    monkeypatch.setattr(join, "BLOCK", 9_000)
    assert join.smaller(p) is None and pairs(join.hybrid_join(p, 0.02, 0.5, 4)) == want
    assert pairs(verification.partial_pairs(p, 0.1)) == wide and wide


def test_queries_of_fixed_values_read_given_tables(spark, sf):
    """Spark scans a given table for each of them, and two empty sets have no Jaccard similarity."""
    from simblock import functions
    from simblock.catalog import QUERIES

    for name, table in (("band_choice", "lineitem"), ("cosine_prefix_growth", "documents"), ("op_registered_functions", "documents")):
        df = QUERIES[name](spark, sf)
        assert any(f.endswith(f"/{table}.parquet") for f in df.inputFiles()) and df.count() > 1, name
    functions.register(spark)
    assert spark.sql("SELECT set_jaccard(token_words(''), token_words('-')) AS j").first().j is None


def test_ngrams_of_both_forms_and_streams_agree(spark, tmp_path, monkeypatch):
    """n-grams cut in Python are those of the column, and a join with a small side writes no sets of the other."""
    import os

    from simblock import weights
    from simblock.join import hybrid_join
    from simblock.tokens import term_counts

    texts = [None, "", " ", "a", "ABC", "a  b\tC d", "zß😀日本語", "abcabcabc", "x" * 5_000]
    rows = spark.createDataFrame([(i, t) for i, t in enumerate(texts)] + [(4, "abcd")], "rec_id int, text string")
    want = sorted(tuple(r) for r in term_counts(rows, "trigram").select("rec_id", "token", "tf").collect())
    for single, table in ((False, 1 << 25), (False, 0)):
        monkeypatch.setattr(weights, "TABLE", table)
        monkeypatch.setattr(weights, "TOKENS", 9)
        got = weights.unpacked(weights.counted(weights.token_lists(rows, "trigram", single), 3)).select("rec_id", "token", "tf")
        assert sorted(tuple(r) for r in got.collect()) == want
    folder = str(tmp_path)
    monkeypatch.setattr("simblock.plans.stages.shared_dir", lambda s: folder)
    p = weights.prepare(rows.where("rec_id > 5"), rows, weights.TokenModel("trigram", "tfidf"), "cosine")
    assert hybrid_join(p, 0.01, 0.5, 3).count() > 3 and not [f for f in os.listdir(folder) if f.startswith(("sets", "terms"))]


def test_swept_blocks_find_all_pairs_of_large_sides(spark, sf, monkeypatch):
    """Every measure and set of filters, blocks of few tokens, against all pairs; no candidates are shuffled."""
    from simblock import classic, join, verification
    from simblock import workloads as W
    from simblock.queries import even, odd
    from simblock.weights import TokenModel, prepare

    monkeypatch.setattr(join, "SMALL", 0)
    monkeypatch.setattr(join, "BLOCK", 15_000)
    monkeypatch.setattr(join, "CHUNK", 20_000)
    pairs = lambda df: {(r.a_id, r.b_id): round(r.sim, 6) for r in df.collect()}
    docs, sides, shared, one = W.docs(spark, sf), (even(spark, sf), odd(spark, sf)), {}, {}
    for measure, tau in (("jaccard", 0.3), ("cosine", 0.3), ("dice", 0.35), ("overlap", 300.5)):
        p, d = prepare(*sides, TokenModel(), measure, shared), prepare(docs, None, TokenModel(), measure, one)
        want = pairs(classic.naive_hybrid(d, tau))
        for filters in (None, frozenset({"prefix", "size", "suffix_plain", "positional_exact"})):
            assert pairs(join.hybrid_join(d, tau, filters=filters)) == want and want
        assert pairs(verification.partial_join(d, tau)) == want
        assert pairs(classic.generalised_prefix_join(p, tau)) == pairs(classic.naive_hybrid(p, tau))


def test_swept_blocks_with_long_lists_as_a_matrix(spark, sf, monkeypatch):
    """Nearest partners of two sides and of a deduplication, most tokens in the matrix, against all pairs."""
    from simblock import classic, join, sweep
    from simblock import workloads as W
    from simblock.queries import even, odd
    from simblock.weights import TokenModel, prepare

    monkeypatch.setattr(join, "SMALL", 0)
    monkeypatch.setattr(join, "BLOCK", 30_000)
    monkeypatch.setattr(join, "CHUNK", 20_000)
    monkeypatch.setattr(sweep, "SHARE", 40)
    pairs = lambda df: {(r.a_id, r.b_id): round(r.sim, 6) for r in df.collect()}
    p, d = prepare(even(spark, sf), odd(spark, sf), TokenModel(), "cosine"), prepare(W.docs(spark, sf), None, TokenModel(), "cosine")
    assert pairs(join.hybrid_join(p, k=5)) == pairs(classic.naive_hybrid(p, k=5))
    assert pairs(join.hybrid_join(d, 0.1, 0.5, 3)) == pairs(classic.naive_hybrid(d, 0.1, 0.5, 3))


def test_norms_are_worked_out_once_a_record(spark):
    """Unit weights of a long record, whose norm Spark's plan would have put into each weight."""
    from simblock.weights import TokenModel, prepare

    df = spark.createDataFrame([(1, " ".join(f"w{i}" for i in range(2_000)))], "rec_id long, text string")
    sets = prepare(df, df, TokenModel(), "cosine").a._packed
    assert "aggregate(" not in sets._jdf.queryExecution().optimizedPlan().toString().lower()
    r = sets.first()
    assert len(r.ws) == 2_000 and abs(sum(w * w for w in r.ws) - 1) < 1e-9 and abs(r.total - 1) < 1e-9


def test_sweep_of_totals_and_lesser_weights(spark, monkeypatch):
    """Blocks of like totals hold each record once, whole lists of an overlap leave light records out, and texts are split once."""
    from simblock import join, sweep, weights
    from simblock.measures import MEASURES

    rng = np.random.default_rng(3)
    rows = []
    for i in range(60):
        keys = np.sort(rng.choice(40, 1 + i // 2, replace=False))
        ws = rng.integers(1, 9, len(keys)).astype(float)
        rows.append((i, keys.tolist(), ws.tolist(), float(ws.sum())))
    sets = spark.createDataFrame(rows, "rec_id long, keys array<bigint>, ws array<double>, total double")
    ends = [(low, high, n) for low, high, n, _ in sweep.blocks(sets, 150, True)]
    assert len(ends) > 3 and all(sum(low <= total <= high for low, high, n in set(ends)) == 1 for *_, total in rows)
    assert [x[2:] for x in sweep.blocks(sets, 300, False)] == [(4, i) for i in range(4)]
    monkeypatch.setattr(join, "BLOCK", 600)
    monkeypatch.setattr(sweep, "COLUMNS", 7)
    weight = [dict(zip(keys, ws)) for _, keys, ws, _ in rows]
    for measure, t in (("overlap", 40.5), ("dice", 0.5), ("jaccard", 0.3)):
        m = MEASURES[measure]
        for dedup in (False, True):
            want = {}
            for a in range(60):
                for b in range(60):
                    i = sum(min(w, weight[b].get(k, 0)) for k, w in weight[a].items())
                    if m.number(i, rows[a][3], rows[b][3]) >= t and (not dedup or a < b):
                        want[a, b] = round(m.number(i, rows[a][3], rows[b][3]), 9)
            got = sweep.swept(sets, sets, m, t, frozenset({"prefix", "size", "positional"}), dedup, (t, 0.0, None)).collect()
            assert len(got) == len(want) and {(min(r.a_id, r.b_id), max(r.a_id, r.b_id)) if dedup else (r.a_id, r.b_id): round(r.sim, 9) for r in got} == want
    texts = weights.token_lists(spark.createDataFrame([(1, "a b")], "rec_id long, text string"), "word", True)
    assert weights.frequencies(texts)._jdf.queryExecution().optimizedPlan().toString().count("split(") == 1


def test_joins_with_filters_send_the_small_side(spark, sf, monkeypatch):
    """With filters named, too, the small side is the block, and no more than its records go to the tasks at once."""
    from simblock import classic, join, sweep
    from simblock import workloads as W
    from simblock.queries import prepared

    p, met = prepared(spark, sf, weighting="binary", measure="cosine"), []
    made = sweep.swept
    monkeypatch.setattr(sweep, "swept", lambda a, b, *more: met.append(b.count()) or made(a, b, *more))
    pairs = lambda df: {(r.a_id, r.b_id): round(r.sim, 6) for r in df.collect()}
    for tau, k in ((0.25, None), (0.0, 5)):
        assert pairs(join.directed_join(p, join.JoinConfig(tau=tau, k=k, filters=frozenset({"prefix", "suffix"})))) == pairs(classic.naive_hybrid(p, tau, k=k))
    assert met == [W.items(spark, sf).count()]


def test_recall_conditions_of_few_probes_write_no_log(spark, sf, monkeypatch):
    """Counted as pairs pass by, conditions are those of the whole log, for matches that are far from the best, too."""
    from simblock import estimate, join
    from simblock.queries import prepared

    p = prepared(spark, sf, weighting="binary")
    matches = spark.createDataFrame([(a, b) for (a,) in p.a.select("rec_id").distinct().orderBy("rec_id").limit(9).collect() for b in range(0, 200, 23)], "a_id long, b_id long")
    rows = lambda: sorted(tuple(round(x, 9) if isinstance(x, float) else x for x in r) for r in estimate.recall_conditions(p, matches, (0.0, 0.1, 0.5)).select("a_id", "b_id", "d", "tau_max", "tau_r_max", "k_min", "rank_min").fillna(-1).collect())
    with monkeypatch.context() as patch:
        patch.setattr(join, "smaller", lambda p: None)
        want = rows()
    monkeypatch.setattr(estimate, "candidate_log", None)
    assert rows() == want and len({x[5] for x in want}) > 20


def test_small_probes_walk_their_own_lists_only(spark, sf, monkeypatch):
    """Lists of tokens that no probe has are not built, and joins by rank stay the same."""
    from simblock import cutoff, join
    from simblock.queries import prepared

    p = prepared(spark, sf, measure="cosine")
    rows = lambda: sorted((r.a_id, r.b_id, round(r.sim, 9)) for r in cutoff.rank_cut_pairs(p, 150).collect())
    got, lists = rows(), cutoff.met_lists(p, p.a).select("key").distinct()
    assert lists.join(p.a.select("key").distinct(), "key", "left_anti").count() == 0 and lists.count() > 50
    monkeypatch.setattr(join, "smaller", lambda p: None)
    assert got and rows() == got


def test_hashed_vectors_are_made_once(spark, sf):
    """The fit and the vectors of all records come from the same written ones."""
    from simblock import baselines
    from simblock import workloads as W
    from simblock.queries import prepared

    p = prepared(spark, sf, measure="cosine")
    u, v = baselines.encode_matched(p, W.items_in_docs(spark, sf).truth)
    assert all(x.inputFiles() and all("/vectors-" in f for f in x.inputFiles()) for x in (u, v))
    assert v.count() == p.b.select("rec_id").distinct().count()


def test_broadcast_join_is_one_whatever_the_sizes(spark, sf):
    """Without automatic broadcasts, too, the small side is sent."""
    from simblock.operators.relational import QUERIES

    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        found = QUERIES["op_broadcast_join"](spark, sf)
        assert "BroadcastHashJoin" in found._jdf.queryExecution().executedPlan().toString()
        assert found.columns == ["n_name", "r_name"] and found.count() == 25
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_match_training_fits_all_matches(spark, sf, monkeypatch):
    """More matches than were once fitted: the weights are those of all, on the driver and summed by the tasks; without matches all vectors are fitted."""
    import numpy as np

    from simblock import baselines
    from simblock.queries import W, prepared

    p = prepared(spark, sf, W.docs, None, measure="cosine")
    vectors = {r.rec_id: np.array(r.vector) for r in baselines.hashed_vectors(p.a).collect()}
    ids = sorted(vectors)
    pairs = [(a, b) for a in ids for b in ids if a < b]
    assert len(pairs) > 10_000
    unit = lambda x: x / np.linalg.norm(x, axis=1, keepdims=True)
    u, v = (unit(np.array([vectors[x[i]] for x in pairs])) for i in (0, 1))
    feats, y = np.concatenate([u * v, u * np.roll(v, 1, axis=0)]) * 256, np.repeat([1.0, 0.0], len(pairs))
    w, bias = np.ones(256) / 256, 0.0
    for _ in range(4):
        z = 1 / (1 + np.exp(-np.clip(feats @ w + bias, -30, 30)))
        w, bias = w - 0.1 * (feats.T @ (z - y) / len(y) + 1e-3 * w), bias - 0.1 * float((z - y).mean())
    want = {x: vectors[x] * np.sqrt(np.maximum(w, 1e-6)) for x in ids}
    matches = spark.createDataFrame(pairs, "a_id long, b_id long")
    for held in (1 << 20, 100):
        monkeypatch.setattr(baselines, "HELD", held, raising=False)
        got = {r.rec_id: np.array(r.vector) for r in baselines.encode_matched(p, matches, rounds=4)[0].collect()}
        assert got.keys() == want.keys() and all(np.allclose(got[x], want[x], atol=1e-9) for x in ids)
    x = np.array([vectors[i] for i in ids])
    axes = np.linalg.svd(x.T @ x)[2][:64]
    none = {r.rec_id: np.array(r.vector) for r in baselines.encode_matched(p, matches.where("false"))[0].collect()}
    assert all(np.isclose(np.linalg.norm(none[i]), np.linalg.norm(axes @ vectors[i])) for i in ids)


def test_scalability_runs_the_blocker_with_all_configurations(spark, sf, monkeypatch):
    """The blocker chooses among all models and measures on each share of the documents."""
    from simblock import experiments, unsupervised

    met = []
    monkeypatch.setattr(unsupervised, "prepare", lambda a, b, model, measure, shared: (model, measure))
    monkeypatch.setattr(unsupervised, "balanced", lambda prepared, k, *more: met.append((sorted(prepared, key=str), k)) or (unsupervised.Choice(None, "", 0.0), None))
    monkeypatch.setattr(unsupervised, "directed_join", lambda *x: spark.createDataFrame([(1, 2, 0.5)], "a_id long, b_id long, sim double"))
    monkeypatch.setattr(experiments, "FRACTIONS", (0.25,))
    for name in ("hybrid_join", "prepare"):
        monkeypatch.setattr(experiments, name, lambda *x, **y: spark.range(1))
    for name in ("token_blocking", "high_value_blocking", "high_value_blocking_pruned", "minhash"):
        monkeypatch.setattr(experiments.baselines, name, lambda *x, **y: spark.range(1))
    rows = experiments.scalability(spark, sf).collect()
    assert len(rows) == 7 and met == [(sorted(unsupervised.SPACE, key=str), 5)]


def test_products_of_single_precision_lose_no_neighbour():
    """Similarities that single precision can't tell apart are ranked by their exact values, whole products are summed for few pairs only."""
    import numpy as np
    import pyarrow as pa

    from simblock import join, sweep
    from simblock.measures import MEASURES

    rng, n, width = np.random.default_rng(5), 200, 12
    common = rng.random(width) + 1
    weights = common + 1e-8 * rng.random((n, width))  # of every record and all nearly alike
    weights /= np.linalg.norm(weights, axis=1, keepdims=True)
    ends = pa.array(np.arange(n + 1) * width, pa.int32())
    lists = lambda x, kind: pa.ListArray.from_arrays(ends, pa.array(x.ravel(), kind))
    side = (pa.array(np.arange(n)), lists(np.tile(np.arange(width), n), pa.int64()), lists(weights, pa.float64()), pa.array(np.ones(n)))
    x = sweep.Block(side, MEASURES["cosine"], 0.0, False)
    assert x.single.dtype == np.float32 and len(x.single) == width
    order = x.ids.to_numpy()
    sims = weights @ weights.T
    for dedup in (False, True):
        found = list(sweep.pairs(x, join.Sets(*side[1:]), side[0], MEASURES["cosine"], 0.0, frozenset(), dedup, False, 3))
        a, b, s = (np.concatenate([f[i] for f in found]) for i in range(3))
        got = {(i, int(order[j])): v for i, j, v in zip(a.tolist(), b.tolist(), s.tolist())}
        assert all(abs(v - sims[i, j]) < 1e-14 for (i, j), v in got.items())
        for i in range(n):
            mine = np.where(np.arange(n) == i, -1.0, sims[i]) if dedup else sims[i]
            assert all((i, j) in got for j in np.flatnonzero(mine >= np.sort(mine)[-3]).tolist())
    spread = rng.random((n, width)) ** 8 + 1e-3
    spread /= np.linalg.norm(spread, axis=1, keepdims=True)
    side = (side[0], side[1], lists(spread, pa.float64()), side[3])
    x = sweep.Block(side, MEASURES["cosine"], 0.0, False)
    found = list(sweep.pairs(x, join.Sets(*side[1:]), side[0], MEASURES["cosine"], 0.0, frozenset(), False, False, 3, 0.5))
    assert n * 3 <= sum(len(f[0]) for f in found) < n * 4
