"""The methods that the hybrid blockers are compared with."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F

from ..estimate import MARGINS
from ..join import conditions, unordered
from ..plans.ordering import running_totals
from ..plans.stages import cut
from ..weights import Prepared

HELD = 10_000  # matches whose vectors are held on the driver while weights are fitted to them


def token_blocking(p: Prepared) -> DataFrame:
    """All pairs that share a token. Quadratic in the longest list; for comparison only."""
    from ..classic import overlap_counts

    return overlap_counts(p).select("a_id", "b_id")


def _valued_tokens(p: Prepared) -> tuple[DataFrame, DataFrame]:
    """Tokens of several records whose weight in the record is above the mean of all."""
    rows = p.a if p.dedup else p.a.unionByName(p.b)
    common = p.vocabulary.where("df > 1").select("key")
    mean = rows.join(common, "key").agg(F.avg("w")).first()[0] or 0.0
    keep = lambda side: side.join(common, "key").where(F.round("w", 9) > F.lit(round(mean, 9)))
    return keep(p.a), keep(p.b)


def high_value_blocking(p: Prepared) -> DataFrame:
    """Valued tokens only; pairs with fewer common ones than the mean pair are dropped."""
    a, b = _valued_tokens(p)
    met = a.select("key", F.col("rec_id").alias("a_id")).join(b.select("key", F.col("rec_id").alias("b_id")), "key")
    counts = cut((met.where("a_id < b_id") if p.dedup else met).groupBy("a_id", "b_id").agg(F.count("*").alias("n")), "counts")
    mean = counts.agg(F.avg("n")).first()[0] or 0.0
    return counts.where(F.col("n") >= F.lit(mean)).select("a_id", "b_id")


def high_value_blocking_pruned(p: Prepared) -> DataFrame:
    """The same pairs from one pass that keeps pairs of two or more common tokens only.

    As soon as any pair has two, the mean is above one and pairs of one token can't reach it. The mean over
    all pairs is observed while they pass by; only if no pair has two are all of them the result.
    """
    a, b = _valued_tokens(p)
    met = a.select("key", F.col("rec_id").alias("a_id")).join(b.select("key", F.col("rec_id").alias("b_id")), "key")
    counts = (met.where("a_id < b_id") if p.dedup else met).groupBy("a_id", "b_id").agg(F.count("*").alias("n"))
    all_pairs = Observation()
    kept = cut(counts.observe(all_pairs, F.avg("n").alias("mean"), F.max("n").alias("most")).where("n > 1"), "counts")
    mean, most = all_pairs.get["mean"] or 0.0, all_pairs.get["most"] or 0
    return (kept.where(F.col("n") >= F.lit(mean)) if most > 1 else counts).select("a_id", "b_id")


def choose_bands(tau: float, permutations: int = 128, least_recall: float | None = None) -> tuple[int, int]:
    """(bands, rows) of minhash: least false positives plus negatives, or least positives at a recall."""
    best = None
    s = (np.arange(1000) + 0.5) / 1000
    for rows in range(1, permutations + 1):
        bands = permutations // rows
        hit = 1 - (1 - s**rows) ** bands
        false_pos, false_neg = hit[s < tau].sum() / 1000, (1 - hit)[s >= tau].sum() / 1000
        if least_recall is None:
            score = false_pos + false_neg
        elif hit[s >= tau].mean() < least_recall:
            continue
        else:
            score = false_pos
        if best is None or score < best[0]:
            best = (score, bands, rows)
    return (best[1], best[2]) if best else (permutations, 1)


def minhash(p: Prepared, tau: float, permutations: int = 128, bands: tuple[int, int] | None = None, seed: int = 0) -> DataFrame:
    """Pairs that agree on all minima of some band. Signatures stay in the JVM."""
    b, r = bands or choose_bands(tau, permutations)

    def signed(side: DataFrame, name: str) -> DataFrame:
        mins = side.groupBy(F.col("rec_id").alias(name)).agg(*[F.min(F.xxhash64("key", F.lit(seed + i))).alias(f"m{i}") for i in range(b * r)])
        keys = F.array(*[F.xxhash64(F.lit(x), *[f"m{x * r + y}" for y in range(r)]) for x in range(b)])
        return mins.select(name, F.explode(keys).alias("band"))

    met = signed(p.a, "a_id").join(signed(p.b, "b_id"), "band")
    return (met.where("a_id < b_id") if p.dedup else met).select("a_id", "b_id").distinct()


def dense_top_k(a: DataFrame, b: DataFrame | None, k: int, block: int = 4096) -> DataFrame:
    """``(a_id, b_id, sim)``: exact cosine neighbours of ``(rec_id, vector)`` frames, block by block.

    Index vectors are dealt to blocks; each block meets all probe blocks and keeps k for
    each probe, so memory is bounded by two blocks and what is shuffled by k a probe and block.
    """
    dedup = b is None
    index = a if dedup else b
    blocks = max(1, math.ceil(index.count() / block))
    probe_blocks = max(1, math.ceil(a.count() / block))
    deal = lambda df, n: F.pmod(F.xxhash64("rec_id"), F.lit(n)).cast("int")
    left = a.select("rec_id", "vector", deal(a, probe_blocks).alias("i"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("j"), F.lit(0).alias("side"))
    right = index.select("rec_id", "vector", F.explode(F.sequence(F.lit(0), F.lit(probe_blocks - 1))).alias("i"), deal(index, blocks).alias("j"), F.lit(1).alias("side"))

    def near(g: pd.DataFrame) -> pd.DataFrame:
        x, y = g[g["side"] == 0], g[g["side"] == 1]
        if not len(x) or not len(y):
            return pd.DataFrame({"a_id": [], "b_id": [], "sim": []}).astype({"a_id": "int64", "b_id": "int64", "sim": float})
        u, v = (np.stack(z["vector"].to_numpy()).astype(float) for z in (x, y))
        u /= np.maximum(np.linalg.norm(u, axis=1, keepdims=True), 1e-300)
        v /= np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-300)
        ids = y["rec_id"].to_numpy()
        out = []
        for i, (row, me) in enumerate(zip(u @ v.T, x["rec_id"])):
            if dedup:
                row = np.where(ids == me, -2.0, row)
            order = np.lexsort((ids, -np.round(row, 9)))[:k]
            out += [(me, ids[o], row[o]) for o in order if row[o] > -2]
        return pd.DataFrame(out, columns=["a_id", "b_id", "sim"])

    found = left.unionByName(right).groupBy("i", "j").applyInPandas(near, "a_id long, b_id long, sim double")
    order = Window.partitionBy("a_id").orderBy(F.round("sim", 9).desc(), "b_id")
    return found.withColumn("n", F.row_number().over(order)).where(F.col("n") <= k).drop("n")


def hashed_vectors(side: DataFrame, width: int = 256) -> DataFrame:
    """Weighted tokens hashed to a signed vector of fixed width."""
    at = F.pmod(F.xxhash64("key"), F.lit(width)).cast("int")
    sign = F.when(F.pmod(F.xxhash64("key", F.lit(1)), F.lit(2)) == 0, 1.0).otherwise(-1.0)
    cells = side.groupBy("rec_id", at.alias("at")).agg(F.sum(F.col("w") * sign).alias("x"))
    m = cells.groupBy("rec_id").agg(F.map_from_entries(F.collect_list(F.struct("at", "x"))).alias("m"))
    return m.select("rec_id", F.transform(F.sequence(F.lit(0), F.lit(width - 1)), lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0.0))).alias("vector"))


def _project(df: DataFrame, matrix: np.ndarray) -> DataFrame:
    @F.pandas_udf("array<double>")
    def turn(v: pd.Series) -> pd.Series:
        return pd.Series(list(np.stack(v.to_numpy()) @ matrix)) if len(v) else pd.Series([], dtype=object)

    return df.select("rec_id", turn("vector").alias("vector"))


def _gram(vectors: DataFrame) -> np.ndarray:
    """Products of the dimensions summed over all vectors, a matrix from each task."""

    def total(batches):
        out = 0.0
        for batch in batches:
            if len(batch):
                x = _rows(batch.column("vector"))
                out = out + x.T @ x
        if not np.isscalar(out):
            yield pa.RecordBatch.from_arrays([pa.array([out.ravel()])], ["x"])

    parts = vectors.select("vector").mapInArrow(total, "x array<double>")
    found = np.zeros(0)
    for part in parts.toLocalIterator(prefetchPartitions=True):
        x = np.array(part["x"])
        found = x if not len(found) else found + x
    return found.reshape(math.isqrt(len(found)), -1)


def encode_self(p: Prepared, width: int = 256, dims: int = 64, fit_rows: int | None = 5000) -> tuple[DataFrame, DataFrame | None]:
    """Stand-in for a self-supervised encoder: vectors of both sides by a linear autoencoder (principal axes
    of a bounded sample of hashed TF-IDF vectors, of all of the first side's without ``fit_rows``)."""
    va, vb = hashed_vectors(p.a, width), None if p.dedup else hashed_vectors(p.b, width)
    if fit_rows is None:
        va = cut(va, "vectors")  # read for the fit and for all records
        products = _gram(va)
        products = products if len(products) else np.zeros((width, width))
    else:
        rows = va.orderBy(F.md5(F.col("rec_id").cast("string"))).limit(fit_rows).select("vector").collect()
        x = np.array([r[0] for r in rows])
        products = x.T @ x
    _, _, axes = np.linalg.svd(products)
    return _project(va, axes[:dims].T), None if vb is None else _project(vb, axes[:dims].T)


def _rows(vectors: pa.Array) -> np.ndarray:
    """Vectors of one length as the rows of a matrix."""
    return vectors.flatten().to_numpy(zero_copy_only=False).reshape(len(vectors), -1).astype(float)


def _agreement(u: np.ndarray, v: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Features of matches ``(u, v)`` and of as many non-matches ``(u, w)``: products of unit vectors by dimension."""
    u, v, w = (x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300) for x in (u, v, w))
    return np.concatenate([u * v, u * w]) * u.shape[1], np.concatenate([np.ones(len(u)), np.zeros(len(u))])


def _slope(feats: np.ndarray, y: np.ndarray, w: np.ndarray, bias: float) -> tuple[np.ndarray, float]:
    """Summed slopes of the logistic loss by weight and by bias."""
    z = 1 / (1 + np.exp(-np.clip(feats @ w + bias, -30, 30))) - y
    return feats.T @ z, float(z.sum())


def _training(va: DataFrame, vb: DataFrame, matches: DataFrame) -> DataFrame:
    """``(u, v, w)``: vectors of all matches in the order of their ids, and the second one of the match before, the last one's for the first."""
    met = cut(matches.select("a_id", "b_id", F.lit(1).cast("long").alias("_one")).join(va.select(F.col("rec_id").alias("a_id")), "a_id", "left_semi").join(vb.select(F.col("rec_id").alias("b_id")), "b_id", "left_semi"), "matches")
    at = cut(running_totals(met, ["a_id", "b_id"], {"_at": "_one"}), "matches")
    n = at.count()
    before = at.select(F.pmod(F.col("_at") + 1, F.lit(max(n, 1))).alias("_at"), F.col("b_id").alias("w_id"))
    side = lambda v, name, x: v.select(F.col("rec_id").alias(name), F.col("vector").alias(x))
    rows = at.join(before, "_at").join(side(va, "a_id", "u"), "a_id").join(side(vb, "b_id", "v"), "b_id").join(side(vb, "w_id", "w"), "w_id")
    return cut(rows.select("_at", "u", "v", "w"), "training")


def fit_agreement(training: DataFrame, width: int, rounds: int) -> np.ndarray | None:
    """Weights of the dimensions by logistic regression on all rows ``(u, v, w)``; None without any.

    Up to ``HELD`` rows are fitted on the driver. Of more, each round's slope is summed by the tasks from the
    written rows, so that nothing but a vector of weights and a slope a task travels.
    """
    n = training.count()
    if not n:
        return None
    if n <= HELD:
        table = training.orderBy("_at").select("u", "v", "w").toArrow().combine_chunks()
        feats, y = _agreement(*(_rows(pa.concat_arrays(table[c].chunks)) for c in ("u", "v", "w")))
        slope = lambda w, bias: _slope(feats, y, w, bias)
    else:
        def slope(w, bias):
            def part(batches):
                out = np.zeros(width + 1)
                for batch in (b for b in batches if len(b)):
                    x, z = _slope(*_agreement(*(_rows(batch.column(c)) for c in ("u", "v", "w"))), w, bias)
                    out += np.append(x, z)
                yield pa.RecordBatch.from_arrays([pa.array([out])], ["x"])

            found = np.sum([r["x"] for r in training.select("u", "v", "w").mapInArrow(part, "x array<double>").collect()], axis=0)
            return found[:-1], float(found[-1])

    w, bias = np.ones(width) / width, 0.0
    for _ in range(rounds):
        x, z = slope(w, bias)
        w = w - 0.1 * (x / (2 * n) + 1e-3 * w)
        bias -= 0.1 * z / (2 * n)
    return w


def encode_matched(p: Prepared, matches: DataFrame, width: int = 256, rounds: int = 200) -> tuple[DataFrame, DataFrame | None]:
    """Stand-in for a match-trained encoder: weights of the hashed dimensions by logistic
    regression on the agreement of all matches and of as many shifted non-matches."""
    va = cut(hashed_vectors(p.a, width), "vectors")  # read for the fit and for all records
    vb = va if p.dedup else cut(hashed_vectors(p.b, width), "vectors")
    w = fit_agreement(_training(va, vb, matches), width, rounds)
    if w is None:
        return encode_self(p, width, fit_rows=None)
    scale = np.diag(np.sqrt(np.maximum(w, 1e-6)))
    return _project(va, scale), None if p.dedup else _project(vb, scale)


def _neighbours(vectors: tuple[DataFrame, DataFrame | None], k: int) -> DataFrame:
    out = dense_top_k(*vectors, k)
    return unordered(out) if vectors[1] is None else out


def dense_self(p: Prepared, k: int, width: int = 256, dims: int = 64, fit_rows: int = 5000) -> DataFrame:
    """Cosine neighbours under :func:`encode_self`."""
    return _neighbours(encode_self(p, width, dims, fit_rows), k)


def dense_matched(p: Prepared, matches: DataFrame, k: int, width: int = 256, rounds: int = 200) -> DataFrame:
    """Cosine neighbours under :func:`encode_matched`."""
    return _neighbours(encode_matched(p, matches, width, rounds), k)


def dense_tuned(vectors: tuple[DataFrame, DataFrame | None], matches: DataFrame, target: float) -> tuple[DataFrame, int]:
    """(pairs, k): neighbours with the k that a recall of the matches asks for, vectors made once.

    Probes of the matches alone are searched with a doubling k until enough matches are among their partners.
    """
    a, b = (None if v is None else cut(v, "vectors") for v in vectors)
    index = a if b is None else b
    probes, size = a.join(matches.select(F.col("a_id").alias("rec_id")).distinct(), "rec_id", "left_semi"), index.count()
    order = Window.partitionBy("a_id").orderBy(F.round("sim", 9).desc(), "b_id")
    k = 1
    while True:
        near = dense_top_k(probes, index, k + (b is None)).where("true" if b is not None else "a_id <> b_id").withColumn("n", F.row_number().over(order))
        ranks = matches.select("a_id", "b_id").distinct().join(near, ["a_id", "b_id"], "left").select(F.col("n").cast("double")).toPandas()["n"].fillna(np.inf).to_numpy()
        if k >= size or tune_k(ranks, target) is not None:
            break
        k *= 2
    best = tune_k_validated(ranks, target)[0] or k
    return _neighbours((a, b), best), best


def threshold_join(scored: DataFrame, tau: float, dedup: bool) -> DataFrame:
    out = conditions(scored, tau, 0.0, None)
    return unordered(out) if dedup else out


# tuning on known matches ----------------------------------------------------------------------


def confident_recall(values: list[float], confidence: float = 0.95) -> float:
    """Lower end of the mean of validation recalls (normal approximation)."""
    x = np.array(values)
    z = {0.9: 1.2816, 0.95: 1.6449, 0.99: 2.3263}[confidence]
    return float(x.mean() - z * x.std(ddof=1) / math.sqrt(len(x))) if len(x) > 1 else float(x.mean())


def validated_margin(n: int, margins, target: float, found, seed: int = 1):
    """The least margin whose recall on left-out matches is confidently the target (else the last).

    ``found(train, test, margin)`` gives the recall on the test rows of what was tuned on the training rows, three folds.
    """
    folds = np.random.default_rng(seed).permutation(n) % 3
    for margin in margins:
        if confident_recall([found(folds != f, folds == f, margin) for f in range(3)]) >= target:
            break
    return margin


def tune_threshold(sims: np.ndarray, target: float, seed: int = 1) -> tuple[float, float]:
    """(tau, margin): the quantile of match similarities, lowered until left-out recall is confident."""
    if len(sims) < 3:
        return 0.0, 1.0
    quantile = lambda x, d: float(np.quantile(x, 1 - target, method="lower")) * (1 - d)
    margin = validated_margin(len(sims), MARGINS, target, lambda train, test, d: float((sims[test] >= quantile(sims[train], d) - 1e-9).mean()), seed)
    return quantile(sims, margin), margin


def tune_k(ranks: np.ndarray, target: float) -> int | None:
    """The least k whose recall over the matches' ranks reaches the target (None: none does)."""
    good = np.sort(ranks[np.isfinite(ranks)])
    need = math.ceil(target * len(ranks) - 1e-9)
    return int(good[need - 1]) if 0 < need <= len(good) else None


def tune_k_validated(ranks: np.ndarray, target: float, seed: int = 1) -> tuple[int | None, int]:
    """(k, margin): the least k of the target's recall plus a margin of 0, 1, 2, 4, ... that left-out recall asks for.

    ``ranks`` has each match's rank among its probe's partners, infinite where the two share nothing.
    """
    if len(ranks) < 3:
        return tune_k(ranks, target), 0
    most = ranks[np.isfinite(ranks)].max(initial=1)

    def found(train, test, d):
        k = tune_k(ranks[train], target)
        return float((ranks[test] <= (np.inf if k is None else k + d)).mean()) if k is not None else 0.0

    margin = validated_margin(len(ranks), [0, *(1 << i for i in range(int(most).bit_length()))], target, found, seed)
    k = tune_k(ranks, target)
    return (None if k is None else k + margin), margin


def tuned_bands(sims: np.ndarray, target: float, permutations: int = 128) -> tuple[float, tuple[int, int]]:
    """(tau, bands and rows) of minhash for a recall of the matches, whose Jaccard similarities are given."""
    tau, _ = tune_threshold(sims, target)
    return tau, choose_bands(tau, permutations, target)


def tuned_threshold_join(a: DataFrame, b: DataFrame | None, matches: DataFrame, target: float, space: list, sample: int = 1000) -> tuple:
    """(pairs estimated, model, measure, tau, sets) of the combination that returns fewest pairs.

    Each combination's threshold is tuned by itself; pairs are estimated from ``sample`` probes.
    """
    from ..estimate import by_sampling, recall_conditions
    from ..weights import prepare

    best, shared = None, {}
    for model, measure in space:
        p = prepare(a, b, model, measure, shared)
        sims = recall_conditions(p, matches).select("tau_max").toPandas()["tau_max"].fillna(0).to_numpy()
        tau, _ = tune_threshold(sims, target)
        pairs = by_sampling(p, tau, 0.0, None, sample)
        if best is None or pairs < best[0]:
            best = (pairs, model, measure, tau, p)
    return best


def recall_curve(theta: DataFrame, column: str, grid: list) -> list[tuple[float, float]]:
    """(parameter, recall) at each grid value from recall conditions; ``column`` is tau_max or k_min."""
    meets = (lambda g: F.col(column) <= g) if column == "k_min" else (lambda g: F.round(column, 9) >= round(g, 9))
    row = theta.agg(F.count("*"), *[F.count_if(F.coalesce(meets(g), F.lit(False))) for g in grid]).first()
    return [(float(g), row[i + 1] / max(1, row[0])) for i, g in enumerate(grid)]


def global_default(curves: dict[str, list[tuple[float, float]]], target: float) -> float | None:
    """The most aggressive parameter that reaches the target on every workload.

    ``curves`` has (parameter, recall) by workload, parameters from the most aggressive on.
    """
    grid = [x for x, _ in next(iter(curves.values()))]
    return next((g for g in grid if all(dict(c)[g] >= target - 1e-12 for c in curves.values())), None)
