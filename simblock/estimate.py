"""Estimates from a bounded sample of probes and from known matches.

A trajectory tells, for a probe, how many pairs of which similarity the walk over its
lists has found at checkpoints whose ranks grow by a tenth. Histograms are built by
Spark over all index records; what comes to the driver is bounded by probes, checkpoints
and bins, not by the collections.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from .cutoff import candidate_log, list_bases, met_lists
from .plans.stages import cut
from .weights import Prepared

BINS = 100
SAMPLE = 1000
KEPT = 1000  # similarities kept for each probe
MARGINS = (0.0, 0.01, 0.05, 0.1, 0.2, 0.3, 0.4, 0.5)


def checkpoint_levels(last: int) -> list[int]:
    """1, 2, ... growing by a tenth, rounded up, until ``last`` is reached."""
    levels = [1]
    while levels[-1] < last:
        levels.append(max(levels[-1] + 1, math.ceil(levels[-1] * 11 / 10)) if levels[-1] * 11 % 10 else levels[-1] * 11 // 10)
    return levels


def sample_probes(side: DataFrame, n: int = SAMPLE) -> DataFrame:
    """Rows of at most n records, chosen by a hash of the id: the same ones each time."""
    ids = side.select("rec_id").distinct().orderBy(F.md5(F.col("rec_id").cast("string")), "rec_id").limit(n)
    return side.join(F.broadcast(ids), "rec_id", "left_semi")


@dataclass
class Trajectories:
    probes: list  # ids of the sample
    scale: float  # records for each sampled one
    top: float  # upper end of the last bin
    levels: np.ndarray
    counts: np.ndarray  # probe, level, bin: pairs found by the level in the bin or above
    sums: np.ndarray  # their similarities
    sims: np.ndarray  # probe, KEPT: similarities from the best down
    walk: list  # probe: (base rank, suffix) of each of its lists
    totals: np.ndarray
    measure: str

    def edges(self) -> np.ndarray:
        return np.arange(BINS + 1) * self.top / BINS

    def bin_of(self, x: np.ndarray) -> np.ndarray:
        return np.clip(np.floor(np.asarray(x) / self.top * BINS + 1e-9).astype(int), 0, BINS - 1)

    def level_of(self, rho: int | None) -> int:
        return len(self.levels) - 1 if rho is None else max(0, int(np.searchsorted(self.levels, rho, side="right")) - 1)

    def cutoffs(self, tau: float, tau_r: float) -> np.ndarray:
        return np.maximum(tau, tau_r * (self.sims[:, 0] if self.sims.shape[1] else 0))

    def pairs(self, tau: float, tau_r: float, k: int | None, rho: int | None = None) -> float:
        """Upper bound of the number of pairs: whole bins, scaled to the collection."""
        low = self.bin_of(self.cutoffs(tau, tau_r))
        found = self.counts[np.arange(len(self.probes)), self.level_of(rho), low]
        return float(np.minimum(found, k if k is not None else np.inf).sum() * self.scale)

    def exact_sums(self, tau: float, tau_r: float, k: int | None) -> np.ndarray:
        """Similarity sums of the whole join, exact where the kept similarities reach.

        A probe with more partners than are kept, the last of them still similar enough, gets an
        upper bound: the sum of the histogram's bins from the threshold's on, over the whole walk.
        """
        s, low = self.sims[:, : k if k is not None else None], self.cutoffs(tau, tau_r)
        out = np.where(s >= low[:, None] - 1e-9, s, 0).sum(axis=1)
        if k is not None and k <= self.sims.shape[1]:
            return out
        rows = np.arange(len(self.probes))
        cut_off = (self.counts[rows, -1, 0] > self.sims.shape[1]) & (self.sims[:, -1] >= low - 1e-9)
        bins = self.bin_of(low)
        return np.where(cut_off, np.maximum(out, self.sums[rows, -1, bins]), out)

    def sum_bounds(self, tau: float, tau_r: float, k: int | None, level: int) -> np.ndarray:
        """Lower bounds of the similarity sums that the walk has by a level.

        Bins that begin at or above the threshold count whole; with more than k of them the k best are
        those of the highest bin that still has k, less its surplus at the bin's upper edge.
        """
        rows = np.arange(len(self.probes))
        low = np.clip(np.ceil(self.cutoffs(tau, tau_r) / self.top * BINS - 1e-9).astype(int), 0, BINS)
        counts = np.concatenate([self.counts[:, level], np.zeros((len(rows), 1))], axis=1)
        sums = np.concatenate([self.sums[:, level], np.zeros((len(rows), 1))], axis=1)
        if k is None:
            return sums[rows, low]
        at = np.where(counts >= k, np.arange(BINS + 1), -1).max(axis=1)
        at = np.where(at < low, low, at)
        surplus = np.maximum(counts[rows, at] - k, 0)
        return np.maximum(sums[rows, at] - surplus * np.append(self.edges()[1:], self.top)[at], 0)

    def visited(self, tau: float, tau_r: float, k: int | None, rho: int | None, sigma) -> float:
        """Upper estimate of list entries visited, the unit of the cost model."""
        kth = self.sims[:, k - 1] if k is not None and 0 < k <= self.sims.shape[1] else np.zeros(len(self.probes))
        need = np.maximum(self.cutoffs(tau, tau_r), kth)
        out = 0.0
        for i, (base, suffix, end) in enumerate(self.walk):
            stop = np.flatnonzero(suffix < sigma(self.totals[i], need[i]))
            seen = base[stop[0]] if len(stop) else end
            out += min(seen, rho) if rho is not None else seen
        return out * self.scale


SIGMA = {
    "jaccard": lambda total, tau: tau * total,
    "cosine": lambda total, tau: tau * tau,
    "dice": lambda total, tau: tau / (2 - tau) * total,
    "overlap": lambda total, tau: tau,
}


def record(p: Prepared, n: int = SAMPLE, rank_cap: int | None = None) -> Trajectories:
    """Trajectories of a sample of ``p.a`` over the index of ``p.b``; the whole walk is followed unless a cap is given."""
    probe = cut(sample_probes(p.a, n), "sample")
    postings = cut(met_lists(p, probe), "lists")
    log = cut(candidate_log(probe, p, postings, rank_cap), "log")
    ids = sorted(r[0] for r in probe.select("rec_id").distinct().collect())
    at = {x: i for i, x in enumerate(ids)}
    top, last = log.agg(F.max("sim"), F.max("rank")).first()
    top = 1.0 if p.measure != "overlap" else float(top or 1.0)
    levels = np.array(checkpoint_levels(int(last or 1)))
    level = F.size(F.filter(F.array(*[F.lit(int(x)) for x in levels]), lambda x: x < F.col("rank")))
    cell = F.least(F.floor(F.col("sim") / F.lit(top) * BINS + F.lit(1e-9)).cast("int"), F.lit(BINS - 1))
    cells = log.groupBy("a_id", level.alias("level"), cell.alias("cell")).agg(F.count("*").alias("n"), F.sum("sim").alias("s")).collect()
    counts, sums = np.zeros((len(ids), len(levels), BINS)), np.zeros((len(ids), len(levels), BINS))
    for r in cells:
        counts[at[r["a_id"]], r["level"], r["cell"]] = r["n"]
        sums[at[r["a_id"]], r["level"], r["cell"]] = r["s"]
    for x in (counts, sums):
        np.cumsum(x, axis=1, out=x)
        x[:] = np.cumsum(x[:, :, ::-1], axis=2)[:, :, ::-1]
    best = Window.partitionBy("a_id").orderBy(F.desc("sim"), "b_id")
    near = log.withColumn("n", F.row_number().over(best)).where(F.col("n") <= KEPT).groupBy("a_id").agg(F.sort_array(F.collect_list("sim"), asc=False).alias("s")).collect()
    width = max([1, *(len(r["s"]) for r in near)])
    sims = np.zeros((len(ids), width))
    for r in near:
        sims[at[r["a_id"]], : len(r["s"])] = r["s"]
    walk: list = [(np.zeros(0), np.zeros(0), 0.0)] * len(ids)
    steps = list_bases(probe, postings).groupBy("a_id").agg(F.sort_array(F.collect_list(F.struct("base", "s_a", "n"))).alias("w")).collect()
    for r in steps:
        base = np.array([x["base"] for x in r["w"]], dtype=float)
        walk[at[r["a_id"]]] = (base, np.array([x["s_a"] for x in r["w"]]), float(r["w"][-1]["base"] + r["w"][-1]["n"]))
    totals = np.zeros(len(ids))
    for r in probe.select("rec_id", "total").distinct().collect():
        totals[at[r["rec_id"]]] = r["total"]
    return Trajectories(ids, p.n_a / max(1, len(ids)), top, levels, counts, sums, sims, walk, totals, p.measure)


def by_sampling(p: Prepared, tau: float, tau_r: float, k: int | None, n: int = SAMPLE) -> float:
    """Plain estimate of the number of pairs: the join on a sample, scaled."""
    from .classic import scored_pairs
    from .join import conditions

    probe = sample_probes(p.a, n)
    some = max(1, probe.select("rec_id").distinct().count())
    part = Prepared(probe, p.b, p.vocabulary, some, p.n_b, p.measure, p.dedup)
    return conditions(scored_pairs(part), tau, tau_r, k).count() * p.n_a / some


def recall_conditions(p: Prepared, matches: DataFrame, margins: tuple = (0.0,)) -> DataFrame:
    """``(a_id, b_id, d, tau_max, tau_r_max, k_min, rank_min)``: what a join may ask at most to find each match.

    With margin d the match is taken as if it had (1 - d) of its similarity and all others
    theirs. Matches that share no token have nulls. Only probes with matches are walked.
    """
    from .join import smaller

    if not p.dedup and p.a.schema["rec_id"].dataType == p.b.schema["rec_id"].dataType == LongType() and smaller(p) == "a":
        return _streamed_conditions(p, cut(matches.select("a_id", "b_id").distinct(), "matches"), margins)
    m = matches.select("a_id", "b_id").distinct()
    probe = p.a.join(m.select(F.col("a_id").alias("rec_id")).distinct(), "rec_id", "left_semi")
    log = cut(candidate_log(probe, p), "log")
    own = m.join(log, ["a_id", "b_id"]).select("a_id", "b_id", "sim", F.col("rank").alias("own_rank"))
    own = own.withColumn("d", F.explode(F.array(*[F.lit(float(d)) for d in margins]))).withColumn("low", F.col("sim") * (1 - F.col("d")))
    other = log.select("a_id", F.col("b_id").alias("o_id"), F.col("sim").alias("o_sim"), F.col("rank").alias("o_rank"))
    met = own.join(other, "a_id", "left")
    rival = F.col("o_id") != F.col("b_id")
    better = rival & ((F.round("o_sim", 9) > F.round("low", 9)) | ((F.round("o_sim", 9) == F.round("low", 9)) & (F.col("o_id") < F.col("b_id"))))
    found = met.groupBy("a_id", "b_id", "d", "low", "own_rank").agg(
        (F.count_if(better) + 1).alias("k_min"),
        F.greatest(F.max(F.when(rival, F.col("o_sim"))), F.first("low")).alias("best"),
        F.min_by(F.when(better, F.col("o_rank")), F.when(better, F.struct("o_sim", (-F.col("o_id")).alias("x")))).alias("ahead"),
    )
    out = found.select("a_id", "b_id", "d", F.col("low").alias("tau_max"), (F.col("low") / F.col("best")).alias("tau_r_max"), F.col("k_min").cast("long").alias("k_min"), F.greatest("own_rank", F.coalesce("ahead", F.lit(0))).cast("long").alias("rank_min"))
    every = m.withColumn("d", F.explode(F.array(*[F.lit(float(d)) for d in margins])))
    return every.join(out, ["a_id", "b_id", "d"], "left")


def _nine(x: np.ndarray) -> np.ndarray:
    """Billionths, rounded."""
    return np.floor(x * 1e9 + 0.5).astype(np.int64)


def _first_two(at: np.ndarray, v: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Rows of the two least ``v`` of each place ``at``, of equal ones those of the larger ``b``."""
    order = np.lexsort((-b, v, at))
    start = np.flatnonzero(np.diff(at[order], prepend=-1))
    n = np.diff(np.append(start, len(at)))
    return order[np.arange(len(at)) - np.repeat(start, n) < 2]


def _places(pairs: DataFrame, t_a: np.ndarray, t_n: np.ndarray, t_b: np.ndarray) -> DataFrame:
    """``(k, at, n, two)``: where the pairs of probes stand among their targets, which are sorted from the best of a probe down.

    For k = 0 ``n`` pairs stand right ahead of target ``at``, ``two`` being the least similar of them; for k = 1
    ``two`` are the most similar of probe ``t_a[at]``, with their similarities turned to negative.
    """
    import pyarrow as pa

    first = np.flatnonzero(np.diff(t_a, prepend=t_a[0] - 1))
    probes = t_a[first]

    def place(batches):
        counts, kept, held, size = np.zeros(len(t_a), np.int64), [np.zeros((0, 2), np.int64), np.zeros(0), np.zeros(0, np.int64)], [], 0

        def sift():
            nonlocal counts, kept
            a, b, sim = (np.concatenate([x[i] for x in held]) for i in range(3))
            mine = np.flatnonzero(probes[np.minimum(np.searchsorted(probes, a), len(probes) - 1)] == a)
            a, b, sim = a[mine], b[mine], sim[mine]
            target = np.append(np.ones(len(t_a), bool), np.zeros(len(a), bool))
            order = np.lexsort((~target, np.append(t_b, b), -np.append(t_n, _nine(sim)), np.append(t_a, a)))
            behind = np.empty(len(order), np.int64)
            behind[order] = np.cumsum(target[order])
            slot = behind[len(t_a) :]
            ahead = np.flatnonzero((slot < len(t_a)) & (t_a[np.minimum(slot, len(t_a) - 1)] == a))
            counts += np.bincount(slot[ahead], minlength=len(t_a))
            own = first[np.searchsorted(probes, a)]
            kind = np.append(np.zeros(len(ahead), np.int64), np.ones(len(a), np.int64))
            at = np.append(kept[0], np.stack([kind, np.append(slot[ahead], own)], axis=1), axis=0)
            v, ids = np.concatenate([kept[1], sim[ahead], -sim]), np.concatenate([kept[2], b[ahead], b])
            some = _first_two(at[:, 0] * len(t_a) + at[:, 1], v, ids)
            kept = [at[some], v[some], ids[some]]

        for batch in batches:
            held.append([batch.column(c).to_numpy() for c in ("a_id", "b_id", "sim")])
            size += len(batch)
            if size > 1 << 20:
                sift()
                held, size = [], 0
        if held:
            sift()
        some = np.flatnonzero(counts)
        none = pa.nulls(len(some), pa.float64()), pa.nulls(len(some), pa.int64())
        yield pa.RecordBatch.from_arrays([pa.array(np.zeros(len(some), np.int64)), pa.array(some), pa.array(counts[some]), *none], ["k", "at", "n", "v", "b_id"])
        yield pa.RecordBatch.from_arrays([pa.array(kept[0][:, 0]), pa.array(kept[0][:, 1]), pa.array(np.zeros(len(kept[1]), np.int64)), pa.array(kept[1]), pa.array(kept[2])], ["k", "at", "n", "v", "b_id"])

    rows = pairs.mapInArrow(place, "k long, at long, n long, v double, b_id long")
    two = F.slice(F.sort_array(F.collect_list(F.when(F.col("v").isNotNull(), F.struct("v", (-F.col("b_id")).alias("b"))))), 1, 2)
    return rows.groupBy("k", "at").agg(F.sum("n").alias("n"), two.alias("two"))


def pair_ranks(p: Prepared, pairs: DataFrame) -> DataFrame:
    """``(a_id, b_id, rank)`` of some pairs that share a token: only lists of the probes' tokens are read, and none is sorted."""
    from .measures import MEASURES
    from .weights import entries

    probe = p.a
    keys = np.unique(probe.select("key").distinct().toPandas()["key"].to_numpy())
    rows = entries(p.b._packed, MEASURES[p.measure].power, among=keys).select("key", F.col("rec_id").alias("b_id"), "pre", "suf")
    means = cut(rows.groupBy("key").agg(F.count("*").alias("n"), F.sum("pre").alias("s")), "means")
    post = rows.join(F.broadcast(means), "key").select("key", (F.col("pre") * F.col("n") >= F.col("s")).cast("int").alias("half"), "b_id", "suf")
    lengths = cut(post.groupBy("key", "half").agg(F.count("*").alias("list_len")), "lengths")
    met = post.join(F.broadcast(pairs), "b_id").join(F.broadcast(probe.select("key", F.col("rec_id").alias("a_id"))), ["a_id", "key"])
    firsts = cut(met.groupBy("a_id", "b_id").agg(F.min_by(F.struct("key", "half", "suf"), "key").alias("f")).select("a_id", "b_id", "f.*"), "firsts")
    lists = F.broadcast(firsts.select("key", "half", F.col("suf").alias("s"), F.col("b_id").alias("b")).distinct())
    up_to = (F.col("suf") < F.col("s")) | ((F.col("suf") == F.col("s")) & (F.col("b_id") <= F.col("b")))
    places = post.join(lists, ["key", "half"]).where(up_to).groupBy("key", "half", F.col("b").alias("b_id")).agg(F.count("*").alias("place"))
    bases = list_bases(probe, lengths).select("a_id", "key", "half", "base")
    return firsts.join(places, ["key", "half", "b_id"]).join(bases, ["a_id", "key", "half"]).select("a_id", "b_id", (F.col("base") + F.col("place")).alias("rank"))


def _streamed_conditions(p: Prepared, m: DataFrame, margins: tuple) -> DataFrame:
    """:func:`recall_conditions` of few probes: pairs pass by and are counted between the matches, and only the ranks that matter are worked out."""
    from .join import merge_lists

    spark = m.sparkSession
    own = merge_lists(p, "a").join(F.broadcast(m), ["a_id", "b_id"]).toPandas()
    n = len(own)
    a, b, sim = (np.repeat(own[c].to_numpy(), len(margins)) for c in ("a_id", "b_id", "sim"))
    d = np.tile(np.array(margins, dtype=float), n)
    low = sim * (1 - d)
    order = np.lexsort((b, -_nine(low), a))
    a, b, sim, d, low = (x[order] for x in (a, b, sim, d, low))
    found = {(r["k"], r["at"]): (r["n"], [(x["v"], -x["b"]) for x in r["two"]]) for r in _places(merge_lists(p, "a"), a, _nine(low), b).collect()} if n else {}
    out, better, least, start = [], 0, [], 0
    for i in range(len(a)):
        if i == 0 or a[i] != a[i - 1]:
            better, least, start = 0, [], i
        many, two = found.get((0, i), (0, []))
        better, least = better + many, sorted(least + two, key=lambda x: (x[0], -x[1]))[:2]
        mine = _nine(sim[i : i + 1])[0] > _nine(low[i : i + 1])[0]
        rivals = [-v for v, x in found[1, start][1] if x != b[i]]
        ahead = [x for _, x in least if x != b[i]]
        out.append((int(a[i]), int(b[i]), float(d[i]), float(low[i]), float(low[i] / max([low[i], *rivals])), int(better - mine + 1), int(ahead[0]) if ahead else None))
    t = cut(spark.createDataFrame(out, "a_id long, b_id long, d double, tau_max double, tau_r_max double, k_min long, ahead long"), "conditions")
    ranks = cut(pair_ranks(p, cut(t.select("a_id", "b_id").unionAll(t.where("ahead IS NOT NULL").select("a_id", "ahead")).distinct(), "pairs")), "ranks")
    t = t.join(ranks.withColumnRenamed("rank", "own_rank"), ["a_id", "b_id"]).join(ranks.select("a_id", F.col("b_id").alias("ahead"), F.col("rank").alias("other")), ["a_id", "ahead"], "left")
    t = t.select("a_id", "b_id", "d", "tau_max", "tau_r_max", "k_min", F.greatest("own_rank", F.coalesce("other", F.lit(0))).cast("long").alias("rank_min"))
    return m.withColumn("d", F.explode(F.array(*[F.lit(float(x)) for x in margins]))).join(t, ["a_id", "b_id", "d"], "left")


def recalled(tau: float, tau_r: float, k: int | None, rho: int | None = None):
    """Predicate over recall conditions."""
    out = (F.round("tau_max", 9) >= round(tau, 9)) & (F.round("tau_r_max", 9) >= round(tau_r, 9))
    if k is not None:
        out = out & (F.col("k_min") <= k)
    if rho is not None:
        out = out & (F.col("rank_min") <= rho)
    return F.coalesce(out, F.lit(False))


def recall(theta: DataFrame, tau: float, tau_r: float, k: int | None, rho: int | None = None) -> DataFrame:
    """``(d, recall)`` estimated for a configuration."""
    return theta.groupBy("d").agg(F.avg(recalled(tau, tau_r, k, rho).cast("double")).alias("recall"))


def union_recall(forward: DataFrame, backward: DataFrame, cfg_ab: tuple, cfg_ba: tuple) -> DataFrame:
    """Recall when either direction finds a match; ``backward`` has the ids the other way round."""
    f = forward.select("a_id", "b_id", "d", recalled(*cfg_ab).alias("x"))
    b = backward.select(F.col("b_id").alias("a_id"), F.col("a_id").alias("b_id"), "d", recalled(*cfg_ba).alias("y"))
    both = f.join(b, ["a_id", "b_id", "d"], "full_outer")
    return both.groupBy("d").agg(F.avg((F.coalesce("x", F.lit(False)) | F.coalesce("y", F.lit(False))).cast("double")).alias("recall"))
