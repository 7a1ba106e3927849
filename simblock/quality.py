"""Quality of approximate joins: measured, checked for consistency, and chosen by bootstrap."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .estimate import Trajectories
from .weights import Prepared

RESAMPLES = 200
CONFIDENCE = 0.95


def measure(exact: DataFrame, approximate: DataFrame, probes: DataFrame, tau_r: float = 0.0) -> DataFrame:
    """One row ``quality``: mean over ``probes(a_id)`` of kept over exact similarity.

    Approximate pairs below ``tau_r`` times the exact best don't count; a probe
    without exact pairs has ratio 1.
    """
    whole = exact.groupBy("a_id").agg(F.sum("sim").alias("whole"), F.max("sim").alias("best"))
    kept = approximate.join(whole, "a_id").where(F.round("sim", 9) >= F.round(F.col("best") * tau_r, 9)).groupBy("a_id").agg(F.sum("sim").alias("kept"))
    ratio = F.when(F.coalesce("whole", F.lit(0.0)) == 0, 1.0).otherwise(F.coalesce("kept", F.lit(0.0)) / F.col("whole"))
    return probes.select("a_id").distinct().join(whole, "a_id", "left").join(kept, "a_id", "left").agg(F.avg(ratio).alias("quality"))


def violations(pairs: DataFrame, tau: float, tau_r: float, k: int | None) -> DataFrame:
    """Pairs that break a condition within the result itself; a consistent result has none."""
    by = Window.partitionBy("a_id")
    checked = pairs.withColumn("best", F.max("sim").over(by)).withColumn("n", F.row_number().over(by.orderBy(F.round("sim", 9).desc(), "b_id")))
    bad = (F.round("sim", 9) < round(tau, 9)) | (F.round("sim", 9) < F.round(F.col("best") * tau_r, 9))
    if k is not None:
        bad = bad | (F.col("n") > k)
    return checked.where(bad).select("a_id", "b_id", "sim")


def quality_of(level: int, t: Trajectories, tau: float, tau_r: float, k: int | None, q_p: float = CONFIDENCE, resamples: int = RESAMPLES, seed: int = 1) -> float:
    """Quality that the walk up to a checkpoint has with probability ``q_p`` over resampled probes."""
    exact = t.exact_sums(tau, tau_r, k)
    ratio = np.where(exact > 0, np.minimum(1.0, t.sum_bounds(tau, tau_r, k, level) / np.maximum(exact, 1e-300)), 1.0)
    rng = np.random.default_rng(seed)
    means = np.sort(ratio[rng.integers(0, len(ratio), (resamples, len(ratio)))].mean(axis=1)) if len(ratio) else np.ones(resamples)
    return float(means[int(np.floor((1 - q_p) * (resamples - 1)))])


def rank_for(q: float, t: Trajectories, tau: float, tau_r: float, k: int | None, q_p: float = CONFIDENCE, resamples: int = RESAMPLES) -> int | None:
    """Least checkpoint rank of quality ``q``; None (no cutoff) for q = 1 or if none is good enough."""
    if q >= 1:
        return None
    low, high = 0, len(t.levels) - 1
    if quality_of(high, t, tau, tau_r, k, q_p, resamples) < q:
        return None
    while low < high:
        mid = (low + high) // 2
        if quality_of(mid, t, tau, tau_r, k, q_p, resamples) >= q:
            high = mid
        else:
            low = mid + 1
    return int(t.levels[low])


def join_with_quality(p: Prepared, tau: float, tau_r: float, k: int | None, q: float, q_p: float = CONFIDENCE, sample: int = 1000) -> DataFrame:
    """The approximate join whose quality is at least ``q`` with probability ``q_p``."""
    from .estimate import record
    from .join import hybrid_join

    rho = None if q >= 1 else rank_for(q, record(p, sample), tau, tau_r, k, q_p)
    return hybrid_join(p, tau, tau_r, k, rho)
