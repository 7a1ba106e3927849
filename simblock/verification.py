"""Partial similarity: pairs are compared from their first shared token on, until they cannot reach a threshold."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .join import CHUNK, Sets, arrays, conditions, merge_lists, pre_candidates, smaller, spans, thresholds, unordered, verify
from .measures import MEASURES
from .sweep import swept
from .weights import Prepared

STRIDE = 16  # tokens of a record that are looked up before the next test


def partial(measure: str, tau: float):
    """Similarity, or 0 below ``tau``, of pairs ``(l, r)`` of records of two blocks from the shared token ``key`` on.

    All pairs advance by a stride of the first record's tokens at a time; those whose known overlap and
    the lesser remainder cannot reach ``tau`` leave.
    """
    product, m = measure == "cosine", MEASURES[measure]

    def mass(s: Sets) -> np.ndarray:
        """Mass from each entry to the last."""
        return np.concatenate([np.cumsum((s.ws * s.ws if product else s.ws)[::-1])[::-1], [0.0]])

    def compare(x: Sets, y: Sets, l: np.ndarray, r: np.ndarray, key: np.ndarray) -> np.ndarray:  # noqa: E741
        known = np.union1d(x.keys, y.keys)
        step, code_x, code_y = len(known) + 1, x.coded(known), y.coded(known)
        mass_x, mass_y = mass(x), mass(y)
        at = np.searchsorted(known, key)
        at_l, at_r = np.searchsorted(code_x, l * step + at), np.searchsorted(code_y, r * step + at)
        end_l, end_r = x.ends[l + 1], y.ends[r + 1]
        both = (at_l < end_l) & (at_r < end_r)  # a key that a record lacks leaves an empty suffix
        both[both] = (x.keys[at_l[both]] == key[both]) & (y.keys[at_r[both]] == key[both])
        i, here, out = np.zeros(len(l)), at_l.copy(), np.zeros(len(l), dtype=bool)
        for live in np.array_split(np.flatnonzero(both), max(1, both.sum() * STRIDE // CHUNK)):
            while len(live):
                take = np.minimum(STRIDE, end_l[live] - here[live])
                entry = spans(here[live], take)
                wanted = code_x[entry] + np.repeat((r[live] - l[live]) * step, take)
                at = np.minimum(np.searchsorted(code_y, wanted), len(code_y) - 1)
                hit = code_y[at] == wanted
                u, v = x.ws[entry[hit]], y.ws[at[hit]]
                i[live] += np.bincount(np.repeat(np.arange(len(live)), take)[hit], u * v if product else np.minimum(u, v), len(live))
                here[live] += take
                next_r = np.searchsorted(code_y, code_x[here[live] - 1] + (r[live] - l[live]) * step, side="right")
                rest_l = np.maximum(mass_x[here[live]] - mass_x[end_l[live]], 0.0)
                rest_r = np.maximum(mass_y[next_r] - mass_y[end_r[live]], 0.0)
                rest = np.sqrt(rest_l * rest_r) if product else np.minimum(rest_l, rest_r)
                # sums over a whole block carry more rounding than a record's
                short = m.number(i[live] + rest + 1e-6, x.total[l[live]], y.total[r[live]]) < tau
                out[live[short]] = True
                live = live[~short & (here[live] < end_l[live]) & (next_r < end_r[live])]
        i[out] = 0.0
        sim = m.number(i, x.total[l], y.total[r])
        return np.where(np.round(sim, 9) >= round(tau, 9), sim, 0.0)

    return compare


def partial_similarity(pairs: DataFrame, sets_a: DataFrame, sets_b: DataFrame, measure: str, tau: float) -> DataFrame:
    """``(a_id, b_id, sim)`` of pairs ``(a_id, b_id, key)`` with their first shared token; 0 below ``tau``.

    A key that a record lacks leaves an empty suffix and so 0.
    """
    return verify(pairs, sets_a, sets_b, measure, partial(measure, tau), "key")


def partial_pairs(p: Prepared, tau: float) -> DataFrame:
    """Partial similarities of all pairs of two collections that share a token; a small side goes to every task."""
    if not p.dedup and (small := smaller(p)) is not None:
        return merge_lists(p, small, compare=partial(p.measure, tau))
    return partial_similarity(first_shared(p), arrays(p.a, "a"), arrays(p.b, "b"), p.measure, tau)


def first_shared(p: Prepared, tau: float = 0.0, filters: frozenset = frozenset()) -> DataFrame:
    """``(a_id, b_id, key)``: the first shared token of pairs that the filters leave at ``tau``."""
    probe = thresholds(p.a, MEASURES[p.measure], F.lit(float(tau)), filters)
    met = pre_candidates(probe, p.b, MEASURES[p.measure], filters, p.dedup, tau, half=True)
    return met.groupBy(F.col("rec_id").alias("a_id"), "b_id").agg(F.min("key").alias("key"))


def partial_join(p: Prepared, tau: float, filters: frozenset = frozenset({"prefix", "size", "suffix", "positional"})) -> DataFrame:
    """The threshold join with partial similarities as its verification."""
    if hasattr(p.a, "_packed") and hasattr(p.b, "_packed"):
        # what prefixes share is summed as they meet; a pair goes on behind them only while it can reach the threshold
        found = swept(p.a._packed, p.b._packed, MEASURES[p.measure], tau, filters, p.dedup, (tau, 0.0, None))
    else:
        found = partial_similarity(first_shared(p, tau, filters), arrays(p.a, "a"), arrays(p.b, "b"), p.measure, tau)
    out = conditions(found, tau, 0.0, None)
    return unordered(out) if p.dedup else out
