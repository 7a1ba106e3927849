"""The unsupervised blocker: from a budget of pairs and a quality to conditions and pairs."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .estimate import SAMPLE, Trajectories, record
from .join import JoinConfig, directed_join, unordered
from .quality import CONFIDENCE, rank_for
from .tokens import allow_ngrams
from .weights import Prepared, TokenModel, prepare

SPACE = [(TokenModel(t, "tfidf"), m) for t in ("trigram", "word") for m in ("jaccard", "cosine", "overlap")]
NEIGHBOURS = 10


def split_budget(n_a: int, n_b: int, k: int) -> tuple[int, int]:
    """(k of A's probes, k of B's probes) for n_a <= n_b: halves of k pairs for each record of A."""
    back = (k * n_a) // (2 * n_b) if n_b else 0
    return ((k * n_a - back * n_b) // n_a if n_a else 0), back


def discriminative_power(t: Trajectories, k: int = NEIGHBOURS) -> float:
    """1 less the mean similarity of a probe's other neighbours relative to its best one."""
    s = t.sims[:, :k]
    best = np.maximum(s[:, :1], 1e-300)
    rest = np.where(s[:, :1] > 0, (s / best)[:, 1:].sum(axis=1, keepdims=True), 0.0)
    return float(1 - (rest / (k - 1)).mean()) if len(s) else 0.0


def balance(t: Trajectories, k: int, n_a: int) -> tuple[float, float]:
    """The highest tau and tau_r, on bin edges, each of which alone would meet the budget."""
    budget = k * n_a
    tau = next((e for e in t.edges()[-2::-1] if t.pairs(float(e), 0.0, None) >= budget), 0.0)
    steps = np.arange(100, -1, -1) / 100
    tau_r = next((e for e in steps if t.pairs(0.0, float(e), None) >= budget), 0.0)
    return float(tau), float(tau_r)


@dataclass
class Choice:
    model: TokenModel
    measure: str
    power: float
    tau: float = 0.0
    tau_r: float = 0.0
    k: int = 0
    rho: int | None = None
    quality: float = 1.0
    direction: str = "a->b"

    def describe(self) -> str:
        cut = "" if self.rho is None else f", at most {self.rho} list entries (quality {self.quality} with probability {CONFIDENCE})"
        return f"{self.direction}: {self.model.name} {self.measure} >= {self.tau:.4g}, >= {self.tau_r:.3g} of the best, first {self.k}{cut}"


def balanced(prepared: dict, k: int, q: float, sample: int, direction: str) -> tuple[Choice, Prepared]:
    """The model of highest discriminative power and its balanced conditions, for one direction."""
    best = None
    for (model, measure), p in prepared.items():
        t = record(p, sample)
        power = discriminative_power(t)
        if best is None or power > best[0] + 1e-12:
            best = (power, model, measure, p, t)
    power, model, measure, p, t = best
    tau, tau_r = balance(t, k, p.n_a)
    rho = rank_for(q, t, tau, tau_r, k)
    return Choice(model, measure, power, tau, tau_r, k, rho, q, direction), p


def block(a: DataFrame, b: DataFrame | None, k: int = 10, q: float = 1.0, space: list | None = None, sample: int = SAMPLE, explain: list | None = None) -> DataFrame:
    """``(a_id, b_id)`` of at most k pairs for each record of the smaller collection.

    ``b=None`` deduplicates ``a``. ``explain`` gets the chosen conditions.
    """
    dedup = b is None
    n_a = a.count()
    n_b = n_a if dedup else b.count()
    swapped = not dedup and n_a > n_b
    if swapped:
        a, b, n_a, n_b = b, a, n_b, n_a
    if n_a == 0 or n_b == 0:
        return a.select(F.col("rec_id").alias("a_id"), F.col("rec_id").alias("b_id")).where("false")
    space = space or SPACE
    if any(m.tokenizer == "trigram" for m, _ in space) and not allow_ngrams(a, *([] if dedup else [b])):
        space = [(m, s) for m, s in space if m.tokenizer != "trigram"]
    shared: dict = {}
    forward = {(m, s): prepare(a, b, m, s, shared) for m, s in space}
    found = []
    if dedup:
        choice, p = balanced(forward, k, q, sample, "dedup")
        found.append((choice, unordered(directed_join(p, JoinConfig(choice.tau, choice.tau_r, choice.k, choice.rho))).select("a_id", "b_id")))
    else:
        k_ab, k_ba = split_budget(n_a, n_b, k)
        for budget, sets, direction in ((k_ab, forward, "a->b"), (k_ba, {c: p.flipped() for c, p in forward.items()}, "b->a")):
            if budget == 0:
                continue
            choice, p = balanced(sets, budget, q, sample, direction)
            pairs = directed_join(p, JoinConfig(choice.tau, choice.tau_r, choice.k, choice.rho)).select("a_id", "b_id")
            if direction == "b->a":
                pairs = pairs.select(F.col("b_id").alias("a_id"), F.col("a_id").alias("b_id"))
            found.append((choice, pairs))
    if explain is not None:
        explain += [c for c, _ in found]
    out = found[0][1]
    for _, more in found[1:]:
        out = out.union(more)
    out = out.distinct()
    return out.select(F.col("b_id").alias("a_id"), F.col("a_id").alias("b_id")) if swapped else out
