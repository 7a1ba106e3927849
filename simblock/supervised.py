"""The supervised blocker: conditions of up to two joins tuned on known matches."""

from __future__ import annotations

import time
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .estimate import MARGINS, SIGMA, Trajectories, recall_conditions, record, sample_probes
from .join import JoinConfig, directed_join, unordered
from .quality import CONFIDENCE, rank_for
from .tokens import allow_ngrams
from .unsupervised import Choice
from .weights import Prepared, TokenModel, prepare

SPACE = [(TokenModel(t, w), m) for w in ("binary", "tfidf") for t in ("trigram", "word") for m in ("jaccard", "cosine", "dice", "overlap")]
SAMPLE = 500
RESTARTS, DRAWS = 32, 10
SECONDS_PER_ENTRY = 1e-7  # where nothing was measured


@dataclass
class Side:
    """One direction's material: by configuration, trajectories and conditions by margin."""

    prepared: list[Prepared]
    trajectories: list[Trajectories]
    theta: list[pd.DataFrame]


@dataclass(frozen=True)
class Point:
    config: int
    tau: float
    tau_r: float
    k: int
    rho: int | None


def calibrate(entries: float, seconds: float) -> float:
    """Seconds for each visited list entry, from one measured join."""
    return seconds / max(entries, 1.0)


def measured_seconds(p: Prepared, t: Trajectories, sample: int = SAMPLE) -> float:
    """Seconds for each visited entry, from two threshold joins of the sampled probes.

    What both joins take alike, such as starting jobs, falls out of the difference. If the
    longer walk is not the slower one, entries cost too little to be seen and the default stays.
    """
    part = Prepared(sample_probes(p.a, sample), p.b, p.vocabulary, len(t.probes), p.n_b, p.measure, p.dedup, p.weighting)
    best = t.sims[:, 0] if t.sims.size else np.zeros(1)
    seen = []
    for tau in (0.9 * t.top, float(np.quantile(best, 0.1))):
        start = time.perf_counter()
        directed_join(part, JoinConfig(tau)).count()
        seen.append((t.visited(tau, 0.0, None, None, SIGMA[t.measure]) / t.scale, time.perf_counter() - start))
    (few, fast), (many, slow) = seen
    return calibrate(many - few, slow - fast) if many > few and slow > fast else SECONDS_PER_ENTRY


def evaluate(sides: list[Side], point: tuple[Point, ...], rows: np.ndarray, margin: float, n_min: int, seconds_per_entry: float) -> tuple[float, float, float]:
    """(recall over the chosen matches, pairs for each record, seconds)."""
    hit = np.zeros(len(rows), dtype=bool)
    pairs = seconds = 0.0
    for side, x in zip(sides, point):
        if x.k == 0:
            continue
        th = side.theta[x.config]
        th = th[th["d"] == margin].sort_values(["a_id", "b_id"]).iloc[rows] if len(th) else th
        ok = (th["tau_max"] >= x.tau - 1e-9) & (th["tau_r_max"] >= x.tau_r - 1e-9) & (th["k_min"] <= x.k)
        if x.rho is not None:
            ok &= th["rank_min"] <= x.rho
        hit |= ok.fillna(False).to_numpy(dtype=bool)
        t = side.trajectories[x.config]
        pairs += t.pairs(x.tau, x.tau_r, x.k, x.rho)
        seconds += seconds_per_entry * t.visited(x.tau, x.tau_r, x.k, x.rho, SIGMA[t.measure])
    return float(hit.mean()) if len(hit) else 0.0, pairs / n_min, seconds


def optimise(sides: list[Side], rows: np.ndarray, margin: float, objective, n_min: int, seed: int, restarts: int = RESTARTS, draws: int = DRAWS, seconds_per_entry: float = SECONDS_PER_ENTRY, q: float = 1.0) -> tuple:
    """(value, point): random draws, the best of which climbs by steps of growing and shrinking size."""
    rng = np.random.default_rng(seed)

    def stopped(side: Side, x: Point) -> Point:
        return Point(x.config, x.tau, x.tau_r, x.k, rank_for(q, side.trajectories[x.config], x.tau, x.tau_r, x.k))

    def draw() -> tuple[Point, ...]:
        out = []
        for side in sides:
            c = int(rng.integers(len(side.prepared)))
            x = Point(c, float(rng.random() ** 2 * side.trajectories[c].top), float(rng.random()), int(rng.choice([0, 1, 2, 3, 5, 8, 13, 21, 50])), None)
            out.append(stopped(side, x) if q < 1 and x.k > 0 and rng.random() < 0.5 else x)
        return tuple(out)

    def value(point: tuple[Point, ...]):
        return objective(*evaluate(sides, point, rows, margin, n_min, seconds_per_entry))

    def neighbours(point: tuple[Point, ...]):
        for i, x in enumerate(point):
            top = sides[i].trajectories[x.config].top
            options = [Point(c, x.tau, x.tau_r, x.k, x.rho) for c in range(len(sides[i].prepared)) if c != x.config]
            for s in (0.005, 0.02, 0.08, 0.3):
                options += [Point(x.config, min(top, max(0.0, x.tau + d * s * top)), x.tau_r, x.k, x.rho) for d in (-1, 1)]
                options += [Point(x.config, x.tau, min(1.0, max(0.0, x.tau_r + d * s)), x.k, x.rho) for d in (-1, 1)]
            options += [Point(x.config, x.tau, x.tau_r, max(0, x.k + d), x.rho) for d in (-8, -4, -2, -1, 1, 2, 4, 8)]
            if q < 1 and x.k > 0:
                options += [stopped(sides[i], x), Point(x.config, x.tau, x.tau_r, x.k, None)]
            for y in options:
                yield (*point[:i], y, *point[i + 1 :])

    best = None
    for _ in range(restarts):
        now = max((draw() for _ in range(draws)), key=value)
        score = value(now)
        while True:
            nxt = max(neighbours(now), key=value)
            if value(nxt) <= score:
                break
            now, score = nxt, value(nxt)
        if best is None or score > best[0]:
            best = (score, now)
    return best


def choose_margin(sides: list[Side], n: int, margins: tuple, objective, n_min: int, seed: int, restarts: int, q: float = 1.0, seconds_per_entry: float = SECONDS_PER_ENTRY) -> float:
    """The margin whose tuned conditions score best on left-out matches in three folds."""
    if n < 3:
        return max(margins)
    folds = np.random.default_rng(seed).permutation(n) % 3
    scored = []
    for d in margins:
        values = []
        for f in range(3):
            _, point = optimise(sides, np.flatnonzero(folds != f), d, objective, n_min, seed + f, max(1, restarts // 8), seconds_per_entry=seconds_per_entry, q=q)
            values.append(evaluate(sides, point, np.flatnonzero(folds == f), 0.0, n_min, seconds_per_entry))
        scored.append((objective(*(float(np.mean(x)) for x in zip(*values))), -d))
    return -max(scored)[1]


def block(a: DataFrame, b: DataFrame | None, matches: DataFrame, objective, space: list | None = None, sample: int = SAMPLE, margins: tuple = MARGINS, seed: int = 1, restarts: int = RESTARTS, explain: list | None = None, q: float = 1.0, seconds_per_entry: float | None = None) -> DataFrame:
    """``(a_id, b_id)`` of the tuned joins; ``b=None`` deduplicates (one direction).

    With ``q`` below 1 each direction may stop its walk at the least rank that keeps this quality.
    Seconds for each visited list entry are measured unless given (a given value makes choices repeatable).
    """
    dedup = b is None
    space = space or SPACE
    if any(m.tokenizer == "trigram" for m, _ in space) and not allow_ngrams(a, *([] if dedup else [b])):
        space = [(m, s) for m, s in space if m.tokenizer != "trigram"]
    if dedup:  # a pair may be found from either record
        turned = matches.select(F.col("b_id").alias("a_id"), F.col("a_id").alias("b_id"))
        matches = matches.select("a_id", "b_id").union(turned).distinct()
    shared: dict = {}
    forward = [prepare(a, b, m, s, shared) for m, s in space]
    sides = []
    for direction in range(1 if dedup else 2):
        ps = forward if direction == 0 else [p.flipped() for p in forward]
        ms = matches if direction == 0 else matches.select(F.col("b_id").alias("a_id"), F.col("a_id").alias("b_id"))
        thetas = [recall_conditions(p, ms, margins).toPandas() for p in ps]
        if direction == 1:
            thetas = [t.rename(columns={"a_id": "b_id", "b_id": "a_id"}) for t in thetas]
        sides.append(Side(ps, [record(p, sample) for p in ps], thetas))
    n = len(sides[0].theta[0]) // len(margins)
    n_min = min(forward[0].n_a, forward[0].n_b)
    if seconds_per_entry is None:
        seconds_per_entry = measured_seconds(forward[0], sides[0].trajectories[0], sample)
    margin = choose_margin(sides, n, margins, objective, n_min, seed, restarts, q, seconds_per_entry)
    _, point = optimise(sides, np.arange(n), margin, objective, n_min, seed, restarts, seconds_per_entry=seconds_per_entry, q=q)
    out = None
    for i, (side, x) in enumerate(zip(sides, point)):
        if explain is not None and x.k:
            explain.append(Choice(*space[x.config], 0.0, x.tau, x.tau_r, x.k, x.rho, q, ("dedup" if dedup else "a->b") if i == 0 else "b->a"))
        if x.k == 0:
            continue
        pairs = directed_join(side.prepared[x.config], JoinConfig(x.tau, x.tau_r, x.k, x.rho))
        if dedup:
            pairs = unordered(pairs)
        pairs = pairs.select("a_id", "b_id") if i == 0 else pairs.select(F.col("b_id").alias("a_id"), F.col("a_id").alias("b_id"))
        out = pairs if out is None else out.union(pairs)
    if out is None:
        return matches.select("a_id", "b_id").where("false")
    return out.distinct()
