"""The hybrid similarity join: absolute, relative and per-probe-cardinality conditions at once.

A pair is in the result if it shares a token and its similarity is at least ``tau``, at
least ``tau_r`` times the probe's best, and among the probe's first ``k`` (ties by the
smaller index record). A small side is merged in every task, and large ones are joined block by
block (``sweep``). The sequential method walks inverted lists while the
threshold rises; where only a part of a side is given, the same set is worked out in rounds. A round at threshold t joins
the prefixes that t asks for, which finds all pairs of similarity t or more;
a probe is final once its k-th best or ``tau_r`` times its best reaches t, or t has come down
to ``tau``. Pairs that were verified below t are kept too: the k-th best of all that a probe
has seen bounds its k-th best partner from below, so a later round, which holds unfinished probes only,
never asks for less, and only probes that have met fewer than k partners come down to ``tau``.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .measures import MEASURES, Measure
from .plans.stages import cut
from .weights import Prepared, Stream, Unwritten, entries, sliced

LEVELS = (0.5, 0.3, 0.15, 0.08)
FILTERS = frozenset({"prefix", "size", "suffix", "positional"})
SMALL = 200_000  # tokens of a side that is sent to every task
BLOCK = 4_000_000  # tokens of the records of one side that a task compares at once
LETTERS = 50  # bytes of text for each token, beyond which a side is not counted to see whether it is small
WHOLE = 0.2  # thresholds below which large sides are merged by their whole lists
HELD = 200_000  # pairs of a task that are held before they are sifted
CHUNK = 1 << 21  # tokens of pairs that are compared at once


@dataclass(frozen=True)
class JoinConfig:
    tau: float = 0.0
    tau_r: float = 0.0
    k: int | None = None
    rho: int | None = None
    filters: frozenset | None = None
    levels: tuple = LEVELS


def _posting(side: DataFrame) -> DataFrame:
    return side.select("key", F.col("rec_id").alias("b_id"), F.col("w").alias("w_b"), F.col("pre").alias("p_b"), F.col("suf").alias("s_b"), F.col("total").alias("t_b"))


def admissible(m: Measure, filters: frozenset, t: Column) -> Column:
    """Residual of the token join: which list entries the probe's token may meet."""
    s_a, p_a, t_a = F.col("suf"), F.col("pre"), F.col("total")
    s_b, p_b, t_b = F.col("s_b"), F.col("p_b"), F.col("t_b")
    out = F.lit(True)
    if "size" in filters:
        out = out & (t_b >= m.size_low(t, t_a))
        if (high := m.size_high(t, t_a)) is not None:
            out = out & (t_b <= high)
    if "suffix" in filters:
        out = out & (s_b >= m.suffix_low(t, t_a, s_a, p_b))
        if (high := m.suffix_high(t, s_a, p_a, p_b)) is not None:
            out = out & (s_b <= high)
    if "suffix_plain" in filters:  # the bounds of the size filter, on suffixes
        out = out & (s_b >= m.size_low(t, t_a))
        if (high := m.size_high(t, t_a)) is not None:
            out = out & (s_b <= high)
    if "positional" in filters:
        out = out & m.attainable(t, s_a, s_b, t_a, t_b)
    if "positional_exact" in filters:
        out = out & m.attainable_exact(t, s_a, s_b, t_a, t_b, F.col("w"), F.col("w_b"))
    return out


def thresholds(side: DataFrame, m: Measure, t: Column | DataFrame, filters: frozenset = FILTERS) -> DataFrame:
    """Rows of a prepared side with a threshold, a column or ``(rec_id, t)``; of its prefixes only, if they filter."""
    sets = getattr(side, "_packed", None)
    add = (lambda df: df.withColumn("t", t)) if isinstance(t, Column) else (lambda df: df.join(t, "rec_id"))
    if sets is None:
        return add(side)
    return entries(add(sets), m.power, m.sigma if "prefix" in filters else None)


def pre_candidates(probe: DataFrame, index: DataFrame, m: Measure, filters: frozenset, dedup: bool, low: float = 0.0, half: bool = False) -> DataFrame:
    """Entries of both prefixes that meet on a token; ``probe`` has its threshold in ``t``.

    No threshold is below ``low``, by which the index is cut before it is shuffled. With
    ``half`` a pair of a deduplication is met from its smaller id only.
    """
    if "prefix" in filters:
        index = thresholds(index, m, F.lit(float(low))).drop("t")
        index = index.where(F.col("suf") >= m.sigma(F.col("total"), F.lit(float(low))))
        probe = probe.where(F.col("suf") >= m.sigma(F.col("total"), F.col("t")))
        # the index side's own prefix at the probe's threshold
        own = F.col("s_b") >= m.sigma(F.col("t_b"), F.col("t"))
    else:
        own = F.lit(True)
    joined = probe.join(_posting(index), "key").where(own & admissible(m, filters, F.col("t")))
    return joined.where("rec_id < b_id" if half else "rec_id <> b_id") if dedup else joined


def candidates(pre: DataFrame, m: Measure) -> DataFrame:
    """``(a_id, b_id, i, total, t_b, t)``: pairs that may still reach ``t``, with what they are known to share.

    Each filter fails for good once it fails on a pair's shared tokens in their order, so the entries
    that are left are the pair's first shared tokens. Behind the last of them no more is
    shared than both records have left, which are the least remainders seen. Sums and minima are
    combined before the shuffle, and no token list travels for a pair that falls here.
    """
    square = (lambda w: w * w) if m.power == 2 else (lambda w: w)
    met = pre.groupBy(F.col("rec_id").alias("a_id"), "b_id").agg(
        F.sum(m.shared(F.col("w"), F.col("w_b"))).alias("i"),
        F.min(F.col("suf") - square(F.col("w"))).alias("_a"),
        F.min(F.col("s_b") - square(F.col("w_b"))).alias("_b"),
        *[F.max(c).alias(c) for c in ("total", "t_b", "t")],
    )
    left_a, left_b = F.greatest("_a", F.lit(0.0)), F.greatest("_b", F.lit(0.0))
    rest = F.sqrt(left_a * left_b) if m.power == 2 else F.least(left_a, left_b)
    return met.where(m.value(F.col("i") + rest, F.col("total"), F.col("t_b")) >= F.col("t") - 1e-8).drop("_a", "_b")


def known(pairs: DataFrame, m: Measure) -> DataFrame:
    """``(a_id, b_id, sim)`` of candidates at threshold 0, whose shared tokens have all been met."""
    return pairs.select("a_id", "b_id", m.value(F.col("i"), F.col("total"), F.col("t_b")).alias("sim"))


def arrays(side: DataFrame, prefix: str) -> DataFrame:
    """``(id, keys, weights, total)``: one row a record, tokens in global order."""
    sets = getattr(side, "_packed", None)
    if sets is None:
        sets = side.groupBy("rec_id").agg(F.sort_array(F.collect_list(F.struct("key", "w"))).alias("s"), F.first("total").alias("total")).select("rec_id", F.col("s.key").alias("keys"), F.col("s.w").alias("ws"), "total")
    return sets.select(*[F.col(c).alias(f"{prefix}_{d}") for c, d in (("rec_id", "id"), ("keys", "keys"), ("ws", "ws"), ("total", "total"))])


class Sets:
    """Token sets of a block of records as flat arrays."""

    def __init__(self, keys: pa.ListArray, ws: pa.ListArray, total: pa.Array):
        ends = keys.offsets.to_numpy()
        self.ends, self.keys = (ends - ends[0]).astype(np.int64), keys.flatten().to_numpy(zero_copy_only=False)
        self.ws, self.total = ws.flatten().to_numpy(zero_copy_only=False), total.to_numpy(zero_copy_only=False)
        self.row = np.repeat(np.arange(len(keys)), np.diff(self.ends))

    def coded(self, known: np.ndarray) -> np.ndarray:
        """Row and key of every entry in one rising number; ``known`` holds all keys, sorted."""
        return self.row * (len(known) + 1) + np.searchsorted(known, self.keys)


def spans(first: np.ndarray, n: np.ndarray) -> np.ndarray:
    """The numbers of ranges that begin at ``first`` and hold ``n``, one after another."""
    return np.repeat(first - (np.cumsum(n) - n), n) + np.arange(n.sum())


def whole(measure: str):
    """Similarity of pairs ``(l, r)`` of records of two blocks: the shorter set's tokens are looked up in the other."""
    m = MEASURES[measure]

    def compare(x: Sets, y: Sets, l: np.ndarray, r: np.ndarray) -> np.ndarray:  # noqa: E741
        known = np.union1d(x.keys, y.keys)
        code = (x.coded(known), y.coded(known))
        i, step = np.zeros(len(l)), len(known) + 1
        longer = np.diff(x.ends)[l] > np.diff(y.ends)[r]
        for swap in (False, True):
            mine = np.flatnonzero(longer == swap)
            (p, q), (own, other) = ((y, x), (r, l)) if swap else ((x, y), (l, r))
            code_p, code_q = code[::-1] if swap else code
            n = np.diff(p.ends)[own[mine]]
            for some in np.split(mine, np.searchsorted(np.cumsum(n), np.arange(CHUNK, n.sum(), CHUNK))):
                if not len(some) or not len(code_q):
                    continue
                n = np.diff(p.ends)[own[some]]
                entry, pair = spans(p.ends[own[some]], n), np.repeat(np.arange(len(some)), n)
                wanted = code_p[entry] + (other[some][pair] - own[some][pair]) * step
                at = np.minimum(np.searchsorted(code_q, wanted), len(code_q) - 1)
                hit = code_q[at] == wanted
                u, v = p.ws[entry[hit]], q.ws[at[hit]]
                i[some] = np.bincount(pair[hit], u * v if measure == "cosine" else np.minimum(u, v), len(some))
        return m.number(i, x.total[l], y.total[r])

    return compare


def verify(pairs: DataFrame, sets_a: DataFrame, sets_b: DataFrame, measure: str, compare=None, at: str | None = None) -> DataFrame:
    """``(a_id, b_id, sim)`` of candidate pairs.

    A record's tokens are sent once to each block of records of the other side in which it has a candidate, not
    once a pair: pairs become lists of partners by record and block, and a task compares two blocks.
    ``compare`` replaces :func:`whole`; ``at`` names a long column of pairs that it takes too.
    """
    compare = compare or whole(measure)
    n_a, n_b = (max(1, -(-(s.agg(F.sum(F.size(f"{x}_keys"))).first()[0] or 0) // BLOCK)) for s, x in ((sets_a, "a"), (sets_b, "b")))
    block = lambda c, n: F.pmod(F.xxhash64(c), F.lit(n)).cast("int")
    partner = F.struct(F.col("b_id").alias("id"), F.lit(0).cast("long").alias("at") if at is None else F.col(at).alias("at"))
    left = pairs.groupBy("a_id", block("b_id", n_b).alias("_y")).agg(F.collect_list(partner).alias("_to")).join(sets_a, "a_id").withColumn("_x", block("a_id", n_a))
    right = sets_b.withColumn("_y", block("b_id", n_b)).withColumn("_x", F.explode(F.sequence(F.lit(0), F.lit(n_a - 1))))
    id_a, id_b = pairs.schema["a_id"].dataType.simpleString(), pairs.schema["b_id"].dataType.simpleString()

    def met(x: pa.Table, y: pa.Table) -> pa.Table:
        schema = pa.schema([("a_id", x.schema.field("a_id").type), ("b_id", y.schema.field("b_id").type), ("sim", pa.float64())])
        if not len(x) or not len(y):
            return schema.empty_table()
        x, y = ({c: t[c].combine_chunks() for c in t.column_names} for t in (x, y))
        x, y = ({c: v.chunk(0) if isinstance(v, pa.ChunkedArray) else v for c, v in t.items()} for t in (x, y))
        to = x["_to"].flatten()
        l = np.repeat(np.arange(len(x["_to"])), np.diff(x["_to"].offsets.to_numpy()))  # noqa: E741
        r = pc.index_in(to.field("id"), value_set=y["b_id"])
        found = r.is_valid().to_numpy(zero_copy_only=False)
        l, r = l[found], r.drop_null().to_numpy(zero_copy_only=False).astype(np.int64)  # noqa: E741
        more = [] if at is None else [to.field("at").to_numpy(zero_copy_only=False)[found]]
        sim = compare(*(Sets(t[f"{c}_keys"], t[f"{c}_ws"], t[f"{c}_total"]) for t, c in ((x, "a"), (y, "b"))), l, r, *more)
        return pa.Table.from_arrays([x["a_id"].take(pa.array(l)), y["b_id"].take(pa.array(r)), pa.array(sim, pa.float64())], schema=schema)

    return left.groupBy("_x", "_y").cogroup(right.groupBy("_x", "_y")).applyInArrow(met, f"a_id {id_a}, b_id {id_b}, sim double")


def merged(small: DataFrame, large: DataFrame | Stream, m: Measure, best: tuple | None = None, compare=None) -> DataFrame:
    """``(a_id, b_id, sim)`` of all pairs of packed sides that share a token; ``small`` goes to every task.

    The lists of the small side are merged for each record of the large one, so that no row of it is
    shuffled. ``best`` is (tau, tau_r, k): pairs that fail them among those of a task fail them among all, and are left
    out. ``compare`` scores pairs from their first shared token on instead.
    """
    one = small.toArrow().combine_chunks()
    parts = None if not len(one) else [one[c].combine_chunks() for c in ("rec_id", "keys", "ws", "total")]
    parts = parts and [c.chunk(0) if isinstance(c, pa.ChunkedArray) else c for c in parts]
    frame, read = (large.frame, large.sets) if isinstance(large, Stream) else (large, None)
    sent = frame.sparkSession.sparkContext.broadcast(parts)
    id_a, id_b = (x.schema["rec_id"].dataType.simpleString() for x in (small, frame))

    def pairs(batches):
        ids, x = sent.value[0], Sets(*sent.value[1:])
        order = np.argsort(x.keys, kind="stable")
        keys, ws, owner = x.keys[order], x.ws[order], x.row[order]
        known = np.unique(keys)
        for every in batches if read is None else read(batches):
            for batch in sliced(every, "keys"):
                y = Sets(*(batch.column(c) for c in ("keys", "ws", "total")))
                first, many = np.zeros(len(y.keys), np.int64), np.zeros(len(y.keys), np.int64)
                held = np.flatnonzero(known[np.minimum(np.searchsorted(known, y.keys), len(known) - 1)] == y.keys) if len(known) else np.zeros(0, np.int64)
                first[held] = np.searchsorted(keys, y.keys[held])
                many[held] = np.searchsorted(keys, y.keys[held], side="right") - first[held]
                for some in _parts(many, y.row):
                    n = many[some]
                    at = spans(first[some], n)
                    base = y.row[some.start]
                    pair, room = (np.repeat(y.row[some], n) - base) * len(ids) + owner[at], (y.row[some.stop - 1] - base + 1) * len(ids)
                    if compare is None:
                        u, v = ws[at], np.repeat(y.ws[some], n)
                        i = np.bincount(pair, u * v if m.name == "cosine" else np.minimum(u, v), room)
                    else:
                        key = np.zeros(room, dtype=np.int64)
                        key[pair[::-1]] = keys[at][::-1]  # the last one written is the first met
                    pair = np.flatnonzero(np.bincount(pair, minlength=room))
                    a, b = pair % len(ids), pair // len(ids) + base
                    sim = m.number(i[pair], x.total[a], y.total[b]) if compare is None else compare(x, y, a, b, key[pair])
                    if best is not None:
                        a, b, sim = _leading(a, b, sim, *best)
                    yield a, batch.column("rec_id").take(pa.array(b)), sim

    def join(batches):
        if sent.value is None:
            return
        row = lambda a, b, sim: pa.RecordBatch.from_arrays([sent.value[0].take(pa.array(a)), b, pa.array(sim)], ["a_id", "b_id", "sim"])
        if best is None or (best[1] == 0 and best[2] is None):
            yield from (row(*x) for x in pairs(batches))
            return
        held, size, least = [], 0, 0
        for x in pairs(batches):
            held.append(x)
            size += len(x[0])
            if size > 2 * least + HELD:
                held = [_best(held, best)]
                size = least = len(held[0][0])
        if held:
            yield row(*_best(held, best))

    return frame.mapInArrow(join, f"a_id {id_a}, b_id {id_b}, sim double")


def _best(held: list, best: tuple) -> tuple:
    """:func:`_leading` over parts ``(a, b's ids, sim)``."""
    ids = pa.concat_arrays([b for _, b, _ in held])
    a, at, sim = _leading(np.concatenate([a for a, _, _ in held]), np.arange(len(ids)), np.concatenate([s for _, _, s in held]), *best)
    return a, ids.take(pa.array(at)), sim


def _parts(many: np.ndarray, row: np.ndarray):
    """Ranges of entries, whole records each, that meet about ``CHUNK`` list entries."""
    ends = np.flatnonzero(np.diff(row, append=-1)) + 1
    met = np.concatenate([[0], np.cumsum(many)])
    start = 0
    while start < len(row):
        stop = ends[min(max(np.searchsorted(met[ends], met[start] + CHUNK, side="right") - 1, np.searchsorted(ends, start, side="right")), len(ends) - 1)]
        yield slice(start, int(stop))
        start = int(stop)


def _leading(a: np.ndarray, b: np.ndarray, sim: np.ndarray, tau: float, tau_r: float, k: int | None):
    """Pairs that reach ``tau``, ``tau_r`` times their probe's best here and its k-th best similarity here, ties too."""
    keep = (sim > 0) & (sim >= tau - 1e-8)
    a, b, sim = a[keep], b[keep], sim[keep]
    order = np.lexsort((-sim, a))
    a, b, sim = a[order], b[order], sim[order]
    start = np.flatnonzero(np.diff(a, prepend=-1))
    n = np.diff(np.append(start, len(a)))
    keep = sim >= np.repeat(sim[start] * tau_r, n) - 1e-8
    if k is not None:
        keep &= sim >= np.repeat(np.where(n >= k, sim[start + np.minimum(n, k) - 1], 0.0), n) - 1e-8
    return a[keep], b[keep], sim[keep]


def conditions(pairs: DataFrame, tau: float, tau_r: float, k: int | None) -> DataFrame:
    """The three conditions over scored pairs ``(a_id, b_id, sim)``."""
    by = Window.partitionBy("a_id")
    out = pairs.where((F.col("sim") > 0) & (F.round("sim", 9) >= round(tau, 9)))
    if tau_r > 0:
        out = out.withColumn("_best", F.max("sim").over(by)).where(F.round("sim", 9) >= F.round(F.col("_best") * tau_r, 9)).drop("_best")
    if k is not None:
        out = out.withColumn("_n", F.row_number().over(by.orderBy(F.round("sim", 9).desc(), "b_id"))).where(F.col("_n") <= k).drop("_n")
    return out


def unordered(pairs: DataFrame) -> DataFrame:
    """Each pair of a deduplication once, smaller id first."""
    return pairs.groupBy(F.least("a_id", "b_id").alias("a_id"), F.greatest("a_id", "b_id").alias("b_id")).agg(F.max("sim").alias("sim"))


def _sets(p: Prepared, x: str) -> DataFrame | Stream:
    """Packed records of a side, as they are read if they can be and are not written yet."""
    return (p.stream(x) if isinstance(p, Unwritten) and p.codes._written is None else None) or getattr(p, x)._packed


def smaller(p: Prepared) -> str | None:
    """The side of at most ``SMALL`` tokens, if there is one; the first of two."""
    if not isinstance(p, Unwritten) and not all(hasattr(side, "_packed") for side in (p.a, p.b)):  # a part of a side has rows only
        return None
    for x in "ab":
        if isinstance(p, Unwritten) and p.bytes(x) > LETTERS * SMALL:
            continue
        sets = _sets(p, x)
        sets = sets.packed() if isinstance(sets, Stream) else sets
        if (sets.agg(F.sum(F.size("keys"))).first()[0] or 0) <= SMALL:
            return x
    return None


def merge_lists(p: Prepared, small: str, best: tuple | None = None, compare=None) -> DataFrame:
    """``(a_id, b_id, sim)`` of all pairs of two collections that share a token, with one side sent to every task."""
    m = MEASURES[p.measure]
    one, large = (_sets(p, x) for x in ("ab" if small == "a" else "ba"))
    one = one.packed() if isinstance(one, Stream) else one
    if small == "a":
        return merged(one, large, m, best, compare)
    turned = merged(one, large, m, None if best is None else (best[0], 0.0, None), compare)  # a probe's conditions are not an index record's
    return turned.select(F.col("b_id").alias("a_id"), F.col("a_id").alias("b_id"), "sim")


def directed_join(p: Prepared, cfg: JoinConfig) -> DataFrame:
    """``(a_id, b_id, sim)`` of one direction (no self pairs in deduplication).

    A deduplication by threshold only is symmetric and gives each pair from its smaller id.
    """
    if cfg.k == 0 or cfg.rho == 0:
        return p.a.select(F.col("rec_id").alias("a_id"), F.col("rec_id").alias("b_id"), F.lit(0.0).alias("sim")).where("false")
    if cfg.rho is not None:
        from .cutoff import rank_cut_pairs

        return conditions(rank_cut_pairs(p, cfg.rho), cfg.tau, cfg.tau_r, cfg.k)
    m = MEASURES[p.measure]
    filters = FILTERS if cfg.filters is None else cfg.filters
    small = None if p.dedup else smaller(p)
    if small is not None and (cfg.filters is None or cfg.tau <= 0 or "prefix" not in filters):  # at threshold 0 filters leave all
        if cfg.filters is not None:
            _ = p.a, p.b  # written, as who names filters compares several joins
        return conditions(merge_lists(p, small, (cfg.tau, cfg.tau_r, cfg.k)), cfg.tau, cfg.tau_r, cfg.k)
    if small == "a":
        from .sweep import swept

        # the small side is the one block that goes to the tasks, and records of the large one are its probes
        turned = swept(p.b._packed, p.a._packed, m, cfg.tau, filters, False, (cfg.tau, 0.0, None))
        return conditions(turned.select(F.col("b_id").alias("a_id"), F.col("a_id").alias("b_id"), "sim"), cfg.tau, cfg.tau_r, cfg.k)
    if hasattr(p.a, "_packed") and hasattr(p.b, "_packed"):
        from .sweep import swept

        best = (cfg.tau, cfg.tau_r, cfg.k)
        # low thresholds leave nearly whole sets as prefixes, whose lists give the similarities themselves
        low = m.bounded and (cfg.tau < WHOLE)
        return conditions(swept(p.a._packed, p.b._packed, m, 0.0 if low else cfg.tau, filters, p.dedup, best), *best)
    kept = lambda side, x: arrays(side, x) if hasattr(side, "_packed") else cut(arrays(side, x), "arrays")
    sets_a = kept(p.a, "a")
    sets_b = sets_a.select(*[F.col(c).alias(c.replace("a_", "b_", 1)) for c in sets_a.columns]) if p.dedup else kept(p.b, "b")
    raised = cfg.k is not None or cfg.tau_r > 0
    levels = [x for x in cfg.levels if x > cfg.tau] if raised else []
    # the state of a probe: its threshold in this round
    scale = F.lit(1.0) if m.bounded else F.col("a_total")
    probes = sets_a.select("a_id", F.greatest(F.lit(cfg.tau), F.lit(levels[0]) * scale if levels else F.lit(cfg.tau)).alias("t"))
    met, done = None, []
    for n in range(len(levels) + 1):
        probe = thresholds(p.a, m, probes.select(F.col("a_id").alias("rec_id"), "t"), filters)
        low = max(cfg.tau, levels[n] if n < len(levels) and m.bounded else 0.0)
        pairs = candidates(pre_candidates(probe, p.b, m, filters, p.dedup, low, not raised), m)
        if low > 0:
            found = verify(pairs.select("a_id", "b_id"), sets_a, sets_b, p.measure)
        elif not raised:
            found = known(pairs, m)
        else:
            pairs = cut(pairs, "candidates")
            found = known(pairs.where("t <= 0"), m).unionByName(verify(pairs.where("t > 0").select("a_id", "b_id"), sets_a, sets_b, p.measure))
        if not levels:
            return conditions(found, cfg.tau, cfg.tau_r, cfg.k)
        seen_now = cut(found.join(probes, "a_id"), "round")
        found = seen_now.where(F.col("sim") >= F.col("t") - 1e-9)
        kept = conditions(found.select("a_id", "b_id", "sim"), cfg.tau, cfg.tau_r, cfg.k)
        if n == len(levels):
            done.append(kept)
            break
        seen = found.groupBy("a_id").agg(F.max("sim").alias("best"), F.count("*").alias("n"))
        enough = F.lit(False) if cfg.k is None else F.coalesce(F.col("n") >= cfg.k, F.lit(False))
        final = enough | (F.coalesce(F.col("best") * cfg.tau_r, F.lit(0.0)) >= F.col("t")) | (F.col("t") <= cfg.tau)
        state = cut(probes.join(seen, "a_id", "left").withColumn("final", final), "probes")
        done.append(kept.join(state.where("final").select("a_id"), "a_id", "left_semi"))
        level = F.lit(cfg.tau) if n + 1 == len(levels) else F.lit(levels[n + 1])
        totals = sets_a.select("a_id", "a_total")
        if cfg.k is not None:
            older = seen_now.select("a_id", "b_id", "sim")
            met = older if met is None else met.unionByName(older)
            open_ = met.join(state.where("not final").select("a_id"), "a_id", "left_semi").groupBy("a_id", "b_id").agg(F.max("sim").alias("sim"))
            best_k = Window.partitionBy("a_id").orderBy(F.desc("sim"))
            kth = open_.withColumn("_n", F.row_number().over(best_k)).where(F.col("_n") == cfg.k).select("a_id", F.col("sim").alias("_kth"))
            state = state.join(kth, "a_id", "left")
        else:
            state = state.withColumn("_kth", F.lit(None).cast("double"))
        nxt = F.greatest(F.coalesce("_kth", F.lit(0.0)), F.lit(cfg.tau), level * (F.lit(1.0) if m.bounded or n + 1 == len(levels) else F.col("a_total")), F.coalesce(F.col("best") * cfg.tau_r, F.lit(0.0)))
        probes = cut(state.where("not final").join(totals, "a_id").select("a_id", nxt.alias("t")), "probes")
        if not probes.limit(1).count():
            break
    out = done[0]
    for more in done[1:]:
        out = out.unionByName(more)
    return out


def hybrid_join(p: Prepared, tau: float = 0.0, tau_r: float = 0.0, k: int | None = None, rho: int | None = None, filters: frozenset | None = None) -> DataFrame:
    """``(a_id, b_id, sim)``; in deduplication unordered distinct pairs."""
    out = directed_join(p, JoinConfig(tau, tau_r, k, rho, filters))
    return unordered(out) if p.dedup else out
