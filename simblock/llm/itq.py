"""Embedding near-duplicates: iterative quantisation, multi-index Hamming tables, exact rerank.

Rotations that give balanced sign codes are learned on a bounded sample; every row is
encoded. A code is cut into one substring for each table; rows whose substrings (and
labels) agree in some table meet in a bucket of it. Buckets first hold whole codes only, and a row stays
if some other row of its bucket is within a Hamming distance that pairs at the threshold hardly ever exceed
(``hamming_bound``). Only rows that stay bring their vectors to the bucket, where exact
cosines in double precision decide. A pair is counted only in the first table where
its substrings agree, so nothing is emitted for each pair: a bucket yields rows that stay, then link counts
and a spanning forest, all linear in its size. A bucket over ``block`` rows is cut
into blocks that are compared two at a time, in bounded memory and without leaving out any pair.

Defined results: vectors that are null, empty, zero, or hold null or non-finite
components, and rows without a label, link with nothing and are their own component;
vectors of different lengths never link; equal vectors of one label are one node with
a multiplicity and all link with each other; repeated rows count as separate vectors;
an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BinaryType, LongType, StructField, StructType

from ..plans.components import connected_components
from ..plans.stages import cut
from .unionfind import Forest

FIT_ROWS = 20_000  # bound of the sample on which rotations are learned
MOST_TABLES = 64
LEAST_BITS = 128  # length of a whole code, at least
MISSED = 1e-4  # chance that a pair at the threshold is beyond the Hamming bound


def learn_rotation(sample: np.ndarray, seed: int, rounds: int = 30) -> tuple[np.ndarray, np.ndarray]:
    """(mean, projection): principal axes turned so that signs lose least of the projections."""
    mean = sample.mean(axis=0)
    centred = sample - mean
    _, _, axes = np.linalg.svd(centred.T @ centred)
    projected = centred @ axes.T
    rng = np.random.default_rng(seed)
    turn, _ = np.linalg.qr(rng.standard_normal((projected.shape[1],) * 2))
    for _ in range(rounds):
        signs = np.where(projected @ turn >= 0, 1.0, -1.0)
        u, _, vt = np.linalg.svd(signs.T @ projected)
        turn = vt.T @ u.T
    return mean, axes.T @ turn


def sign_differs(threshold: float, radii: np.ndarray | None) -> np.ndarray:
    """For each distance from the mean: the chance that a sign differs for a pair at the threshold."""
    chord = math.sqrt(max(0.0, 2 - 2 * threshold))
    r = np.ones(1) if radii is None or not len(radii) else np.maximum(np.asarray(radii, dtype=float), 1e-12)
    return 2 * np.arcsin(np.minimum(1.0, chord / (2 * r))) / math.pi


def hamming_bound(length: int, threshold: float, radii: np.ndarray | None = None, missed: float = MISSED) -> int:
    """Least distance of codes of ``length`` bits that pairs at the threshold exceed with a mean chance of ``missed`` at most."""
    p = np.clip(sign_differs(threshold, radii), 1e-12, 1 - 1e-12)
    if len(p) > 512:
        p = np.quantile(p, np.linspace(0, 1, 512))
    k = np.arange(length + 1)
    ways = math.lgamma(length + 1) - np.array([math.lgamma(i + 1) + math.lgamma(length - i + 1) for i in k])
    beyond = 1 - np.exp(ways + k * np.log(p)[:, None] + (length - k) * np.log1p(-p)[:, None]).cumsum(axis=1).mean(axis=0)
    return int(k[np.append(beyond[:-1] <= missed, True)][0])


def table_layout(rows_per_label: float, threshold: float, target_bucket: int = 256, recall: float = 0.999, radii: np.ndarray | None = None) -> tuple[int, int]:
    """(tables, bits a substring): buckets near the target size, and tables enough for the recall.

    A sign of a rotated coordinate differs with a chance of angle/pi. Signs are those of centred
    vectors, so the angle is that of a pair at the threshold as seen from the mean, at the
    distances ``radii`` of vectors from it; the recall is the mean over them. Where that needs over
    ``MOST_TABLES``, substrings get shorter, down to none, where all rows of a label meet.
    """
    same = 1 - sign_differs(threshold, radii)
    for bits in range(min(24, max(6, math.ceil(math.log2(max(rows_per_label, 1) / target_bucket)))), 0, -1):
        for tables in range(1, MOST_TABLES + 1):
            if 1 - ((1 - same**bits) ** tables).mean() >= recall:
                return tables, bits
    return 1, 0


def _signs(vectors: np.ndarray, models: list) -> np.ndarray:
    unit = vectors / np.linalg.norm(vectors, axis=1, keepdims=True)
    return np.concatenate([(unit - m) @ p >= 0 for m, p in models], axis=1)


def _encode(vectors: np.ndarray, models: list, tables: int, bits: int) -> np.ndarray:
    """Substring values, one column for each table."""
    signs = _signs(vectors, models)
    weights = 1 << np.arange(bits, dtype=np.int64)
    return np.stack([signs[:, t * bits : (t + 1) * bits] @ weights for t in range(tables)], axis=1)


def _words(codes: pd.Series) -> np.ndarray:
    """Whole codes as rows of 64-bit words."""
    raw = np.stack([np.frombuffer(c, dtype=np.uint8) for c in codes])
    return np.ascontiguousarray(np.pad(raw, ((0, 0), (0, -raw.shape[1] % 8)))).view(np.uint64)


def have_neighbours(codes: np.ndarray, left: np.ndarray, right: np.ndarray, most: int) -> np.ndarray:
    """Which rows of ``left`` or ``right`` (the same rows, or none in common) have another within ``most`` bits on the other side."""
    out = np.zeros(len(codes), dtype=bool)
    same = left is right
    for s in range(0, len(left), 256):
        a = left[s : s + 256]
        d = np.zeros((len(a), len(right)), dtype=np.uint16)
        for w in range(codes.shape[1]):
            d += np.bitwise_count(codes[a, w][:, None] ^ codes[right, w][None, :])
        near = d <= most
        if same:
            near[np.arange(len(a)), np.arange(s, s + len(a))] = False
        out[a] |= near.any(axis=1)
        out[right] |= near.any(axis=0)
    return out


def _in_blocks(keyed: DataFrame, bucket: list[str], block: int) -> DataFrame:
    """Rows of buckets with the two blocks that meet; a bucket of up to ``block`` rows is one block."""
    wide = keyed.groupBy(*bucket).count().where(F.col("count") > block)
    wide = cut(wide.select(*bucket, F.ceil(F.col("count") / block).cast("int").alias("_parts")), "wide")
    mine = F.pmod(F.xxhash64("_node", "_table"), F.col("_parts").cast("long")).cast("int")
    dealt = keyed.join(wide, bucket, "left").withColumn("_mine", F.coalesce(mine, F.lit(0)))
    dealt = dealt.withColumn("_other", F.explode(F.sequence(F.lit(0), F.coalesce(F.col("_parts"), F.lit(1)) - 1)))
    return dealt.withColumn("_lo", F.least("_mine", "_other")).withColumn("_hi", F.greatest("_mine", "_other")).drop("_parts", "_other")


def _clean(df: DataFrame, id_col: str, vector_col: str, label_col: str) -> DataFrame:
    v = F.col(vector_col)
    bad = F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == F.lit(float("inf"))))
    live = F.aggregate(v, F.lit(0.0), lambda s, x: s + F.abs(x.cast("double"))) > 0
    usable = F.coalesce(F.col(label_col).isNotNull() & v.isNotNull() & ~bad & live, F.lit(False))
    return df.select(F.col(id_col).alias("_id"), F.col(label_col).alias("_label"), v.cast("array<double>").alias("_v"), usable.alias("_ok"))


def near_duplicates(df: DataFrame, threshold: float = 0.98, id_col: str = "vec_id", vector_col: str = "embedding", label_col: str = "label", block: int = 2048, seed: int = 7, layout: tuple[int, int] | None = None) -> DataFrame:
    """``(id, n_links, component_id, kept)`` for every row."""
    rows = _clean(df, id_col, vector_col, label_col).withColumn("_node", F.when(F.col("_ok"), F.xxhash64("_label", "_v")))
    nodes = cut(rows.where("_ok").groupBy("_node").agg(F.first("_label").alias("_label"), F.first("_v").alias("_v"), F.count("*").alias("_n"), F.min("_id").alias("_least")), "vectors")
    # rows that share a row's label, in the mean over rows, so that one large label counts
    total, company = nodes.groupBy("_label").agg(F.count("*").alias("_n")).agg(F.coalesce(F.sum("_n"), F.lit(0)), F.sum(F.col("_n").cast("double") * F.col("_n")) / F.sum("_n")).first()
    part = min(1.0, FIT_ROWS / max(total, 1))
    picked = F.pmod(F.xxhash64(F.col("_node"), F.lit(seed)), F.lit(1 << 20)) < int(part * (1 << 20)) + 1
    sample = nodes.where(picked).select("_v").toPandas()["_v"] if total else []  # about FIT_ROWS rows at most
    by_width: dict[int, list] = {}
    for v in sample:
        by_width.setdefault(len(v), []).append(v)
    units = {}
    for width, vs in by_width.items():
        x = np.asarray(vs, dtype=float)
        units[width] = x / np.linalg.norm(x, axis=1, keepdims=True)
    radii = [np.linalg.norm(x - x.mean(axis=0), axis=1) for x in units.values()]
    every = np.concatenate(radii) if radii else None
    tables, bits = layout or table_layout(company or 0.0, threshold, radii=every)
    rotations = lambda width: max(1, math.ceil(max(tables * bits, LEAST_BITS) / width))
    models = {width: [learn_rotation(x, seed + i) for i in range(rotations(width))] for width, x in units.items()}
    # a width too rare for the sample gets plain random rotations
    def model(width: int) -> list:
        if width not in models:
            models[width] = [(np.zeros(width), np.linalg.qr(np.random.default_rng(seed + i).standard_normal((width, width)))[0]) for i in range(rotations(width))]
        return models[width]

    def encode(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            widths = b["_v"].map(len)
            for width, part in b.groupby(widths):
                x, m = np.stack(part["_v"].to_numpy()), model(int(width))
                yield part.assign(_codes=list(_encode(x, m, tables, bits)), _whole=[c.tobytes() for c in np.packbits(_signs(x, m), axis=1)])

    coded = cut(nodes.mapInPandas(encode, StructType([*nodes.schema.fields, StructField("_codes", ArrayType(LongType())), StructField("_whole", BinaryType())])), "codes") if total else None
    if coded is None:
        return rows.select(F.col("_id").alias(id_col), F.lit(0).cast("long").alias("n_links"), F.col("_id").cast("long").alias("component_id"), F.lit(True).alias("kept"))
    bucket = ["_label", "_w", "_table", "_value"]
    groups = [*bucket, "_lo", "_hi"]
    near = {width: hamming_bound(rotations(width) * width, threshold, r) for width, r in zip(units, radii)}

    def sift(key: tuple, g: pd.DataFrame) -> pd.DataFrame:
        width, lo, hi = int(key[1]), key[4], key[5]
        mine = g["_mine"].to_numpy()
        left = np.flatnonzero(mine == lo)
        right = left if lo == hi else np.flatnonzero(mine == hi)
        if width not in near:
            near[width] = hamming_bound(rotations(width) * width, threshold)
        stays = have_neighbours(_words(g["_whole"]), left, right, near[width])
        return g.loc[stays, ["_node", "_table"]]

    light = coded.select("_node", "_whole", F.size("_v").alias("_w"), "_label", F.posexplode("_codes").alias("_table", "_value"))
    stay = _in_blocks(light, bucket, block).groupBy(*groups).applyInPandas(sift, "_node long, _table int").dropDuplicates()
    value = F.element_at("_codes", F.col("_table") + 1)
    keyed = coded.join(stay, "_node").select("_node", "_n", "_v", "_codes", F.size("_v").alias("_w"), "_label", "_table", value.alias("_value"))
    dealt = _in_blocks(cut(keyed, "candidates"), bucket, block)

    def compare(key: tuple, g: pd.DataFrame) -> pd.DataFrame:
        table, lo, hi = int(key[2]), key[4], key[5]
        x = np.stack(g["_v"].to_numpy()).astype(float)
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        codes, mult, mine = np.stack(g["_codes"].to_numpy()), g["_n"].to_numpy(), g["_mine"].to_numpy()
        node, forest = g["_node"].to_numpy(), Forest(len(g))
        gained = np.zeros(len(g), dtype=np.int64)
        left = np.flatnonzero(mine == lo)
        right = left if lo == hi else np.flatnonzero(mine == hi)
        for s in range(0, len(left), 256):
            a = left[s : s + 256]
            hit = x[a] @ x[right].T >= threshold
            i, j = np.nonzero(hit)
            i, j = a[i], right[j]
            keep = i < j if lo == hi else np.ones(len(i), dtype=bool)
            for t in range(table):
                keep &= codes[i, t] != codes[j, t]
            i, j = i[keep], j[keep]
            np.add.at(gained, i, mult[j])
            np.add.at(gained, j, mult[i])
            forest.link(i, j)
        roots = forest.roots()
        tied = (roots != np.arange(len(g))) | (gained > 0)
        return pd.DataFrame({"_node": node[tied], "_root": node[roots[tied]], "_gained": gained[tied]})

    found = cut(dealt.groupBy(*groups).applyInPandas(compare, "_node long, _root long, _gained long"), "links")
    gained = found.groupBy("_node").agg(F.sum("_gained").alias("_gained"))
    roots = connected_components(found.select(F.col("_node").alias("u"), F.col("_root").alias("v")))
    known = nodes.select("_node", "_n", "_least").join(gained, "_node", "left").join(roots.withColumnRenamed("node", "_node"), "_node", "left").withColumn("root", F.coalesce("root", "_node"))
    least = known.groupBy("root").agg(F.min("_least").alias("_component"))
    known = cut(known.join(least, "root").select("_node", (F.col("_n") - 1 + F.coalesce("_gained", F.lit(0))).alias("_links"), "_component"), "known")
    out = rows.select("_id", "_node").join(known, "_node", "left")
    component = F.coalesce("_component", "_id").cast("long")
    return out.select(F.col("_id").alias(id_col), F.coalesce("_links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), (component == F.col("_id")).alias("kept"))
