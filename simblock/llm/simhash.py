"""SimHash near-duplicates: fingerprints searched through vantage-point trees.

Distinct fingerprints are dealt to shards by a vantage-point tree over Hamming distance
that is built from a bounded sample: an inner node sends fingerprints within its radius
to one side, the others to the other. A fingerprint of the outer side that is within
``radius + bits`` is also copied to the inner side, since by the triangle inequality
only such can link across the boundary: whichever side the partner is on, the two still
share a side at every node, and so a shard. In a shard, fingerprints are sorted by their distance to
a local vantage point, and only windows that the triangle bound leaves are compared.
A shard yields a spanning forest of its links, and the forests are joined to components.

Defined results: a null or wordless text has fingerprint zero and is linked like any
other; fewer words than a shingle make one shingle of all of them; equal texts and
repeated rows share a fingerprint and hence a component; an empty table gives an empty
result; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.components import connected_components
from ..plans.stages import cut, shuffle_partitions
from .unionfind import Forest

SAMPLE = 131_072  # fingerprints from which the tree is built, about
SHARD = 4_096  # fingerprints at home in a shard, about
BLOCK = 131_072  # fingerprints of a shard that one task holds, about
TILE = 16_384  # fingerprints that 256 others are compared with at once


def fingerprint(text: str | None, width: int = 4, seed: int = 42) -> int:
    """Majority bits over the XXH64 of all word shingles of the text, lower-cased in A-Z."""
    from xxhash import xxh64_intdigest as h

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    if len(words) <= width:
        return h(joined, seed)
    ends = np.cumsum(np.fromiter(map(len, words), dtype=np.int64, count=len(words)) + 1) - 1
    stops = ends[width - 1 :].tolist()
    starts = [0, *(ends[: len(words) - width] + 1).tolist()]
    counts = np.zeros(64, dtype=np.int64)
    for s in range(0, len(stops), 65_536):
        part = np.array([h(joined[a:b], seed) for a, b in zip(starts[s : s + 65_536], stops[s : s + 65_536])], dtype="<u8")
        counts += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(counts * 2 > len(stops), bitorder="little").tobytes(), "little")


def fingerprints(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 4) -> DataFrame:
    """``(_id, _print)``, the fingerprint as a signed long."""

    def scan(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            prints = np.array([fingerprint(t, width) for t in b["_text"]], dtype=np.uint64).view(np.int64)
            yield pd.DataFrame({"_id": b["_id"], "_print": prints})

    picked = df.select(F.col(id_col).alias("_id"), F.coalesce(F.col(text_col), F.lit("")).alias("_text"))
    return picked.mapInPandas(scan, f"_id {dict(df.dtypes)[id_col]}, _print long")


class VantageTree:
    """Inner nodes (vantage point, radius, children); leaves are numbered from 0."""

    def __init__(self, sample: np.ndarray, depth: int, seed: int = 11):
        self.nodes: list[tuple[int, int, int, int]] = []
        self.leaves = 0
        self.rng = np.random.default_rng(seed)
        self.root = self._grow(sample, depth)

    def _grow(self, points: np.ndarray, depth: int) -> int:
        """Index of a node, or ``-1 - leaf``."""
        best = None
        if depth > 0 and len(points) >= 8:
            for v in self.rng.choice(points, size=min(8, len(points)), replace=False):
                d = np.bitwise_count(points ^ v)
                radius = int(np.median(d))
                inner = int((d <= radius).sum())
                if inner == len(points):
                    radius, inner = radius - 1, int((d <= radius - 1).sum())
                if 0 < inner < len(points):
                    copied = int(((d > radius) & (d <= radius + 4)).sum())
                    cost = max(inner + copied, len(points) - inner)
                    if best is None or cost < best[0]:
                        best = (cost, v, radius, d)
        if best is None:
            self.leaves += 1
            return -self.leaves
        _, v, radius, d = best
        at = len(self.nodes)
        self.nodes.append((0, 0, 0, 0))
        self.nodes[at] = (int(v), radius, self._grow(points[d <= radius], depth - 1), self._grow(points[d > radius], depth - 1))
        return at

    def deal(self, points: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
        """(leaf, row) for every shard that a point belongs or is copied to."""
        out = []
        todo = [(self.root, np.arange(len(points)))]
        while todo:
            node, rows = todo.pop()
            if not len(rows):
                continue
            if node < 0:
                out.append((np.full(len(rows), -1 - node), rows))
                continue
            v, radius, inner, outer = self.nodes[node]
            d = np.bitwise_count(points[rows] ^ np.uint64(v))
            todo.append((inner, rows[d <= radius + bits]))
            todo.append((outer, rows[d > radius]))
        if not out:
            empty = np.zeros(0, dtype=np.int64)
            return empty, empty
        return tuple(np.concatenate(x) for x in zip(*out))


def shard_links(points: np.ndarray, bits: int, side: np.ndarray | None = None) -> np.ndarray:
    """Root (a row number) of each row in a spanning forest of the shard's links; with sides given, of those across sides."""
    forest = Forest(len(points))
    away = np.bitwise_count(points ^ points[0]).astype(np.int16)
    order = np.lexsort((points, away))
    points, away = points[order], away[order]
    side = None if side is None else side[order]
    for s in range(0, len(points), 256):
        a = points[s : s + 256]
        high = int(np.searchsorted(away, away[min(s + 255, len(points) - 1)] + bits, side="right"))
        for t in range(s, high, TILE):
            i, j = np.nonzero(np.bitwise_count(a[:, None] ^ points[None, t : min(t + TILE, high)]) <= bits)
            i, j = i + s, j + t
            wanted = i < j if side is None else (i < j) & (side[i] != side[j])
            forest.link(order[i[wanted]], order[j[wanted]])
    return forest.roots()


def near_duplicates(df: DataFrame, bits: int = 4, width: int = 4, id_col: str = "doc_id", text_col: str = "text", shard: int = SHARD, block: int = BLOCK) -> DataFrame:
    """``(id, fingerprint, component_id)`` for every row."""
    prints = cut(fingerprints(df, id_col, text_col, width), "prints")
    distinct = cut(prints.groupBy("_print").agg(F.min("_id").alias("_least")), "distinct")
    total = distinct.count()
    share = int(min(1.0, SAMPLE / max(total, 1)) * (1 << 30)) + 1
    rows = distinct.where(F.pmod(F.xxhash64("_print", F.lit(5)), F.lit(1 << 30)) < share).select("_print").toPandas()  # about SAMPLE rows at most
    sample = np.sort(rows["_print"].to_numpy(dtype=np.int64)).view(np.uint64)
    tree = VantageTree(sample, max(0, math.ceil(math.log2(max(total, 1) / shard))))

    def deal(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            points = b["_print"].to_numpy(dtype=np.int64)
            for s in range(0, len(points), 8192):
                part = points[s : s + 8192]
                leaf, row = tree.deal(part.view(np.uint64), bits)
                yield pd.DataFrame({"_leaf": leaf, "_print": part[row]})

    def search(key: tuple, g: pd.DataFrame) -> pd.DataFrame:
        signed = g["_print"].to_numpy(dtype=np.int64)
        root = shard_links(signed.view(np.uint64), bits, None if key[1] == key[2] else g["_mine"].to_numpy())
        tied = root != np.arange(len(g))
        return pd.DataFrame({"u": signed[tied], "v": signed[root[tied]]})

    spread = distinct.select("_print").repartition(shuffle_partitions(df.sparkSession), "_print")
    dealt = cut(spread.mapInPandas(deal, "_leaf long, _print long"), "dealt")
    sizes = dealt.groupBy("_leaf").count().where(F.col("count") > block)
    wide = cut(sizes.select("_leaf", F.ceil(F.col("count") / block).cast("int").alias("_parts")), "wide")
    parts = F.coalesce("_parts", F.lit(1))
    blocks = dealt.join(F.broadcast(wide), "_leaf", "left")  # at most a row for each of the tree's leaves
    blocks = blocks.withColumn("_mine", F.pmod(F.xxhash64("_print", F.lit(9)), parts.cast("long")).cast("int"))
    blocks = blocks.withColumn("_other", F.explode(F.sequence(F.lit(0), parts - 1)))
    blocks = blocks.select("_leaf", "_print", "_mine", F.least("_mine", "_other").alias("_lo"), F.greatest("_mine", "_other").alias("_hi"))
    edges = blocks.groupBy("_leaf", "_lo", "_hi").applyInPandas(search, "u long, v long")
    roots = connected_components(edges)
    known = distinct.join(roots.withColumnRenamed("node", "_print"), "_print", "left").withColumn("root", F.coalesce("root", "_print"))
    known = cut(known.select("_print", "_least", "root"), "roots")
    least = known.groupBy("root").agg(F.min("_least").alias("_component"))
    component = cut(known.join(least, "root").select("_print", "_component"), "components")
    out = prints.join(component, "_print")
    return out.select(F.col("_id").alias(id_col), F.lower(F.lpad(F.hex("_print"), 16, "0")).alias("fingerprint"), F.col("_component").alias("component_id"))


def keep_one_of_each(df: DataFrame, bits: int = 4, width: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The row of least id of each component, with all its columns; null ids come last, and of equal ids any one row stays.

    Rows are numbered in a table of their own and go by that number, so ids may be null or repeated.
    """
    row = "_simblock_row"
    rows = cut(df.withColumn(row, F.monotonically_increasing_id()), "numbered")
    found = near_duplicates(rows, bits, width, row, text_col).select(row, "component_id").join(rows.select(row, F.col(id_col).alias("_key")), row)
    found = cut(found, "groups")
    first = found.groupBy("component_id").agg(F.min(F.struct(F.col("_key").isNull().alias("last"), "_key", row)).alias("first")).select(F.col(f"first.{row}").alias(row))
    gone = cut(found.select(row).join(first, row, "left_anti"), "gone")
    return rows.join(gone, row, "left_anti").select(*[F.col(f"`{c}`") for c in df.columns])
