"""Best-fit-decreasing packing of token sequences.

A document's ids are cut into full windows; what is left over is packed by best fit
decreasing: a segment tree over remaining capacities finds the tightest open window in
logarithmic time. Leftovers are dealt to groups of bounded size by a hash, each packed
in one task, so memory does not grow with the input; within a group windows are filled
as by one global run, and groups are large enough that their last windows do not matter.

Defined results: a null text is an empty one and gives just the end id; rows that
repeat are packed one by one; an empty table gives no pieces; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.ordering import running_totals
from ..plans.stages import cut
from .wordtokens import encoder

GROUP = 20_000  # leftovers that one task packs


class OpenWindows:
    """Segment tree over capacities: leaf c is set while some open window has c left."""

    def __init__(self, size: int):
        self.leaves = 1 << size.bit_length()
        self.live = bytearray(2 * self.leaves)
        self.at: list[list[int]] = [[] for _ in range(size + 1)]

    def add(self, left: int, window: int) -> None:
        self.at[left].append(window)
        i = left + self.leaves
        while i and not self.live[i]:
            self.live[i] = 1
            i >>= 1

    def tightest(self, need: int) -> tuple[int, int] | None:
        """Take out the window with the least capacity of at least ``need``."""
        live, i = self.live, need + self.leaves
        if not live[i]:
            while i > 1 and not (i % 2 == 0 and live[i + 1]):
                i >>= 1
            if i <= 1:
                return None
            i += 1
            while i < self.leaves:
                i = 2 * i if live[2 * i] else 2 * i + 1
        left = i - self.leaves
        window = self.at[left].pop()
        if not self.at[left]:
            live[i] = 0
            while i > 1 and not live[i ^ 1]:
                i >>= 1
                live[i] = 0
        return left, window


def best_fit_decreasing(lengths: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """(window, offset) of each length; every length is from 1 to ``size``."""
    order = np.argsort(-lengths, kind="stable")
    window, offset = np.zeros(len(lengths), dtype=np.int64), np.zeros(len(lengths), dtype=np.int64)
    open_, opened = OpenWindows(size), 0
    for i, need in zip(order.tolist(), lengths[order].tolist()):
        found = open_.tightest(need)
        left, w = found or (size, opened)
        opened += found is None
        window[i], offset[i] = w, size - left
        if left > need:
            open_.add(left - need, w)
    return window, offset


def token_pieces(df: DataFrame, size: int, tokenizer: str, end_id: int, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """Cut each document into full windows and a leftover: one row a piece.

    ``with_ids`` adds the piece's ids as an array.
    """
    schema = f"_id {dict(df.dtypes)[id_col]}, start long, length long, ids_crc32 long, doc_tokens long" + (", ids array<int>" if with_ids else "")

    def pieces(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        import zlib

        encode = encoder(tokenizer)
        for b in batches:
            out: dict[str, list] = {k: [] for k in ("_id", "start", "length", "ids_crc32", "doc_tokens", "ids")}
            for key, ids in zip(b["_id"], encode.documents(b["_text"].tolist(), end_id)):
                for s in range(0, len(ids), size):
                    part = ids[s : s + size]
                    for k, v in zip(out, (key, s, len(part), zlib.crc32(part.astype("<u4").tobytes()), len(ids), part)):
                        out[k].append(v)
            if not with_ids:
                del out["ids"]
            yield pd.DataFrame(out)

    picked = df.select(F.col(id_col).alias("_id"), F.coalesce(F.col(text_col), F.lit("")).alias("_text"))
    return picked.mapInPandas(pieces, schema)


def pack(pieces: DataFrame, size: int, group: int = GROUP) -> DataFrame:
    """Add ``sequence_id`` and ``offset``: full pieces get windows of their own."""
    held = cut(pieces, "pieces")
    total = held.where(F.col("length") < size).count()
    groups = max(1, -(-total // group))
    kept = [c for c in held.columns if c != "_group"]

    def fill(key: tuple, g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values(["length", "_id", "start", "ids_crc32"], ascending=[False, True, True, True], kind="stable")
        window, offset = best_fit_decreasing(g["length"].to_numpy(), size)
        return g[kept].assign(_group=key[0], _window=window, offset=offset)

    loose = held.where(F.col("length") < size).withColumn("_group", F.pmod(F.xxhash64("_id", "start", "ids_crc32", F.monotonically_increasing_id()), F.lit(groups)))
    schema = held.schema.add("_group", "long").add("_window", "long").add("offset", "long")
    filled = cut(loose.groupBy("_group").applyInPandas(fill, schema), "filled")
    per = filled.groupBy("_group").agg((F.max("_window") + 1).alias("_windows"))  # one row a group
    bases = running_totals(per, ["_group"], {"_base": "_windows"}, label="bases")
    used = per.agg(F.coalesce(F.sum("_windows"), F.lit(0))).first()[0]
    loose = filled.join(bases.select("_group", "_base"), "_group").withColumn("sequence_id", F.col("_base") + F.col("_window"))
    full = held.where(F.col("length") >= size).withColumn("_one", F.lit(1).cast("long"))
    full = running_totals(full, ["_id", "start", "ids_crc32"], {"_pos": "_one"}, label="full")
    full = full.withColumn("sequence_id", F.col("_pos") + F.lit(used)).withColumn("offset", F.lit(0).cast("long"))
    order = [*kept, "sequence_id", "offset"]
    return loose.select(*order).unionByName(full.select(*order))
