"""Byte-level BPE: a minimal perfect hash for whole pre-tokens, a heap of merges for the rest.

A text is split by the public pattern. A pre-token that is a vocabulary entry is found
through a minimal perfect hash over the vocabulary's byte strings (and compared with the
entry in full); any other is merged by rank with a heap over a linked list of its
bytes, so a pre-token of n bytes takes O(n log n) however long it is. Results of
pre-tokens are kept in a cache of the worker, bounded by their number and their bytes.

Defined results: a null or empty text has no ids and decodes to no bytes; repeated rows
are encoded one by one; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import base64
from collections.abc import Iterator
from heapq import heapify, heappop, heappush

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .wordtokens import IdTable

CACHE = 400_000  # pre-tokens in a worker's cache
CACHE_BYTES = 64 << 20  # bytes of the cached pre-tokens
_codecs: dict[tuple[str, str], "ByteBpe"] = {}


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


class PerfectHash:
    """Hash-and-displace: buckets choose a displacement that sends their keys to free slots.

    As many slots as keys; a bucket of one key names its slot outright.
    """

    def __init__(self, keys: list[bytes]):
        from xxhash import xxh3_64_intdigest

        self.digest = xxh3_64_intdigest
        self.n = max(1, len(keys))
        self.buckets = max(1, self.n // 4)
        hashes = self.hashes(keys)
        self.shift = np.zeros(self.buckets, dtype=np.int64)
        self.slot_of = np.full(self.n, -1, dtype=np.int64)  # slot -> key number
        bucket = (hashes % np.uint64(self.buckets)).astype(np.int64)
        order = np.argsort(bucket, kind="stable")
        bounds = np.searchsorted(bucket[order], np.arange(self.buckets + 1))
        sizes = np.diff(bounds)
        free = np.ones(self.n, dtype=bool)
        single = []
        for b in np.argsort(-sizes, kind="stable").tolist():
            rows = order[bounds[b] : bounds[b + 1]]
            if len(rows) == 0:
                break
            if len(rows) == 1:
                single.append((b, int(rows[0])))
                continue
            tries = np.arange(1, 257, dtype=np.uint64)
            while True:
                slots = self._slots(hashes[rows][:, None], tries[None, :])
                good = free[slots].all(axis=0)
                for c in np.flatnonzero(good).tolist():
                    if len(set(slots[:, c].tolist())) == len(rows):
                        self.shift[b] = int(tries[c])
                        free[slots[:, c]] = False
                        self.slot_of[slots[:, c]] = rows
                        break
                else:
                    tries += np.uint64(256)
                    continue
                break
        for (b, row), slot in zip(single, np.flatnonzero(free).tolist()):
            self.shift[b] = -1 - slot
            self.slot_of[slot] = row

    def hashes(self, keys: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.digest, keys), dtype=np.uint64, count=len(keys))

    def _slots(self, h: np.ndarray, shift: np.ndarray) -> np.ndarray:
        x = (h ^ (shift * np.uint64(0x9E3779B97F4A7C15))) * np.uint64(0xBF58476D1CE4E5B9)
        return ((x ^ (x >> np.uint64(31))) % np.uint64(self.n)).astype(np.int64)

    def lookup(self, keys: list[bytes]) -> np.ndarray:
        """The only key number that each string could have."""
        h = self.hashes(keys)
        shift = self.shift[(h % np.uint64(self.buckets)).astype(np.int64)]
        slots = np.where(shift < 0, -1 - shift, self._slots(h, np.maximum(shift, 0).astype(np.uint64)))
        return self.slot_of[slots]


class ByteBpe:
    def __init__(self, path: str, pattern: str):
        import regex

        self.split = regex.compile(pattern).findall
        ranks = read_ranks(path)
        self.keys = list(ranks)
        self.ids = np.fromiter(ranks.values(), dtype=np.int64, count=len(ranks))
        self.hash = PerfectHash(self.keys)
        self.ranks = ranks
        self.byte_id = [ranks[bytes([i])] for i in range(256)]
        top = int(self.ids.max()) + 1
        self.by_id = [b""] * top
        for k, i in ranks.items():
            self.by_id[i] = k
        self.bytes_of = self._strings(self.by_id)
        self.decimal_of = self._strings([b"%d," % i for i in range(top)])
        self.reset()

    @staticmethod
    def _strings(rows: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        length = np.fromiter(map(len, rows), dtype=np.int64, count=len(rows))
        return np.frombuffer(b"".join(rows), dtype=np.uint8), np.cumsum(length) - length, length

    @staticmethod
    def _gather(table: tuple[np.ndarray, np.ndarray, np.ndarray], ids: np.ndarray) -> bytes:
        flat, start, lengths = table
        out = []
        for s in range(0, len(ids), 200_000):
            part = ids[s : s + 200_000]
            length = lengths[part]
            ends = np.cumsum(length)
            out.append(flat[np.arange(int(ends[-1])) + np.repeat(start[part] - (ends - length), length)].tobytes())
        return b"".join(out)

    def reset(self) -> None:
        self.known: dict[str, int] = {}
        self.table = IdTable()
        self.held = 0

    def merge(self, word: bytes) -> list[int]:
        """Ids of a pre-token outside the vocabulary."""
        ranks, n = self.ranks, len(word)
        stop = list(range(1, n + 1))  # end of the part that starts here; 0: merged away
        before = list(range(-1, n - 1))
        heap = []
        for i in range(n - 1):
            r = ranks.get(word[i : i + 2])
            if r is not None:
                heap.append((r, i, i + 2))
        heapify(heap)
        while heap:
            _, i, end = heappop(heap)
            mid = stop[i]
            if not mid or mid >= end or stop[mid] != end:
                continue  # one of the two parts has changed since
            stop[i], stop[mid] = end, 0
            if end < n:
                before[end] = i
                r = ranks.get(word[i : stop[end]])
                if r is not None:
                    heappush(heap, (r, i, stop[end]))
            p = before[i]
            if p >= 0:
                r = ranks.get(word[p:end])
                if r is not None:
                    heappush(heap, (r, p, end))
        out, i = [], 0
        while i < n:
            out.append(ranks[word[i : stop[i]]])
            i = stop[i]
        return out

    def learn(self, tokens: list[str]) -> None:
        new = list(dict.fromkeys(t for t in tokens if t not in self.known))
        raw = [t.encode("utf-8", "surrogatepass") for t in new]
        row = self.hash.lookup(raw)
        keys, ids = self.keys, self.ids
        found = [(ids[r],) if r >= 0 and keys[r] == w else self.merge(w) for r, w in zip(row.tolist(), raw)]
        self.known.update(zip(new, range(self.table.rows, self.table.rows + len(new))))
        self.table.extend(found)
        self.held += sum(map(len, raw))

    def encode(self, text: str | None) -> np.ndarray:
        if not text:
            return np.zeros(0, dtype=np.int32)
        tokens = self.split(text)
        rows = list(map(self.known.get, tokens))
        if None in rows:
            if len(self.known) > CACHE:
                self.reset()
            self.learn(tokens)
            rows = list(map(self.known.get, tokens))
        ids = self.table.take(np.asarray(rows, dtype=np.int64))
        if self.held > CACHE_BYTES:  # long unbroken pre-tokens are not kept beyond their text
            self.reset()
        return ids

    def decode(self, ids: np.ndarray) -> bytes:
        return self._gather(self.bytes_of, np.asarray(ids, dtype=np.int64)) if len(ids) else b""

    def decimals(self, ids: np.ndarray) -> bytes:
        """The ids in decimal, joined by commas."""
        return self._gather(self.decimal_of, np.asarray(ids, dtype=np.int64))[:-1] if len(ids) else b""


def codec(path: str, pattern: str) -> ByteBpe:
    if (path, pattern) not in _codecs:
        _codecs[path, pattern] = ByteBpe(path, pattern)
    return _codecs[path, pattern]


def encode(df: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(id, ids array<int>)`` for every row."""

    def scan(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        bpe = codec(path, pattern)
        for b in batches:
            yield pd.DataFrame({id_col: b["_id"], "ids": [bpe.encode(t) for t in b["_text"]]})

    picked = df.select(F.col(id_col).alias("_id"), F.coalesce(F.col(text_col), F.lit("")).alias("_text"))
    return picked.mapInPandas(scan, f"`{id_col}` {dict(df.dtypes)[id_col]}, ids array<int>")


def decode(df: DataFrame, path: str, pattern: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """``(id, decoded binary)`` for every row of ids."""

    def scan(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        bpe = codec(path, pattern)
        for b in batches:
            yield pd.DataFrame({id_col: b["_id"], "decoded": [bpe.decode(np.asarray([] if i is None else i, dtype=np.int64)) for i in b["_ids"]]})

    picked = df.select(F.col(id_col).alias("_id"), F.col(ids_col).alias("_ids"))
    return picked.mapInPandas(scan, f"`{id_col}` {dict(df.dtypes)[id_col]}, decoded binary")


def round_trip(df: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(id, n_tokens, ids_sha256, decoded_sha256)``: both ways in one pass, digests only."""

    def scan(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from hashlib import sha256

        bpe = codec(path, pattern)
        for b in batches:
            out = []
            for t in b["_text"]:
                ids = bpe.encode(t)
                out.append((len(ids), sha256(bpe.decimals(ids)).hexdigest(), sha256(bpe.decode(ids)).hexdigest()))
            n, a, d = zip(*out) if out else ((), (), ())
            yield pd.DataFrame({id_col: b["_id"], "n_tokens": n, "ids_sha256": a, "decoded_sha256": d})

    picked = df.select(F.col(id_col).alias("_id"), F.coalesce(F.col(text_col), F.lit("")).alias("_text"))
    return picked.mapInPandas(scan, f"`{id_col}` {dict(df.dtypes)[id_col]}, n_tokens long, ids_sha256 string, decoded_sha256 string")
