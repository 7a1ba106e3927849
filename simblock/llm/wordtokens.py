"""Encoding by the ``tokenizers`` library through a cache of white-space separated chunks.

Text is split at ASCII white space and before some punctuation. The tokenizers that drop white space and split
at it encode each chunk on its own, so a document's ids are those of its chunks in
turn; the caller must use this for such tokenizers only (a test compares it with whole-text
encoding).
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from itertools import chain

import numpy as np

CACHE = 500_000  # chunks in a worker's cache
CACHE_BYTES = 64 << 20  # bytes of the cached chunks
BLOCK = 300_000  # chunks that are looked up together
STOP = re.compile(rb"[.,](?<=[a-z0-9].)(?=[ \t-\r]|$)")
_encoders: dict[str, "ChunkEncoder"] = {}


class IdTable:
    """Growing rows of ids in flat arrays."""

    def __init__(self):
        self.flat, self.start, self.length = np.zeros(1024, dtype=np.int32), np.zeros(1024, dtype=np.int64), np.zeros(1024, dtype=np.int64)
        self.rows = self.used = 0

    def extend(self, lists: list) -> None:
        lengths = np.fromiter(map(len, lists), dtype=np.int64, count=len(lists))
        self.add(np.fromiter(chain.from_iterable(lists), dtype=np.int32, count=int(lengths.sum())), lengths)

    def add(self, ids: np.ndarray, lengths: np.ndarray) -> None:
        """Rows of the given lengths whose ids follow each other."""
        total = len(ids)
        while self.rows + len(lengths) > len(self.start):
            self.start, self.length = np.resize(self.start, 2 * len(self.start)), np.resize(self.length, 2 * len(self.length))
        while self.used + total > len(self.flat):
            self.flat = np.resize(self.flat, 2 * len(self.flat))
        at = slice(self.rows, self.rows + len(lengths))
        self.length[at] = lengths
        self.start[at] = self.used + np.cumsum(lengths) - lengths
        self.flat[self.used : self.used + total] = ids
        self.rows, self.used = self.rows + len(lengths), self.used + total

    def take(self, rows: np.ndarray) -> np.ndarray:
        length = self.length[rows]
        ends = np.cumsum(length)
        total = int(ends[-1]) if len(ends) else 0
        return self.flat[np.arange(total) + np.repeat(self.start[rows] - (ends - length), length)]


class ChunkEncoder:
    def __init__(self, path: str):
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # tasks are the parallelism here
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        vocabulary = self.tokenizer.get_vocab()
        self.ends_word = np.zeros(max(vocabulary.values()) + 1, dtype=bool)
        self.ends_word[[i for t, i in vocabulary.items() if t.endswith("</w>")]] = True
        self.reset()

    def reset(self) -> None:
        self.known: dict[bytes, int] = {}
        self.table = IdTable()
        self.held = 0

    def learn(self, new: list[bytes]) -> None:
        """Encode chunks. Those of letters only are one pre-token each, so many are encoded as
        one text and told apart by the tokens that end a word."""
        texts = [c.decode("utf-8", "surrogatepass") for c in new]
        plain = [t for t in texts if t.isalpha()]
        other = [t for t in texts if not t.isalpha()]
        for s in range(0, len(plain), 20_000):
            part = plain[s : s + 20_000]
            lines = [" ".join(part[i : i + 200]) for i in range(0, len(part), 200)]
            ids = np.fromiter(chain.from_iterable(e.ids for e in self.tokenizer.encode_batch_fast(lines, add_special_tokens=False)), dtype=np.int32)
            ends = np.flatnonzero(self.ends_word[ids])
            if len(ends) == len(part):
                self.put(part, ids, np.diff(ends, prepend=-1))
            else:  # a letter that the tokenizer doesn't take for one
                other += part
        for s in range(0, len(other), 20_000):
            part = other[s : s + 20_000]
            found = [e.ids for e in self.tokenizer.encode_batch_fast(part, add_special_tokens=False)]
            lengths = np.fromiter(map(len, found), dtype=np.int64, count=len(found))
            self.put(part, np.fromiter(chain.from_iterable(found), dtype=np.int32, count=int(lengths.sum())), lengths)

    def put(self, part: list[str], ids: np.ndarray, lengths: np.ndarray) -> None:
        keys = [t.encode("utf-8", "surrogatepass") for t in part]
        self.known.update(zip(keys, range(self.table.rows, self.table.rows + len(keys))))
        self.table.add(ids, lengths)
        self.held += sum(map(len, keys))

    def documents(self, texts: list[str], end_id: int | None) -> Iterator[np.ndarray]:
        """The ids of each text, with the end id behind them if one is given."""
        tail = np.array([] if end_id is None else [end_id], dtype=np.int32)
        block: list[list[bytes]] = []
        held = 0
        for n, text in enumerate(texts):
            # bytes are lowered in A-Z and split at ASCII blanks only; a full stop or comma
            # between a letter or digit and a blank is a chunk of its own
            raw = STOP.sub(rb" \g<0>", text.encode("utf-8", "surrogatepass").lower())
            block.append(raw.split())
            held += len(block[-1])
            if held >= BLOCK or n + 1 == len(texts):
                yield from (np.concatenate([ids, tail]) for ids in self._block(block))
                block, held = [], 0

    def _block(self, block: list[list[bytes]]) -> Iterator[np.ndarray]:
        """Ids of a few documents' chunks, looked up together."""
        chunks = list(chain.from_iterable(block))
        local = dict.fromkeys(chunks)  # small enough for the processor's caches
        get = self.known.get
        at = list(map(get, local))
        if None in at:
            new = [c for c, r in zip(local, at) if r is None]
            if len(self.known) > CACHE:
                self.reset()
                new, get = list(local), self.known.get
            self.learn(new)
            at = list(map(get, local))
        local = dict(zip(local, at))
        rows = np.fromiter(map(local.__getitem__, chunks), dtype=np.int64, count=len(chunks))
        ids = self.table.take(rows)
        ends = np.concatenate([[0], np.cumsum(self.table.length[rows])])
        at = np.cumsum([0, *map(len, block)])
        for a, b in zip(at[:-1].tolist(), at[1:].tolist()):
            yield ids[ends[a] : ends[b]]
        if self.held > CACHE_BYTES:  # long unbroken chunks are not kept beyond their block
            self.reset()


def encoder(path: str) -> ChunkEncoder:
    if path not in _encoders:
        _encoders[path] = ChunkEncoder(path)
    return _encoders[path]
