"""Quality rules by compression bands, beside plain counts over words, lines and symbols.

A text's zstandard ratio (bytes before over bytes after) is compared with a band chosen
by its length, since short texts compress little whatever they hold. Fixed chunks of a
long text are compared with a band of their own; a text is rejected when its whole
ratio is outside its band (above: repetitive; below: incompressible), or when more
than ``chunk_share`` of its chunks are.

Defined results: a null or empty text has no words and so fails the base rule; texts
below the shortest band are never rejected by compression; repeated rows are judged one
by one; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Bands:
    """(bytes from which the band holds, least ratio, largest ratio), by rising length."""

    # the lower limits lie between noise as text (base64, random characters: 1.40 at most) and prose (1.65 at least from 1 KB on)
    whole: tuple[tuple[int, float, float], ...] = ((256, 1.25, 3.0), (1024, 1.45, 3.5), (4096, 1.55, 4.5), (16384, 1.75, 6.0))
    chunk: tuple[float, float] = (1.4, 4.0)
    chunk_bytes: int = 2048
    chunk_least: int = 512
    chunk_share: float = 0.5
    level: int = 3


SYMBOLS = "#*$%&|<>"
BLANKS = " \t\n\v\f\r"


def repeated_words(words: list[bytes]) -> int:
    """Words that lie in some three-word window which the text has twice or more."""
    if len(words) < 4:
        return 0
    seen: dict[bytes, int] = {}
    w = np.fromiter((seen.setdefault(x, len(seen)) for x in words), dtype=np.int64, count=len(words))
    if len(seen) < 2_000_000:
        keys = (w[:-2] * len(seen) + w[1:-1]) * len(seen) + w[2:]
    else:
        pair = np.unique(w[:-1] * len(seen) + w[1:], return_inverse=True)[1]
        keys = pair[:-1] * len(seen) + w[2:]
    order = np.argsort(keys, kind="stable")
    same = keys[order][1:] == keys[order][:-1]
    if not same.any():
        return 0
    often = np.zeros(len(keys), dtype=bool)
    often[order[1:][same]] = True
    often[order[:-1][same]] = True
    inside = np.zeros(len(words), dtype=bool)
    for k in range(3):
        inside[k : k + len(keys)] |= often
    return int(inside.sum())


def base_counts(text: str) -> tuple[int, int, int, int, int]:
    """Words, code points in words, symbols, lines that repeat, words in repeated windows."""
    words = text.encode("utf-8", "surrogatepass").split()
    seen: set[str] = set()
    repeats = 0
    for line in text.split("\n"):
        if line.strip(BLANKS):
            if line in seen:
                repeats += 1
            else:
                seen.add(line)
    return (len(words), len(text) - sum(map(text.count, BLANKS)), sum(map(text.count, SYMBOLS)), repeats, repeated_words(words))


def ratios(raw: bytes, bands: Bands, compress) -> tuple[float, float, float, float]:
    """Whole ratio, least and largest chunk ratio, share of chunks outside the chunk band."""
    if not raw:
        return 1.0, 1.0, 1.0, 0.0
    whole = len(raw) / len(compress(raw))
    parts = [raw[s : s + bands.chunk_bytes] for s in range(0, len(raw), bands.chunk_bytes)]
    found = [len(p) / len(compress(p)) for p in parts if len(p) >= bands.chunk_least]
    if not found:
        return whole, whole, whole, 0.0
    low, high = bands.chunk
    return whole, min(found), max(found), sum(not low <= r <= high for r in found) / len(found)


def outside(size: int, whole: float, share: float, bands: Bands) -> bool:
    limits = [b for b in bands.whole if size >= b[0]]
    if not limits:
        return False
    _, low, high = limits[-1]
    return not low <= whole <= high or share > bands.chunk_share


def judge(df: DataFrame, bands: Bands = Bands(), min_words: int = 50, repeat_percent: int = 50, id_col: str = "doc_id", text_col: str = "text", keep: list[str] = ()) -> DataFrame:
    """Counts, ratios and the verdict for every row; ``keep`` names columns to carry along under ``in_<name>``."""
    types = dict(df.dtypes)
    carried = ["_id", *[f"in_{c}" for c in keep]]
    head = f"_id {types[id_col]}" + "".join(f", `in_{c}` {types[c]}" for c in keep)

    def scan(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from zstandard import ZstdCompressor

        compress = ZstdCompressor(level=bands.level).compress
        for b in batches:
            rows = []
            for text in b["_text"]:
                counts = base_counts(text)
                raw = text.encode("utf-8", "surrogatepass")
                found = ratios(raw, bands, compress)
                failed = counts[0] < min_words or 100 * counts[4] > repeat_percent * counts[0]
                rows.append((*counts, *found, failed, not failed and not outside(len(raw), found[0], found[3], bands)))
            names = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "ratio", "chunk_low", "chunk_high", "chunk_outside", "base_failed", "kept"]
            out = pd.DataFrame(rows, columns=names)
            yield pd.concat([b[carried].reset_index(drop=True), out], axis=1)

    schema = head + ", n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, ratio double, chunk_low double, chunk_high double, chunk_outside double, base_failed boolean, kept boolean"
    picked = df.select(F.col(id_col).alias("_id"), *[F.col(c).alias(f"in_{c}") for c in keep], F.coalesce(F.col(text_col), F.lit("")).alias("_text"))
    return picked.mapInPandas(scan, schema)


def keep_good(df: DataFrame, bands: Bands = Bands(), min_words: int = 50, repeat_percent: int = 50, text_col: str = "text") -> DataFrame:
    """The rows that pass, with all their columns and no shuffle."""
    at = df.columns.index(text_col)

    def scan(batches):
        import pyarrow as pa
        from zstandard import ZstdCompressor

        compress = ZstdCompressor(level=bands.level).compress
        for b in batches:
            stays = []
            for text in b.column(at).to_pylist():
                text = text or ""
                counts = base_counts(text)
                good = counts[0] >= min_words and 100 * counts[4] <= repeat_percent * counts[0]
                if good:
                    raw = text.encode("utf-8", "surrogatepass")
                    whole, _, _, share = ratios(raw, bands, compress)
                    good = not outside(len(raw), whole, share, bands)
                stays.append(good)
            yield b.filter(pa.array(stays, type=pa.bool_()))

    return df.mapInArrow(scan, df.schema)
