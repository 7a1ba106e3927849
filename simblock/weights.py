"""Token order, weights and weighted token sets.

A prepared collection is a frame ``(rec_id, key, w, pos, pre, suf, total)``: one row for
each token of a record in the global order (rare tokens first), with its weight, the
summed weight (weights squared for the cosine) of the record's earlier tokens, of itself and
all later ones, and of the whole record.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .plans.stages import cut
from .tokens import GRAMS, token_lists

TOKENS = 1 << 20  # tokens of a batch that are worked on at once
TABLE = 1 << 25  # possible n-grams of a batch's characters up to which they are numbered by a table
VOCABULARY = 5_000_000  # tokens in two records or more, up to which their dictionary is sent to every executor


def dictionary(terms: DataFrame, least: int = 1) -> DataFrame:
    """``(token, df, key)`` of tokens in ``least`` records or more, keys rising by (df, token); materialised, as keys must not be redrawn."""
    return ordered(terms.groupBy("token").agg(F.count("*").alias("df")).where(F.col("df") >= least))


def ordered(counts: DataFrame) -> DataFrame:
    return cut(counts.orderBy("df", "token").withColumn("key", F.monotonically_increasing_id()), "dictionary")


def sliced(batch: pa.RecordBatch, column: str, chars: bool = False) -> Iterator[pa.RecordBatch]:
    """Parts of a batch whose lists hold about ``TOKENS`` entries, or bytes with ``chars``, a row at least."""
    ends = batch.column(column).offsets.to_numpy()
    if chars:
        texts = batch.column(column).values
        ends = np.frombuffer(texts.buffers()[1], np.int32)[texts.offset :][ends] if len(texts) else ends
    row = 0
    while row < len(batch):
        end = max(row + 1, int(np.searchsorted(ends, ends[row] + TOKENS, side="right")) - 1)
        yield batch.slice(row, end - row)
        row = end


def grams(texts: pa.Array, n: int) -> tuple[pa.Array, np.ndarray, np.ndarray]:
    """``(tokens, codes, many)``: the different n-grams of texts, those of all texts one after another, and their number by text.

    A text of fewer than n (at most 3) code points gives itself; an empty one gives none.
    """
    chars = np.frombuffer("".join(texts.to_pylist()).encode("utf-32-le", "surrogatepass"), np.uint32)
    size = pc.utf8_length(texts).to_numpy(zero_copy_only=False).astype(np.int64)
    many = np.where(size == 0, 0, np.maximum(size - n + 1, 1))
    first = np.arange(many.sum()) + np.repeat(np.cumsum(size) - size - (np.cumsum(many) - many), many)
    alphabet = np.flatnonzero(np.bincount(chars))
    place = np.zeros(int(alphabet[-1]) + 1 if len(alphabet) else 1, np.int64)
    place[alphabet] = np.arange(len(alphabet)) + 1
    digits, base, code = np.append(place[chars], np.zeros(n, np.int64)), len(alphabet) + 1, np.zeros(len(first), np.int64)
    short = np.flatnonzero(size < n)
    short = short[size[short] > 0]
    at = (np.cumsum(many) - many)[short]
    for i in range(n):
        digit = digits[first + i]
        digit[at[size[short] <= i]] = 0  # behind the end of a short text
        code = code * base + digit
    if base**n <= TABLE:
        seen = np.zeros(base**n, bool)
        seen[code] = True
        found = np.flatnonzero(seen)
        rank = np.empty(len(seen), np.int32)
        rank[found] = np.arange(len(found))
        codes = rank[code].astype(np.int64)
    else:
        found, codes = np.unique(code, return_inverse=True)
    parts = np.stack([found // base ** (n - 1 - i) % base for i in range(n)], axis=1)
    flat = np.append(0, alphabet)[parts].astype("<u4").tobytes().decode("utf-32-le", "surrogatepass")
    tokens = [flat[n * i : n * i + m] for i, m in enumerate((parts > 0).sum(axis=1).tolist())]
    return pa.array(tokens, pa.string()), codes, many


def term_sets(batches, n: int | None) -> Iterator[tuple]:
    """``(ids, tokens, ends, codes, tfs)`` of parts of batches ``(rec_id, t)``: the different tokens of each record, as numbers of ``tokens``.

    ``t`` holds tokens, or texts to be cut into n-grams. Records without a token are left out here, as Spark would
    split each text once more to leave them out.
    """
    for whole in batches:
        for batch in sliced(whole, "t", n is not None):
            t = batch.column("t")
            if n is None:
                coded = t.flatten().dictionary_encode()
                tokens, codes, many = coded.dictionary, coded.indices.to_numpy(zero_copy_only=False).astype(np.int64), np.diff(t.offsets.to_numpy())
            else:
                tokens, codes, each = grams(t.flatten(), n)
                ends = t.offsets.to_numpy()
                many = np.diff(np.concatenate([[0], np.cumsum(each)])[ends - ends[0]])
            some = np.flatnonzero(many)
            if not len(some):
                continue
            both, tf = np.unique(np.repeat(np.arange(len(some)), many[some]) * len(tokens) + codes, return_counts=True)
            yield batch.column("rec_id").take(pa.array(some)), tokens, np.searchsorted(both, np.arange(len(some) + 1) * len(tokens)), both % len(tokens), tf


def counted(lists: DataFrame, n: int | None = None) -> DataFrame:
    """``(rec_id, tokens, tfs)``: the different tokens of records ``(rec_id, t)``, a row a record; none for an empty one."""

    def count(batches):
        for ids, tokens, ends, codes, tf in term_sets(batches, n):
            ends = pa.array(ends, pa.int32())
            yield pa.RecordBatch.from_arrays([ids, pa.ListArray.from_arrays(ends, tokens.take(pa.array(codes))), pa.ListArray.from_arrays(ends, pa.array(tf, pa.int32()))], ["rec_id", "tokens", "tfs"])

    kind = lists.schema["rec_id"].dataType.simpleString()
    return lists.mapInArrow(count, f"rec_id {kind}, tokens array<string>, tfs array<int>")


def frequencies(lists: DataFrame, n: int | None = None) -> DataFrame:
    """``(token, df)`` of records ``(rec_id, t)``, counted by part of a batch: a token may have several rows."""

    def count(batches):
        for _, tokens, _, codes, _ in term_sets(batches, n):
            yield pa.RecordBatch.from_arrays([tokens, pa.array(np.bincount(codes, minlength=len(tokens)), pa.int64())], ["token", "df"])

    return lists.mapInArrow(count, "token string, df bigint")


def unpacked(terms: DataFrame) -> DataFrame:
    """``(rec_id, token, tf)`` of counted records."""
    return terms.select("rec_id", F.explode(F.arrays_zip("tokens", "tfs")).alias("_x")).select("rec_id", "_x.tokens", F.col("_x.tfs").cast("long").alias("tf")).withColumnRenamed("tokens", "token")


def joined(terms: DataFrame, vocabulary: DataFrame) -> DataFrame:
    """``(rec_id, keys, tfs, dfs)`` of counted records, each in the global order of its tokens, by a join with all tokens."""
    met = unpacked(terms).join(vocabulary, "token").groupBy("rec_id").agg(F.sort_array(F.collect_list(F.struct("key", F.col("tf").cast("int").alias("tf"), "df"))).alias("s"))
    return met.select("rec_id", F.col("s.key").alias("keys"), F.col("s.tf").alias("tfs"), F.col("s.df").alias("dfs"))


def sent(frequent: DataFrame):
    """A dictionary as a broadcast ``(tokens, keys, dfs)``."""
    table = frequent.select("token", "key", "df").toArrow().combine_chunks()
    whole = lambda c: pa.concat_arrays(c.chunks) if c.num_chunks else pa.array([], c.type)
    return frequent.sparkSession.sparkContext.broadcast((whole(table["token"]), table["key"].to_numpy(), table["df"].to_numpy()))


def coded(batches, n: int | None, frequent, first: int) -> Iterator[tuple]:
    """``(ids, ends, keys, tfs, dfs, lone, tokens)`` of batches ``(rec_id, t)``, each record in the global order of its tokens; ``frequent`` is a sent dictionary of tokens in two records or more.

    A token that it lacks stands in this record only (``lone``, their number by record): it meets no other, so its key need only be its own and
    rise with the token within the record. Such keys are drawn from ``first`` on, below all others, and must be written before they are used by key.
    """
    from pyspark import TaskContext

    words, keys, dfs = frequent.value
    missing, keys, dfs = len(words), np.append(keys, 0), np.append(dfs, 1)
    free = first + (TaskContext.get().partitionId() << 36)
    for ids, tokens, ends, codes, tfs in term_sets(batches, n):
        at = pc.index_in(tokens, value_set=words.cast(tokens.type)).fill_null(missing).to_numpy(zero_copy_only=False)
        place = np.empty(len(tokens), np.int64)
        place[pc.sort_indices(tokens).to_numpy()] = np.arange(len(tokens))
        row, key = np.repeat(np.arange(len(ids)), np.diff(ends)), keys[at[codes]]
        rare = np.flatnonzero(at[codes] == missing)
        rare = rare[np.lexsort((place[codes[rare]], row[rare]))]
        key[rare] = free + np.arange(len(rare))
        free += len(rare)
        order = np.lexsort((key, row))
        yield ids, ends, key[order], tfs[order], dfs[at[codes[order]]], np.bincount(row[rare], minlength=len(ids)), tokens.take(pa.array(codes[rare]))


def encoded(lists: DataFrame, frequent, first: int, n: int | None = None) -> DataFrame:
    """``(rec_id, keys, tfs, dfs, rare)`` of records ``(rec_id, t)``, as :func:`coded` gives them."""
    kind = lists.schema["rec_id"].dataType.simpleString()

    def encode(batches):
        for ids, ends, key, tfs, dfs, many, tokens in coded(batches, n, frequent, first):
            ends = pa.array(ends, pa.int32())
            rare = pa.ListArray.from_arrays(pa.array(np.append(0, np.cumsum(many)), pa.int32()), tokens)
            yield pa.RecordBatch.from_arrays([ids, *(pa.ListArray.from_arrays(ends, pa.array(x, kind)) for x, kind in ((key, pa.int64()), (tfs, pa.int32()), (dfs, pa.int64()))), rare], ["rec_id", "keys", "tfs", "dfs", "rare"])

    return lists.mapInArrow(encode, f"rec_id {kind}, keys array<bigint>, tfs array<int>, dfs array<bigint>, rare array<string>")


class Stream:
    """A side that is not written: its packed records ``(rec_id, keys, ws, total)`` are made as its texts are read, in the task that uses them.

    Keys of lone tokens may differ from one reading to the next, so only those of one reading may be compared by key.
    """

    def __init__(self, lists: DataFrame, frequent, first: int, n: int | None, weighting: str, records: int, power: int):
        self.frame = lists

        def sets(batches):
            for ids, ends, key, tfs, dfs, _, _ in coded(batches, n, frequent, first):
                yield weighted(ids, ends, key, tfs, dfs, weighting, records, power)

        self.sets = sets

    def packed(self) -> DataFrame:
        kind = self.frame.schema["rec_id"].dataType.simpleString()
        return self.frame.mapInArrow(self.sets, f"rec_id {kind}, keys array<bigint>, ws array<double>, total double")


def lone(codes: DataFrame) -> DataFrame:
    """``(token, df, key)`` of the tokens that stand in one record only."""
    pair = F.explode(F.arrays_zip(F.col("rare").alias("token"), F.slice("keys", 1, F.size("rare")).alias("key")))
    return codes.select(pair.alias("x")).select("x.token", F.lit(1).cast("long").alias("df"), "x.key")


def weighted(ids, ends, keys, tfs, dfs, weighting: str, records: int, power: int) -> pa.RecordBatch:
    """Packed records of flat arrays: weight 1, or tf times ln(1 + records / df), of Euclidean norm 1 for power 2."""
    row = np.repeat(np.arange(len(ids)), np.diff(ends))
    w = np.ones(len(keys)) if weighting == "binary" else tfs * np.log(1 + float(records) / dfs)
    if power == 2:
        w = w / np.sqrt(np.bincount(row, w * w, len(ids)))[row]
    ends = pa.array(ends, pa.int32())
    lists = [pa.ListArray.from_arrays(ends, pa.array(x)) for x in (keys, w)]
    return pa.RecordBatch.from_arrays([ids, *lists, pa.array(np.bincount(row, w * w if power == 2 else w, len(ids)))], ["rec_id", "keys", "ws", "total"])


def packed(codes: DataFrame, weighting: str, records: int, power: int) -> DataFrame:
    """``(rec_id, keys, ws, total)``, a row a record, of coded records.

    In Python, since Spark would work out a norm anew for each weight that it divides.
    """

    def pack(batches):
        for whole in batches:
            for batch in sliced(whole, "keys"):
                ends = batch.column("keys").offsets.to_numpy()
                keys, tfs, dfs = (batch.column(c).flatten().to_numpy(zero_copy_only=False) for c in ("keys", "tfs", "dfs"))
                yield weighted(batch.column("rec_id"), ends - ends[0], keys, tfs, dfs, weighting, records, power)

    kind = codes.schema["rec_id"].dataType.simpleString()
    return codes.select("rec_id", "keys", "tfs", "dfs").mapInArrow(pack, f"rec_id {kind}, keys array<bigint>, ws array<double>, total double")


def entries(sets: DataFrame, power: int = 1, sigma=None, among: np.ndarray | None = None) -> DataFrame:
    """``(rec_id, key, w, pos, pre, suf, total)``: packed records, a row a token; further columns go along.

    With ``sigma``, a function of arrays of totals and of column ``t``, only tokens whose suffix reaches it; with ``among`` only those of these keys.
    """

    def unpack(batches):
        for whole in batches:
            for batch in sliced(whole, "keys"):
                keys, w = batch.column("keys"), batch.column("ws").flatten().to_numpy(zero_copy_only=False)
                ends = keys.offsets.to_numpy()
                ends = ends - ends[0]
                n = np.diff(ends)
                row, first = np.repeat(np.arange(len(n)), n), np.repeat(ends[:-1], n)
                x = w * w if power == 2 else w
                run = _by_row(x, ends)
                total = batch.column("total").to_numpy(zero_copy_only=False)[row]
                suf = np.maximum(total - run, x)
                keep = np.arange(len(w)) if sigma is None else np.flatnonzero(suf >= sigma(total, batch.column("t").to_numpy(zero_copy_only=False)[row]))
                if among is not None:
                    keep = keep[np.isin(keys.flatten().to_numpy()[keep], among)]
                at = pa.array(row[keep])
                out = [batch.column("rec_id").take(at), keys.flatten().take(pa.array(keep)), *(pa.array(y[keep]) for y in (w, (np.arange(len(w)) - first + 1).astype(np.int32), run, suf, total))]
                yield pa.RecordBatch.from_arrays([*out, *(batch.column(c).take(at) for c in more)], ["rec_id", "key", "w", "pos", "pre", "suf", "total", *more])

    more = [c for c in sets.columns if c not in ("rec_id", "keys", "ws", "total")]
    kinds = dict(sets.dtypes)
    return sets.mapInArrow(unpack, ", ".join([f"rec_id {kinds['rec_id']}, key bigint, w double, pos int, pre double, suf double, total double", *(f"{c} {kinds[c]}" for c in more)]))


def _by_row(x: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Sums of the earlier entries of the own row; summed row by row, so that long batches lose no digits."""
    out = np.zeros(len(x))
    for i, j in zip(ends[:-1].tolist(), ends[1:].tolist()):
        out[i + 1 : j] = np.cumsum(x[i : max(i, j - 1)])
    return out


def unit_norm(sets: DataFrame) -> DataFrame:
    """Weights divided by the Euclidean norm of their record."""
    norm = sets.groupBy("rec_id").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
    return sets.join(norm, "rec_id").select("rec_id", "key", (F.col("w") / F.col("norm")).alias("w"))


def running(sets: DataFrame, power: int = 1) -> DataFrame:
    """Add position, prefix and suffix sums and the total of ``w ** power``, by record.

    A record's tokens are few next to a partition, so the window is by record. Suffixes are what
    prefixes leave of the total, as a frame that ends with the record would take quadratic time.
    """
    order = Window.partitionBy("rec_id").orderBy("key")
    x = F.col("w") if power == 1 else F.col("w") * F.col("w")
    out = sets.withColumn("_x", x)
    out = out.withColumn("pos", F.row_number().over(order))
    out = out.withColumn("pre", F.coalesce(F.sum("_x").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)))
    out = out.withColumn("total", F.sum("_x").over(Window.partitionBy("rec_id")))
    out = out.withColumn("suf", F.greatest(F.col("total") - F.col("pre"), "_x"))
    return out.drop("_x")


@dataclass(frozen=True)
class TokenModel:
    tokenizer: str = "word"
    weighting: str = "tfidf"

    @property
    def name(self) -> str:
        return f"{self.tokenizer}/{self.weighting}"


@dataclass
class Prepared:
    """Both collections under one token model and measure; ``b`` is ``a`` itself in deduplication."""

    a: DataFrame
    b: DataFrame
    vocabulary: DataFrame
    n_a: int
    n_b: int
    measure: str
    dedup: bool
    weighting: str = "tfidf"

    def flipped(self) -> "Prepared":
        return Prepared(self.b, self.a, self.vocabulary, self.n_b, self.n_a, self.measure, self.dedup, self.weighting)


class Unwritten(Prepared):
    """Prepared sides that are written when their rows are first asked for; until then they can be read as streams."""

    def __init__(self, codes: "Codes", n_a: int, n_b: int, measure: str, dedup: bool, weighting: str, turned: bool = False):
        self.codes, self.n_a, self.n_b, self.measure, self.dedup, self.weighting, self.turned = codes, n_a, n_b, measure, dedup, weighting, turned
        self._rows: dict = {}

    def _of(self, x: str) -> int:
        return 0 if self.dedup else int((x == "b") != self.turned)

    def stream(self, x: str) -> Stream | None:
        """Side ``x`` as it is read; None if its dictionary is too large to be sent."""
        return self.codes.stream(self._of(x), self.weighting, self._records(), self._power())

    def bytes(self, x: str) -> int:
        return self.codes.bytes[self._of(x)]

    def _records(self) -> int:
        return self.n_a if self.dedup else self.n_a + self.n_b

    def _power(self) -> int:
        return 2 if self.measure == "cosine" else 1

    def _side(self, x: str) -> DataFrame:
        if (i := self._of(x)) not in self._rows:
            sets = packed(self.codes.written()[i], self.weighting, self._records(), self._power())
            rows = entries(sets, self._power())
            rows._packed = sets
            self._rows[i] = rows
        return self._rows[i]

    @property
    def a(self) -> DataFrame:
        return self._side("a")

    @property
    def b(self) -> DataFrame:
        return self._side("b")

    @property
    def vocabulary(self) -> DataFrame:
        return self.codes.written()[2]

    def flipped(self) -> "Unwritten":
        return Unwritten(self.codes, self.n_b, self.n_a, self.measure, self.dedup, self.weighting, not self.turned)


class Codes:
    """Token sets of one or two collections under one tokeniser, as keys, term and document frequencies, a row a record."""

    def __init__(self, sides: list[DataFrame], single: list[bool], size: list[int], tokenizer: str):
        self.n, self.bytes, self._written = GRAMS.get(tokenizer), size, None
        self.lists = [token_lists(df, tokenizer, one) for df, one in zip(sides, single)]
        counts = [frequencies(x, self.n) for x in self.lists]
        counts = counts[0] if len(counts) == 1 else counts[0].unionAll(counts[1])
        self.frequent = ordered(counts.groupBy("token").agg(F.sum("df").alias("df")).where("df >= 2"))
        self.sent = sent(self.frequent) if self.frequent.count() <= VOCABULARY else None

    def stream(self, i: int, weighting: str, records: int, power: int) -> Stream | None:
        return self.sent and Stream(self.lists[i], self.sent, self._first(i), self.n, weighting, records, power)

    def _first(self, i: int) -> int:
        return (-1 << 61) if i else (-1 << 62)

    def written(self) -> tuple:
        """``(a, b, vocabulary)``, in the shared folder."""
        if self._written is None:
            if self.sent:
                sides = [cut(encoded(x, self.sent, self._first(i), self.n), "sets") for i, x in enumerate(self.lists)]
                vocabulary = self.frequent
                for x in sides:
                    vocabulary = vocabulary.unionByName(lone(x))
            else:
                terms = [counted(x, self.n) for x in self.lists]
                tokens = [t.select(F.explode("tokens").alias("token")) for t in terms]
                vocabulary = dictionary(tokens[0] if len(tokens) == 1 else tokens[0].unionAll(tokens[1]))
                sides = [cut(joined(t, vocabulary), "sets") for t in terms]
            self._written = (sides[0], sides[-1], vocabulary)
        return self._written


def measured(df: DataFrame) -> tuple[int, bool, int]:
    """Rows, whether no id has two, and bytes of text."""
    one = df.groupBy("rec_id").agg(F.count("*").alias("n"), F.sum(F.octet_length("text")).alias("x"))
    n, most, x = one.agg(F.sum("n"), F.max("n"), F.sum("x")).first()
    return n or 0, (most or 0) <= 1, x or 0


def prepare(a: DataFrame, b: DataFrame | None, model: TokenModel, measure: str, shared: dict | None = None) -> Prepared:
    """Token sets of ``a(rec_id, text)`` and ``b`` (None: deduplicate ``a``).

    A dictionary is made at once. Sides are written to the shared folder when their rows are first asked for, a row a
    record: keys, term and document frequencies. Weights, sums and the rows of the frames are worked out from it as they
    are read. ``shared`` is kept by a caller that prepares the same two collections several times: tokens and
    dictionaries are then worked out once.
    """
    shared = {} if shared is None else shared
    sides = [a] if b is None else [a, b]
    if "sizes" not in shared:
        shared["sizes"] = [measured(df) for df in sides]
    n, single, size = zip(*shared["sizes"])
    if model.tokenizer not in shared:
        shared[model.tokenizer] = Codes(sides, list(single), list(size), model.tokenizer)
    return Unwritten(shared[model.tokenizer], n[0], n[-1], measure, b is None, model.weighting)
