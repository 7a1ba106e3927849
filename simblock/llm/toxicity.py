"""Toxicity by nearest labelled examples under TF-IDF cosine, with block-max inverted lists.

Fitting takes a bounded sample of labelled rows (``FIT_ROWS``). All of them, of either label, are
examples. Terms are words and their beginnings of 4 to 12 letters, so that inflected and
compounded words meet. By default the terms of the space are those that stand in toxic
sample texts more often than chance allows (one-sided hypergeometric test over distinct
texts, false discoveries held to the share ``lean``) and at least ``LIFT`` times as often; there is
no limit on their number. With
``lean=None`` the space is the whole vocabulary of the sample's words. Inverse document frequencies
are from all rows. Examples are ordered so that similar ones lie together; their postings are cut into
blocks of example numbers, with the largest weight of each block kept aside. A query visits
blocks by falling upper bound and stops when no block can still change its k nearest, so
the result is that of an exhaustive search. Votes are weighted by similarity and shrunk
to the sample's rate. They are calibrated by isotonic regression on votes that each half of the
sample (split by text, so copies stay together) casts on the other with terms of its own
selection; in the whole vocabulary, on left-out votes.

Defined results: a text without any term of the space, also a null or empty one, gets the rate
of such sample rows, shrunk to the sample's, and has no evidence; a word that no example has counts
in the norm of the whole vocabulary only, with the weight of a word of one row; without labelled rows the score is 0; repeated
label rows of a document count as toxic if any is; unlabelled and null labels are never learned
from; repeated rows are scored one by one; an empty table gives an empty result; other
columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.stages import cut, shuffle_partitions

FIT_ROWS = 20_000  # labelled rows that are learned from at most, about
LEAN = 0.1  # share of chance findings among the selected terms, about
LIFT = 2.0  # how many times as often as by chance a selected term stands in toxic texts at least
CACHED = 10_000  # scores of distinct texts that a worker keeps
WORDS = 200_000  # words of at most LONG letters whose terms a worker keeps
LONG = 40
FLUSH = 200_000  # terms a worker counts before it passes them on


def held_out(id_col: str, folds: int = 5) -> Column:
    return F.crc32(F.encode(F.col(id_col).cast("string"), "UTF-8")) % folds == 0


def words(text: str) -> list[str]:
    import re

    return re.findall(r"[^\W\d_]+", text.lower())


def _ranges(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """All numbers of the given ranges, one range after the other."""
    ends = np.cumsum(lengths)
    return np.arange(ends[-1] if len(ends) else 0) + np.repeat(starts - (ends - lengths), lengths)


class BlockMaxIndex:
    """Inverted lists of unit vectors in blocks of ``block`` example numbers."""

    def __init__(self, vectors: list[dict[int, float]], terms: int, block: int = 64):
        example = np.repeat(np.arange(len(vectors)), [len(v) for v in vectors])
        term = np.array([t for v in vectors for t in v], dtype=np.int64)
        self._build(example, term, np.array([w for v in vectors for w in v.values()], dtype=float), len(vectors), terms, block, np.arange(len(vectors)))

    @classmethod
    def of(cls, example: np.ndarray, term: np.ndarray, weight: np.ndarray, n: int, terms: int, order: np.ndarray, block: int = 64) -> BlockMaxIndex:
        """From postings; ``order`` lists the examples as they are to lie in blocks."""
        out = cls.__new__(cls)
        out._build(example, term, weight, n, terms, block, order)
        return out

    def _build(self, example, term, weight, n, terms, block, order) -> None:
        self.n, self.block, self.blocks, self.number = n, block, max(1, -(-n // block)), order
        place = np.empty(n, dtype=np.int64)
        place[order] = np.arange(n)
        at = place[example]
        by = np.lexsort((at, term))
        self.at, self.w, term = at[by].astype(np.int32), weight[by], term[by].astype(np.int64)
        key = term * self.blocks + self.at // block
        start = np.flatnonzero(np.diff(key, prepend=-1))
        self.run_start, self.run_length = start, np.diff(start, append=len(key)).astype(np.int32)
        self.run_block = (key[start] % self.blocks).astype(np.int32)
        self.run_top = np.maximum.reduceat(self.w, start) if len(start) else np.zeros(0)
        self.first = np.searchsorted(key[start] // self.blocks, np.arange(terms + 1))
        self.list_first = np.searchsorted(term, np.arange(terms + 1))

    def _all(self, terms: np.ndarray, weights: np.ndarray) -> np.ndarray:
        """Cosines with all examples: short lists at once, long ones each in its place."""
        a, b = self.list_first[terms], self.list_first[terms + 1]
        short = b - a < 512
        postings = _ranges(a[short], (b - a)[short])
        out = np.zeros(self.n)  # bincount of nothing has whole numbers
        if len(postings):
            out += np.bincount(self.at[postings], np.repeat(weights[short], (b - a)[short]) * self.w[postings], self.n)
        for i, j, x in zip(a[~short].tolist(), b[~short].tolist(), weights[~short].tolist()):
            out[self.at[i:j]] += x * self.w[i:j]
        return out

    def nearest(self, query: dict[int, float], k: int, skip: int = -1) -> list[tuple[int, float]]:
        """The k examples of largest positive cosine, ties by number."""
        return self.search(np.fromiter(query.keys(), np.int64, len(query)), np.fromiter(query.values(), float, len(query)), k, skip)

    def search(self, terms: np.ndarray, weights: np.ndarray, k: int, skip: int = -1) -> list[tuple[int, float]]:
        if not len(terms) or not self.n:
            return []
        lengths = self.first[terms + 1] - self.first[terms]
        runs, weight = _ranges(self.first[terms], lengths), np.repeat(weights, lengths)
        block = self.run_block[runs]
        bound = np.bincount(block, weight * self.run_top[runs], self.blocks)
        order = np.argsort(-bound, kind="stable")
        best, score = np.zeros(0, dtype=np.int64), np.zeros(0)
        done, step = 0, 8
        while done < len(order):
            least = score[k - 1] - 1e-11 if len(score) >= k else 0.0
            part = order[done : done + step]
            part = part[(bound[part] > 0) & (bound[part] >= least)]
            if not len(part):
                break
            if done and np.count_nonzero(bound >= least) > self.blocks // 8:
                # too many blocks are left for picking them to pay: whole lists, of which the visited blocks are known
                found = self._all(terms, weights)
                for b in order[:done].tolist():
                    found[b * self.block : (b + 1) * self.block] = 0
                done = len(order)
            else:
                chosen = np.zeros(self.blocks, dtype=bool)
                chosen[part] = True
                mine = np.flatnonzero(chosen[block])
                many = self.run_length[runs[mine]]
                postings = _ranges(self.run_start[runs[mine]], many)
                found = np.bincount(self.at[postings], np.repeat(weight[mine], many) * self.w[postings], self.n)
            if len(score) < k and np.count_nonzero(found) > k:
                least = max(least, np.partition(found, -k - 1)[-k - 1] - 1e-11)  # one more for an example to skip
            hit = np.flatnonzero((found > 0) & (found >= least))
            best = np.concatenate([best, self.number[hit]])
            score = np.concatenate([score, np.round(found[hit], 12)])
            best, score = best[(best != skip) & (score > 0)], score[(best != skip) & (score > 0)]
            top = np.lexsort((best, -score))[:k]
            best, score = best[top], score[top]
            done, step = done + step, step * 2
        return list(zip(best.tolist(), score.tolist()))


def in_blocks(points: np.ndarray, block: int = 64, seed: int = 5) -> np.ndarray:
    """Row numbers ordered so that similar rows lie together: halved along the widest direction, again and again."""
    rng, out, todo = np.random.default_rng(seed), [], [np.arange(len(points))]
    while todo:
        rows = todo.pop()
        if len(rows) <= block:
            out.append(rows)
            continue
        x = points[rows] - points[rows].mean(axis=0)
        v = rng.standard_normal(x.shape[1]).astype(x.dtype)
        for _ in range(8):
            v = x.T @ (x @ v)
            v /= max(float(np.linalg.norm(v)), 1e-30)
        rows = rows[np.argsort(x @ v, kind="stable")]
        half = -(-len(rows) // (2 * block)) * block
        todo += [rows[half:], rows[:half]]
    return np.concatenate(out) if out else np.zeros(0, dtype=np.int64)


def isotonic(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pool-adjacent-violators: (upper ends, smoothed means) of rising steps."""
    order = np.argsort(x, kind="stable")
    steps: list[list[float]] = []  # end, sum, count
    for a, b in zip(x[order].tolist(), y[order].tolist()):
        if steps and steps[-1][0] == a:
            steps[-1][1] += b
            steps[-1][2] += 1
        else:
            steps.append([a, b, 1.0])
        while len(steps) > 1 and steps[-2][1] / steps[-2][2] >= steps[-1][1] / steps[-1][2]:
            end, s, n = steps.pop()
            steps[-1] = [end, steps[-1][1] + s, steps[-1][2] + n]
    return np.array([s[0] for s in steps]), np.array([(s[1] + 0.5) / (s[2] + 1) for s in steps])


def word_counts(text: str | None) -> dict[str, int]:
    from collections import Counter

    return Counter(words(text or ""))


def terms_of(word: str) -> list[str]:
    """The word and its beginnings of 4 to 12 letters; no word holds the sign that marks a beginning."""
    return [word, *(word[:n] + "*" for n in range(4, min(len(word), 13)))]


def chance(least: np.ndarray, df: np.ndarray, toxic: int, total: int) -> np.ndarray:
    """Probability that ``df`` of ``total`` texts, drawn blindly, hold ``least`` or more of the ``toxic`` ones."""
    logs = np.concatenate([[0.0], np.cumsum(np.log(np.arange(1, total + 1)))])
    ways = lambda n, k: logs[n] - logs[k] - logs[n - k]
    out = np.zeros(len(df))
    for j, (a, n) in enumerate(zip(least.tolist(), df.tolist())):
        i = np.arange(max(a, n - (total - toxic)), min(n, toxic) + 1)
        out[j] = np.exp(ways(toxic, i) + ways(total - toxic, n - i) - ways(total, n)).sum()
    return out


def least_toxic(pairs: pd.DataFrame, toxic: int, total: int, lean: float) -> dict[int, int]:
    """From how many toxic texts on a term of so many texts is selected.

    ``pairs`` has how many terms (``many``) stand in ``n`` texts, ``t`` of them toxic. By the rule
    of Benjamini and Hochberg the largest probability is taken up to which chance would yield
    at most the share ``lean`` of what is found. Common words can lean a little beyond doubt, which
    tells nothing and makes long lists, so a term must also reach ``LIFT`` times its expected number.
    """
    if not len(pairs) or not 0 < toxic < total:
        return {}
    p = chance(pairs["t"].to_numpy(), pairs["n"].to_numpy(), toxic, total)
    order = np.argsort(p, kind="stable")
    many = np.cumsum(pairs["many"].to_numpy()[order])
    good = np.flatnonzero(p[order] <= lean * many / many[-1])
    out: dict[int, int] = {}
    for j in order[: good[-1] + 1] if len(good) else []:
        n, t = int(pairs["n"].iloc[j]), int(pairs["t"].iloc[j])
        if t * total >= LIFT * n * toxic:
            out[n] = min(t, out.get(n, t))
    return out


class Space:
    """Numbered terms; sent as one string and looked up in a dict that each worker builds."""

    def __init__(self, names: list[str], whole: bool):
        self.joined, self.whole, self.size = " ".join(names), whole, len(names)
        self._number, self._of = None, {}

    def __getstate__(self):
        return {**self.__dict__, "_number": None, "_of": {}}

    def of(self, word: str) -> tuple:
        """Numbers of the word's terms."""
        if self._number is None:
            self._number = {w: i for i, w in enumerate(self.joined.split())}
        found = self._of.get(word)
        if found is None:
            number = self._number
            found = tuple(number[t] for t in ([word] if self.whole else terms_of(word)) if t in number)
            if len(word) <= LONG:
                if len(self._of) >= WORDS:
                    self._of.clear()
                self._of[word] = found
        return found

    def counts(self, text: str | None) -> tuple[dict[int, int], list[int]]:
        """How often each term stands in a text, and the counts of words without a term."""
        out: dict[int, int] = {}
        other = []
        for w, n in word_counts(text).items():
            found = self.of(w)
            for t in found:
                out[t] = out.get(t, 0) + n
            if not found:
                other.append(n)
        return out, other


class Scorer:
    """What is learned: terms with weights, all examples, their index and the calibration."""

    def __init__(self, space: Space, idf: np.ndarray, unseen: float, ids: list, labels: np.ndarray, starts: np.ndarray, term: np.ndarray, count: np.ndarray, rate: float, bare_rate: float, k: int):
        self.space, self.idf, self.unseen, self.k, self.rate, self.bare_rate = space, idf, unseen, k, rate, bare_rate
        self.ids, self.labels, self.starts, self.term, self.count = ids, labels, starts, term, count
        self.ends, self.means, self.live = np.zeros(0), np.zeros(0), np.ones(space.size, dtype=bool)
        self._index, self.cache = None, {}

    def __getstate__(self):
        return {**self.__dict__, "_index": None, "cache": {}}

    def _weights(self) -> tuple[np.ndarray, np.ndarray]:
        """Example and weight of each posting; vectors have length 1."""
        n = len(self.ids)
        example = np.repeat(np.arange(n), np.diff(self.starts))
        w = (1 + np.log(self.count)) * self.idf[self.term]
        norm = np.sqrt(np.bincount(example, w * w, n))
        return example, w / norm[example]

    def _common(self, width: int = 256) -> np.ndarray:
        """Weights of the most frequent terms only, by which examples are ordered (it changes no result)."""
        example, w = self._weights()
        often = np.argsort(-np.bincount(self.term, minlength=len(self.idf)), kind="stable")[:width]
        column = np.full(len(self.idf), -1)
        column[often] = np.arange(len(often))
        out = np.zeros((len(self.ids), max(1, len(often))), dtype=np.float32)
        at = column[self.term]
        out[example[at >= 0], at[at >= 0]] = w[at >= 0]
        return out

    @property
    def index(self) -> BlockMaxIndex:
        if self._index is None:
            example, w = self._weights()
            self._index = BlockMaxIndex.of(example, self.term, w, len(self.ids), len(self.idf), in_blocks(self._common()))
        return self._index

    def part(self, rows: np.ndarray, terms: np.ndarray) -> Scorer:
        """The scorer that only the given rows and terms (both as masks) make; term numbers stay."""
        example = np.repeat(np.arange(len(self.ids)), np.diff(self.starts))
        stays = rows[example] & terms[self.term]
        length = np.bincount(example[stays], minlength=len(self.ids))
        rows = rows & (length > 0)
        starts = np.concatenate([[0], np.cumsum(length[rows])])
        rate = float(self.labels[rows].mean()) if rows.any() else 0.0
        out = Scorer(self.space, self.idf, self.unseen, np.flatnonzero(rows).tolist(), self.labels[rows], starts, self.term[stays], self.count[stays], rate, self.bare_rate, self.k)
        out.live = terms
        return out

    def unit(self, text: str | None) -> tuple[np.ndarray, np.ndarray]:
        """Terms and weights of a text; words of no example count in the norm of the whole vocabulary."""
        counts, other = self.space.counts(text)
        at, n = np.fromiter(counts.keys(), np.int64, len(counts)), np.fromiter(counts.values(), float, len(counts))
        at, n = at[self.live[at]], n[self.live[at]]
        w = (1 + np.log(n)) * self.idf[at]
        square = float(w @ w)
        if self.space.whole and other:
            rest = (1 + np.log(np.array(other, dtype=float))) * self.unseen
            square += float(rest @ rest)
        return at, w / math.sqrt(square) if square > 0 else w

    def vote(self, near: list[tuple[int, float]]) -> float:
        return (sum(s * self.labels[i] for i, s in near) + self.rate) / (sum(s for _, s in near) + 1)

    def vote_on(self, term: np.ndarray, count: np.ndarray, skip: int = -1) -> float:
        """Vote on a vector of known terms, if need be without one of the examples."""
        w = (1 + np.log(count)) * self.idf[term]
        norm = np.linalg.norm(w)
        return float(self.vote(self.index.search(term.astype(np.int64), w / norm if norm > 0 else w, self.k, skip)))

    def calibrate(self, votes: np.ndarray, labels: np.ndarray) -> None:
        if len(votes) >= 50:
            self.ends, self.means = isotonic(votes, labels.astype(float))

    def score(self, text: str | None) -> tuple[float, list[tuple[int, float]]]:
        from hashlib import blake2b

        key = blake2b((text or "").encode("utf-8", "surrogatepass"), digest_size=16).digest()
        if key not in self.cache:
            if len(self.cache) >= CACHED:
                self.cache.clear()
            terms, weights = self.unit(text)
            near = self.index.search(terms, weights, self.k)
            if not len(terms):
                value = self.bare_rate
            elif len(self.ends):
                value = float(self.means[min(int(np.searchsorted(self.ends, self.vote(near))), len(self.means) - 1)])
            else:
                value = float(self.vote(near))
            self.cache[key] = (min(1.0, max(0.0, value)), near)
        return self.cache[key]


def _labelled_sample(docs: DataFrame, labels: DataFrame, id_col: str, text_col: str, label_col: str, train: Column) -> DataFrame:
    """``(_id, _text, _toxic, _half)`` of about FIT_ROWS labelled rows of the training part; equal texts share a half."""
    known = labels.where(F.col(label_col).isNotNull() & F.col(id_col).isNotNull()).where(train).groupBy(F.col(id_col).alias("_id")).agg(F.max(F.col(label_col)).cast("int").alias("_toxic"))
    total = known.count()
    share = int(min(1.0, FIT_ROWS / max(total, 1)) * (1 << 30)) + 1
    known = cut(known.where(F.pmod(F.xxhash64("_id", F.lit(3)), F.lit(1 << 30)) < share), "examples")
    rows = docs.select(F.col(id_col).alias("_id"), F.coalesce(F.col(text_col), F.lit("")).alias("_text"))
    picked = rows.join(F.broadcast(known), "_id")  # FIT_ROWS rows of a few bytes
    return cut(picked.withColumn("_half", F.pmod(F.xxhash64("_text", F.lit(17)), F.lit(2)).cast("int")), "sample")


def _term_statistics(sample: DataFrame, whole: bool) -> DataFrame:
    """``(_term, n0, t0, n1, t1)``: distinct sample texts with a term, and toxic ones, by half; a row of no term has all texts."""

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        seen: dict[str, list[int]] = {}

        def told() -> pd.DataFrame:
            out = pd.DataFrame(list(seen.values()), columns=["n0", "t0", "n1", "t1"], dtype="int64").assign(_term=list(seen))
            seen.clear()
            return out[["_term", "n0", "t0", "n1", "t1"]]

        for b in batches:
            for text, toxic, half in zip(b["_text"], b["_toxic"], b["_half"]):
                found = {""}
                for w in word_counts(text):
                    found.update([w] if whole else terms_of(w))
                for t in found:
                    c = seen.get(t)
                    if c is None:
                        c = seen[t] = [0, 0, 0, 0]
                    c[2 * half] += 1
                    c[2 * half + 1] += toxic
                if len(seen) >= FLUSH:
                    yield told()
        if seen:
            yield told()

    texts = sample.groupBy("_text", "_half").agg(F.max("_toxic").alias("_toxic"))
    found = texts.mapInPandas(count, "_term string, n0 long, t0 long, n1 long, t1 long")
    return found.groupBy("_term").agg(*[F.sum(c).alias(c) for c in ("n0", "t0", "n1", "t1")])


def select_terms(sample: DataFrame, lean: float | None) -> pd.DataFrame:
    """``(_term, all, half0, half1)``: the terms of the space, and which of them each half would select by itself."""
    counted = _term_statistics(sample, lean is None)
    views = {"all": (F.col("n0") + F.col("n1"), F.col("t0") + F.col("t1")), "half0": (F.col("n0"), F.col("t0")), "half1": (F.col("n1"), F.col("t1"))}
    if lean is None:
        return counted.where("_term <> ''").select("_term", *[F.lit(True).alias(v) for v in views]).toPandas()  # the words of FIT_ROWS texts
    counted = cut(counted, "terms")
    totals = counted.where("_term = ''").select(*[c for v, (n, t) in views.items() for c in (n.alias(f"n_{v}"), t.alias(f"t_{v}"))]).first()
    terms = counted.where("_term <> '' AND n0 + n1 > 1")
    chosen = []
    for v, (n, t) in views.items():
        pairs = terms.where(n > 1).groupBy(n.alias("n"), t.alias("t")).agg(F.count("*").alias("many")).toPandas()  # pairs of counts of FIT_ROWS texts
        least = least_toxic(pairs, totals[f"t_{v}"], totals[f"n_{v}"], lean) if totals else {}
        known = F.create_map(*[F.lit(x) for kv in least.items() for x in kv]) if least else None
        chosen.append((F.coalesce(t >= F.try_element_at(known, n), F.lit(False)) if least else F.lit(False)).alias(v))
    return terms.select("_term", *chosen).where("all or half0 or half1").orderBy("_term").toPandas()  # selected terms of FIT_ROWS texts


def _frequencies(docs: DataFrame, text_col: str, space: Space) -> tuple[np.ndarray, int]:
    """Of each term the number of rows that have it, over all rows, and the number of rows."""
    sent, size = docs.sparkSession.sparkContext.broadcast(space), space.size

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        s, seen, rows = sent.value, np.zeros(size + 1, dtype=np.int64), 0
        for b in batches:
            rows += len(b)
            for text in b["_text"]:
                found: set = set()
                for w in set(words(text)):
                    found.update(s.of(w))
                seen[list(found)] += 1
        seen[size] = rows
        at = np.flatnonzero(seen)
        yield pd.DataFrame({"_term": at, "_n": seen[at]})

    texts = docs.select(F.coalesce(F.col(text_col), F.lit("")).alias("_text"))
    found = texts.mapInPandas(count, "_term long, _n long").groupBy("_term").agg(F.sum("_n").alias("_n")).toPandas()  # one row a term
    sent.unpersist()
    out = np.zeros(size + 1, dtype=np.int64)
    out[found["_term"].to_numpy(dtype=np.int64)] = found["_n"].to_numpy(dtype=np.int64)
    return out[:size], int(out[size])


def _examples(sample: DataFrame, space: Space) -> pd.DataFrame:
    """``(_id, _toxic, _half, _terms, _counts)`` of all sample rows, terms and counts as packed numbers."""
    sent = sample.sparkSession.sparkContext.broadcast(space)

    def scan(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            counts = [sent.value.counts(t)[0] for t in b["_text"]]
            packed = {"_terms": [np.fromiter(c.keys(), np.int32, len(c)).tobytes() for c in counts], "_counts": [np.fromiter(c.values(), np.int32, len(c)).tobytes() for c in counts]}
            yield b.drop(columns="_text").assign(**packed)

    kind = dict(sample.dtypes)["_id"]
    hashed = sample.select("_id", "_toxic", "_half", F.xxhash64("_id").alias("_h"), F.xxhash64("_text").alias("_t"), "_text")
    rows = hashed.mapInPandas(scan, f"_id {kind}, _toxic int, _half int, _h long, _t long, _terms binary, _counts binary").toPandas()  # the bounded sample
    sent.unpersist()
    return rows.sort_values(["_h", "_t"], kind="stable")


def fit(docs: DataFrame, labels: DataFrame, k: int = 15, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", train: Column | None = None, lean: float | None = LEAN) -> Scorer:
    """The scorer learned from a bounded sample of the labelled rows.

    ``train`` is a predicate over the label rows that may be learned from; by default
    those whose id is not in the held-out fold. ``lean`` is the share of chance findings
    among the selected terms, or None for the whole vocabulary.
    """
    spark = docs.sparkSession
    sample = _labelled_sample(docs, labels, id_col, text_col, label_col, ~held_out(id_col) if train is None else train)
    chosen = select_terms(sample, lean)
    space = Space(chosen["_term"].tolist(), lean is None)
    rows = _examples(sample, space)
    rate = float(rows["_toxic"].mean()) if len(rows) else 0.0
    frequency, total = _frequencies(docs, text_col, space) if space.size else (np.zeros(0), 0)
    idf = np.log((1 + total) / (1 + frequency)) + 1
    starts = np.concatenate([[0], np.cumsum([len(x) // 4 for x in rows["_terms"]], dtype=np.int64)])
    term, count = (np.frombuffer(b"".join(rows[c]), dtype=np.int32) for c in ("_terms", "_counts"))
    toxic, half, ids = rows["_toxic"].to_numpy(dtype=np.int64), rows["_half"].to_numpy(), rows["_id"].tolist()
    every = Scorer(space, idf, math.log((1 + total) / 2) + 1, ids, toxic, starts, term, count, rate, 0.0, k)
    masks = {v: chosen[v].to_numpy(dtype=bool) for v in ("all", "half0", "half1")}
    scorer = every.part(np.ones(len(ids), dtype=bool), masks["all"])
    bare = np.ones(len(ids), dtype=bool)
    bare[scorer.ids] = False
    scorer.bare_rate, scorer.rate = float((toxic[bare].sum() + rate) / (bare.sum() + 1)), rate
    if lean is None:
        judges, asked = [scorer], [(0, j, i) for j, i in enumerate(scorer.ids)]
    else:
        judges = [every.part(half == h, masks[f"half{h}"]) for h in (0, 1)]
        asked = [(1 - int(half[i]), -1, i) for i in range(len(ids))]
    questions = []  # which judge, the judge's own example to leave out, the row, its terms the judge knows
    for judge, skip, i in asked:
        mine = slice(starts[i], starts[i + 1])
        known = masks["all" if lean is None else f"half{judge}"][term[mine]]
        if known.any():
            questions.append((judge, skip, i, term[mine][known], count[mine][known]))
    if questions:
        sent = spark.sparkContext.broadcast((judges, questions))

        def votes(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            told, asked = sent.value
            for b in batches:
                yield pd.DataFrame({"id": b["id"], "vote": [told[asked[n][0]].vote_on(asked[n][3], asked[n][4], asked[n][1]) for n in b["id"]]})

        cast = spark.range(0, len(questions), 1, shuffle_partitions(spark)).mapInPandas(votes, "id long, vote double").toPandas().sort_values("id")
        sent.unpersist()
        scorer.calibrate(cast["vote"].to_numpy(), toxic[[q[2] for q in questions]])
    scorer.ids = [ids[i] for i in scorer.ids]
    return scorer


def score_documents(docs: DataFrame, labels: DataFrame, k: int = 15, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", train: Column | None = None, lean: float | None = LEAN) -> DataFrame:
    """``(id, score, evidence)``: evidence lists the nearest examples as (id, similarity, label)."""
    sent = docs.sparkSession.sparkContext.broadcast(fit(docs, labels, k, id_col, text_col, label_col, train, lean))
    kind = dict(docs.dtypes)[id_col]

    def scan(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        s = sent.value
        for b in batches:
            score, evidence = [], []
            for t in b["_text"]:
                value, near = s.score(t)
                score.append(value)
                evidence.append([{"id": s.ids[i], "similarity": c, "label": int(s.labels[i])} for i, c in near])
            yield pd.DataFrame({id_col: b["_id"], "score": score, "evidence": evidence})

    rows = docs.select(F.col(id_col).alias("_id"), F.coalesce(F.col(text_col), F.lit("")).alias("_text"))
    return rows.mapInPandas(scan, f"`{id_col}` {kind}, score double, evidence array<struct<id:{kind},similarity:double,label:int>>")


def keep_clean(docs: DataFrame, labels: DataFrame, threshold: float = 0.5, **options) -> DataFrame:
    """The rows that score below the threshold, with all their columns and no shuffle of texts."""
    sent = docs.sparkSession.sparkContext.broadcast(fit(docs, labels, **options))
    at = docs.columns.index(options.get("text_col", "text"))

    def scan(batches):
        import pyarrow as pa

        s = sent.value
        for b in batches:
            stays = [s.score(t)[0] < threshold for t in b.column(at).to_pylist()]
            yield b.filter(pa.array(stays, type=pa.bool_()))

    return docs.mapInArrow(scan, docs.schema)
