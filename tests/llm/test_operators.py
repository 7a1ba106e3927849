"""The ten operators against brute force, on a given table and on rows with every odd case."""

import base64
import gzip
import hashlib
import itertools
import math
import zlib

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F

from simblock.llm import boilerplate, bpe, compression, hilbert, itq, packing, queries, quotes, simhash, toxicity, warc

WORD = public_tokenizers.path("word_bpe_49k.json")
RANKS = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
DOCS = "doc_id long, text string, lang string, source string, n_chars long, score double, component_id long, shard string, _id string"


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls in every column, empty and long texts, ties, repeated rows, clashing columns."""
    base = "some words that make a text long enough for shingles and windows " * 3
    long = " ".join(f"w{i * 7919 % 10007}" for i in range(30_000))
    rows = [
        (1, base, "en", "a", 10), (2, base, "en", "b", 10), (3, base, None, "a", None), (3, base, None, "a", None),
        (4, None, "de", None, 0), (5, "", "de", "a", 0), (6, " \n\t ", None, None, None), (7, long, "en", "a", len(long)),
        (8, "x" * 50_000, "en", "a", 50_000), (9, "héllo wörld 東京 🎉 don't\r\n\tstop", "fr", "c", 20), (10, "one", "en", "a", 3),
    ]
    return spark.createDataFrame([(*r, 0.5, 77, "s", "i") for r in rows], DOCS)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


def docs(spark, sf, odd):
    given = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "lang", "source", "n_chars")
    return given.withColumn("doc_id", F.col("doc_id") + 100).unionByName(odd.select(given.columns))


def texts(df):
    return [(r["doc_id"], r["text"]) for r in df.select("doc_id", "text").collect()]


# 1 ---------------------------------------------------------------------------------------------
def slow_hilbert(n, bits):
    """Cells in curve order by the recursive definition: Gray-code walks of rotated cubes."""
    inverse, entry, turn = hilbert._tables(n)
    gray = [i ^ (i >> 1) for i in range(1 << n)]
    rot = lambda x, k: ((x << k % n) | (x >> (n - k % n) % n)) & ((1 << n) - 1) if k % n else x

    def walk(level, e, d, prefix):
        if level < 0:
            yield tuple(prefix)
            return
        for w in range(1 << n):
            label = rot(gray[w], d + 1) ^ e
            yield from walk(level - 1, e ^ rot(entry[w], d + 1), (d + turn[w] + 1) % n, [p | ((label >> i & 1) << level) for i, p in enumerate(prefix)])

    return list(walk(bits - 1, 0, 0, [0] * n))


@pytest.mark.parametrize("n,bits", [(2, 3), (3, 2)])
def test_hilbert_curve(spark, n, bits):
    curve = slow_hilbert(n, bits)
    assert len(set(curve)) == 1 << n * bits
    assert all(sum(abs(a - b) for a, b in zip(p, q)) == 1 for p, q in itertools.pairwise(curve))
    df = spark.createDataFrame([(*c,) for c in curve], [f"c{i}" for i in range(n)])
    got = [r[0] for r in df.select(hilbert.hilbert_index([F.col(f"c{i}") for i in range(n)], bits)).collect()]
    assert got == list(range(len(curve)))


@pytest.mark.parametrize("law", ["bytes", "rows"])
def test_shards(spark, sf, odd, law):
    df = docs(spark, sf, odd)
    placed = hilbert.shard_documents(df, 4, ["lang", "source", "n_chars"], law=law)
    rows = placed.collect()
    want = sorted((i, len((t or "").encode()) + 8, zlib.crc32((t or "").encode())) for i, t in texts(df))
    assert sorted((r["doc_id"], r["size"], r["text_crc32"]) for r in rows) == want
    for s in range(4):
        assert sorted(r["slot"] for r in rows if r["shard"] == s) == list(range(sum(r["shard"] == s for r in rows)))
    ordered = sorted(rows, key=lambda r: (r["shard"], r["slot"]))
    assert [r["hilbert"] for r in ordered] == sorted(r["hilbert"] for r in rows)
    counts = [sum(r["shard"] == s for r in rows) for s in range(4)]
    sizes = [sum(r["size"] for r in rows if r["shard"] == s) for s in range(4)]
    if law == "rows":
        assert max(counts) - min(counts) <= 1
    else:
        assert max(sizes) - min(sizes) <= 2 * max(r["size"] for r in rows)
    listed = hilbert.manifest(placed, ["n_chars"])
    hit = {r["shard"] for r in hilbert.matching_shards(listed, n_chars=(50_000, 60_000)).collect()}
    assert {r["shard"] for r in rows if (r["n_chars"] or 0) >= 50_000} <= hit


def test_shards_empty(none):
    assert hilbert.shard_documents(none, 4, ["lang", "source"]).count() == 0


# 2 ---------------------------------------------------------------------------------------------
def slow_links(rows, threshold):
    ok = {}
    for at, (i, v, label) in enumerate(rows):
        if label is not None and v and all(x is not None and math.isfinite(x) for x in v) and any(v):
            x = np.array(v, dtype=float)
            ok[at] = (label, x / np.linalg.norm(x))
    links = {at: [b for b in ok if at in ok and b != at and ok[b][0] == ok[at][0] and len(ok[b][1]) == len(ok[at][1]) and ok[b][1] @ ok[at][1] >= threshold] for at in range(len(rows))}
    out = []
    for at in range(len(rows)):
        seen, todo = {at}, [at]
        while todo:
            for b in links[todo.pop()]:
                if b not in seen:
                    seen.add(b)
                    todo.append(b)
        least = min(rows[b][0] for b in seen)
        out.append((rows[at][0], len(links[at]), least, least == rows[at][0]))
    return sorted(out)


@pytest.mark.parametrize("block", [2048, 40])
def test_embeddings(spark, sf, block):
    rng = np.random.default_rng(1)
    given = [(r["vec_id"] + 1000, list(map(float, r["embedding"])), r["label"]) for r in spark.read.parquet(f"{sf}/embeddings.parquet").collect()]
    centre = rng.standard_normal(64)
    near = [(2000 + i, (centre + 0.02 * rng.standard_normal(64)).tolist(), 1) for i in range(60)]
    same = [(3000 + i, centre.tolist(), 1) for i in range(30)] + [(4000, (2 * centre).tolist(), 1), (4001, centre.tolist(), 2), (4002, centre.tolist(), None)]
    bad = [(1, None, 1), (2, [], 1), (3, [0.0] * 64, 1), (4, [None] + [1.0] * 63, 1), (5, [float("nan")] * 64, 1), (6, [float("inf")] + [1.0] * 63, 1), (7, [1.0, 2.0], 1), (8, [2.0, 4.0], 1), (9, [1.0, 2.0], 1)]
    rows = given + near + same + bad + [(10, centre.tolist(), 5), (10, centre.tolist(), 5)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").withColumn("_node", F.lit(1))
    got = sorted(map(tuple, itq.near_duplicates(df, 0.98, block=block).collect()))
    assert [g[0] for g in got] == sorted(r[0] for r in rows)
    want = slow_links([(i, None if v is None else [None if x is None else float(np.float32(x)) for x in v], y) for i, v, y in rows], 0.98)
    found, asked = sum(g[1] for g in got), sum(w[1] for w in want)
    assert found <= asked and found >= 0.99 * asked
    assert sum(a == b for a, b in zip(got, want)) >= 0.97 * len(want)
    assert got[:9] == want[:9]


@pytest.mark.parametrize("mean", [0.0, 0.9, 0.95])
def test_embeddings_recall_at_threshold(mean):
    rng = np.random.default_rng(int(mean * 100) + 1)
    unit = lambda x: x / np.linalg.norm(x, axis=1, keepdims=True)
    spread = unit(rng.standard_normal((12_000, 64)))
    spread[:, 0] = 0
    base = math.sqrt(1 - mean * mean) * unit(spread)
    base[:, 0] = mean
    base = unit(base if mean else rng.standard_normal((12_000, 64)))
    step = rng.standard_normal(base.shape)
    step = unit(step - (step * base).sum(axis=1, keepdims=True) * base)
    cosine = rng.uniform(0.98, 0.985, (len(base), 1))
    near = cosine * base + np.sqrt(1 - cosine**2) * step
    radii = np.linalg.norm(base - base.mean(axis=0), axis=1)
    for rows in (200, 100_000, 1_000_000):
        tables, bits = itq.table_layout(rows, 0.98, radii=radii)
        models = [itq.learn_rotation(base[:8000], 7 + i) for i in range(max(1, math.ceil(tables * bits / 64)))]
        a, b = itq._encode(base, models, tables, bits), itq._encode(near, models, tables, bits)
        print(mean, rows, tables, bits, (a == b).any(axis=1).mean())
        assert (a == b).any(axis=1).mean() >= 0.98


@pytest.mark.parametrize("mean", [0.0, 0.9])
def test_hamming_bound_keeps_pairs_at_threshold(mean):
    """Whole codes of pairs at 0.98-0.985 are within the bound, those of unrelated vectors hardly ever."""
    rng = np.random.default_rng(int(mean * 100) + 5)
    unit = lambda x: x / np.linalg.norm(x, axis=1, keepdims=True)
    base = unit(unit(rng.standard_normal((12_000, 64))) * math.sqrt(1 - mean * mean) + mean * np.eye(64)[0])
    step = rng.standard_normal(base.shape)
    step = unit(step - (step * base).sum(axis=1, keepdims=True) * base)
    cosine = rng.uniform(0.98, 0.985, (len(base), 1))
    near = cosine * base + np.sqrt(1 - cosine**2) * step
    radii = np.linalg.norm(base - base.mean(axis=0), axis=1)
    models = [itq.learn_rotation(base[:8000], 7 + i) for i in range(2)]
    a, b = itq._signs(base, models), itq._signs(near, models)
    most = itq.hamming_bound(128, 0.98, radii)
    assert ((a != b).sum(axis=1) <= most).mean() >= 0.999
    assert ((a != np.roll(a, 1, axis=0)).sum(axis=1) <= most).mean() <= 0.01
    assert itq.hamming_bound(128, 1.0) == 0 and itq.hamming_bound(128, 0.98, np.zeros(3)) == 128


def test_have_neighbours():
    rng = np.random.default_rng(4)
    codes = rng.integers(0, 1 << 8, (700, 2), dtype=np.uint64)
    d = np.bitwise_count(codes[:, None] ^ codes[None, :]).sum(axis=2)
    for most in (0, 1, 3):
        every = np.arange(len(codes))
        assert (itq.have_neighbours(codes, every, every, most) == ((d <= most).sum(axis=1) > 1)).all()
        left, right = every[::3], np.setdiff1d(every, every[::3])
        want = np.zeros(len(codes), dtype=bool)
        want[left], want[right] = (d[np.ix_(left, right)] <= most).any(axis=1), (d[np.ix_(left, right)] <= most).any(axis=0)
        assert (itq.have_neighbours(codes, left, right, most) == want).all()


def test_embeddings_empty(spark):
    df = spark.createDataFrame([(1, None, None)], "vec_id long, embedding array<float>, label int")
    assert [tuple(r) for r in itq.near_duplicates(df).collect()] == [(1, 0, 1, True)]
    assert itq.near_duplicates(df.where("false")).count() == 0


# 3 ---------------------------------------------------------------------------------------------
def test_best_fit():
    rng = np.random.default_rng(3)
    for size in (1, 7, 64, 100):
        lengths = rng.integers(1, size + 1, 300)
        window, offset = packing.best_fit_decreasing(lengths, size)
        left, used = [], {}
        for i in np.argsort(-lengths, kind="stable"):  # the same rule with a linear search
            fits = [c for c in left if c >= lengths[i]]
            left.append((min(fits) if fits else size) - lengths[i])
            if fits:
                left.remove(min(fits))
        fill = np.bincount(window, weights=lengths)
        assert sorted(size - fill) == sorted(left)
        for w in range(window.max() + 1):
            at = np.argsort(offset[window == w])
            assert (np.cumsum(lengths[window == w][at]) - lengths[window == w][at] == offset[window == w][at]).all()


def test_packing(spark, sf, odd):
    from tokenizers import Tokenizer

    df = docs(spark, sf, odd)
    rows = packing.pack(packing.token_pieces(df, 512, WORD, 2), 512, group=40).collect()
    t = Tokenizer.from_file(WORD)
    want = []
    for i, text in texts(df):
        ids = np.array(t.encode(text or "", add_special_tokens=False).ids + [2], dtype="<u4")
        want += [(i, s, len(ids[s : s + 512]), zlib.crc32(ids[s : s + 512].tobytes()), len(ids)) for s in range(0, len(ids), 512)]
    assert sorted((r["_id"], r["start"], r["length"], r["ids_crc32"], r["doc_tokens"]) for r in rows) == sorted(want)
    by = {}
    for r in rows:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for parts in by.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 512
    assert sorted(by) == list(range(len(by)))


def test_packing_empty(none):
    assert packing.pack(packing.token_pieces(none, 512, WORD, 2), 512).count() == 0


# 4 ---------------------------------------------------------------------------------------------
def slow_print(text):
    import xxhash

    words = [w for w in "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "").replace("\n", " ").replace("\t", " ").replace("\r", " ").replace("\v", " ").replace("\f", " ").split(" ") if w]
    if not words:
        return 0
    h = [xxhash.xxh64_intdigest(" ".join(words[i : i + 4]).encode(), 42) for i in range(max(1, len(words) - 3))]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def slow_components(prints, bits):
    ids, p = [i for i, _ in prints], np.array([x for _, x in prints], dtype=np.uint64)
    up = list(range(len(p)))

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for i in range(len(p)):
        for j in np.flatnonzero(np.bitwise_count(p ^ p[i]) <= bits).tolist():
            up[max(find(i), find(j))] = min(find(i), find(j))
    least = {}
    for i in range(len(p)):
        least[find(i)] = min(least.get(find(i), ids[i]), ids[i])
    return sorted((ids[i], f"{prints[i][1]:016x}", least[find(i)]) for i in range(len(p)))


def test_simhash(spark, sf, odd):
    df = docs(spark, sf, odd)
    want = slow_components([(i, slow_print(t)) for i, t in texts(df)], 4)
    for shard in (16, 2048):
        assert sorted(map(tuple, simhash.near_duplicates(df, shard=shard).collect())) == want


def test_simhash_cuts_large_shards(spark, sf, odd):
    """Shards over a block are compared block by block, with the same result."""
    df = docs(spark, sf, odd)
    want = slow_components([(i, slow_print(t)) for i, t in texts(df)], 4)
    for shard, block in ((1 << 20, 37), (64, 16), (1 << 20, 1)):
        got = simhash.near_duplicates(df if block > 1 else odd, shard=shard, block=block)
        assert sorted(map(tuple, got.collect())) == (want if block > 1 else slow_components([(i, slow_print(t)) for i, t in texts(odd)], 4))


def test_shard_links_in_tiles(monkeypatch):
    """Narrow tiles, with and without sides, give the links of brute force."""
    rng = np.random.default_rng(9)
    base = rng.integers(0, 1 << 63, 400, dtype=np.uint64)
    points = np.unique(np.concatenate([base, base ^ (np.uint64(1) << rng.integers(0, 64, 400, dtype=np.uint64))]))
    side = rng.integers(0, 2, len(points))
    near = np.bitwise_count(points[:, None] ^ points[None, :]) <= 4
    monkeypatch.setattr(simhash, "TILE", 50)
    for sides in (None, side):
        want = simhash.Forest(len(points))
        want.link(*np.nonzero(near if sides is None else near & (side[:, None] != side[None, :])))
        roots, expected = simhash.shard_links(points, 4, sides), want.roots()
        assert len(set(zip(roots.tolist(), expected.tolist()))) == len(set(expected.tolist())) == len(set(roots.tolist()))


def test_vantage_tree_meets_every_pair():
    rng = np.random.default_rng(5)
    base = rng.integers(0, 1 << 63, 300, dtype=np.uint64)
    points = base.copy()
    for _ in range(6):
        points = np.concatenate([points, base ^ (np.uint64(1) << rng.integers(0, 64, 300, dtype=np.uint64))])
    points = np.unique(points)
    tree = simhash.VantageTree(points, 5)
    leaf, row = tree.deal(points, 4)
    assert (np.bincount(row, minlength=len(points)) >= 1).all()
    from simblock.llm.unionfind import Forest

    whole = Forest(len(points))
    for k in np.unique(leaf):
        at = row[leaf == k]
        root = simhash.shard_links(points[at], 4)
        whole.link(at, at[root])
    want = Forest(len(points))
    i, j = np.nonzero(np.bitwise_count(points[:, None] ^ points[None, :]) <= 4)
    want.link(i, j)
    assert (whole.roots() == want.roots()).all()


def test_simhash_empty_and_keep(none, odd):
    assert simhash.near_duplicates(none).count() == 0
    kept = simhash.keep_one_of_each(odd)
    assert kept.columns == odd.columns
    assert sorted(r["doc_id"] for r in kept.collect()) == [1, 4, 7, 8, 9, 10]


# 5 ---------------------------------------------------------------------------------------------
def test_simhash_keeps_by_row(spark):
    a, b, c = (" ".join(f"{x}{i * 7 % 101}" for i in range(80)) for x in "abc")
    rows = [(1, a), (1, b), (2, a), (2, c), (None, a), (None, "one two three four five six"), (None, "nothing like the other text here"), (5, a), (5, a), (7, "seven"), (7, "seven")]
    kept = simhash.keep_one_of_each(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    want = [(1, a), (1, b), (2, c), rows[5], rows[6], (7, "seven")]
    assert sorted(map(str, map(tuple, kept))) == sorted(map(str, want))
    twins = simhash.keep_one_of_each(spark.createDataFrame([(None, a), (None, a), (3, b)], "doc_id long, text string")).collect()
    assert sorted(str(tuple(r)) for r in twins) == sorted([str((None, a)), str((3, b))])


def test_quotes(spark):
    rows = [
        (1, 0, "user", "Where is the station?\nI am lost."),
        (1, 1, "assistant", "> Where is the  STATION?\n> I am lost.\n\nGo left."),
        (1, 2, "user", ">> Where is the station?\n>> I am lost.\n> Go left.\nThank you, that helped me a lot!"),
        (2, 0, "user", "> Thank you, that helped me a lot!\nGlad to hear."),
        (2, 1, "user", "> never said by anyone here\nno"),
        (3, 0, "user", "> Go left.\nshort passages don't link across"),
        (4, 0, "user", None), (4, 1, None, ""), (None, 1, "user", "> Go left."), (5, None, "user", "x"),
        (6, 0, "user", ">" * 3 + "\n" + "\n".join("> line" for _ in range(5000))), (7, 0, "user", "dup"), (7, 0, "user", "dup"),
    ]
    df = spark.createDataFrame([(*r, "z") for r in rows], "conv_id long, turn long, role string, text string, position string")
    out = {(r["conv_id"], r["turn"]): r for r in quotes.link_quotations(df).collect()}
    assert quotes.link_quotations(df).count() == len(rows)
    assert (out[1, 1]["parent_conv"], out[1, 1]["parent_turn"], out[1, 1]["reply_text"]) == (1, 0, "Go left.")
    assert (out[1, 2]["parent_turn"], out[1, 2]["n_quotes"], out[1, 2]["n_linked"], out[1, 2]["quote_depth"]) == (1, 2, 2, 2)
    assert (out[2, 0]["parent_conv"], out[2, 0]["parent_turn"], out[2, 0]["thread_id"], out[2, 0]["reply_depth"]) == (1, 2, 1, 3)
    assert [out[k]["position"] for k in ((1, 0), (1, 1), (1, 2), (2, 0))] == [0, 1, 2, 3]
    assert out[2, 1]["n_linked"] == 0 and out[2, 1]["thread_id"] == 2 and out[3, 0]["n_linked"] == 0
    assert out[4, 0]["reply_text"] == "" and out[None, 1]["thread_id"] is None and out[6, 0]["n_quotes"] == 1
    assert quotes.link_quotations(df.where("false")).count() == 0


# 6 ---------------------------------------------------------------------------------------------
def test_bpe(spark, sf, odd):
    import tiktoken

    ranks = bpe.read_ranks(RANKS)
    t = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    df = docs(spark, sf, odd)
    got = {r["doc_id"]: r for r in bpe.round_trip(df, RANKS, public_tokenizers.PATTERN).collect()}
    for i, text in texts(df):
        ids = t.encode_ordinary(text or "")
        assert got[i]["n_tokens"] == len(ids)
        assert got[i]["ids_sha256"] == hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest()
        assert got[i]["decoded_sha256"] == hashlib.sha256((text or "").encode()).hexdigest()
    ids = bpe.encode(df, RANKS, public_tokenizers.PATTERN)
    back = {r["doc_id"]: bytes(r["decoded"]) for r in bpe.decode(ids, RANKS, public_tokenizers.PATTERN).collect()}
    assert all(back[i] == (text or "").encode() for i, text in texts(df))
    assert bpe.round_trip(df.where("false"), RANKS, public_tokenizers.PATTERN).count() == 0


def test_caches_are_bounded_by_bytes(monkeypatch):
    """Long unbroken pre-tokens and chunks give the libraries' ids and leave no more than the bound behind."""
    import tiktoken
    from tokenizers import Tokenizer

    from simblock.llm import wordtokens

    rng = np.random.default_rng(2)
    words = ["".join(map(chr, rng.integers(97, 123, n))) for n in (5, 20_000, 7, 30_000, 3, 200_000)]
    given = [*words, " ".join(words[:4]), "short words stay", words[1]]
    t = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=bpe.read_ranks(RANKS), special_tokens={})
    monkeypatch.setattr(bpe, "CACHE_BYTES", 1000)
    monkeypatch.setattr(wordtokens, "CACHE_BYTES", 1000)
    own = bpe.ByteBpe(RANKS, public_tokenizers.PATTERN)
    for text in given:
        assert own.encode(text).tolist() == t.encode_ordinary(text)
        assert own.held <= 1000 and sum(map(len, own.known)) <= 1000
    chunks, whole = wordtokens.ChunkEncoder(WORD), Tokenizer.from_file(WORD)
    for texts_ in (given, given[:3], given[-2:]):
        got = [ids.tolist() for ids in chunks.documents(texts_, 2)]
        assert got == [whole.encode(x, add_special_tokens=False).ids + [2] for x in texts_]
        assert chunks.held <= 1000 and sum(map(len, chunks.known)) <= 1000


def test_perfect_hash():
    keys = list(bpe.read_ranks(RANKS))
    h = bpe.PerfectHash(keys)
    assert (h.lookup(keys) == np.arange(len(keys))).all() and sorted(h.slot_of) == list(range(len(keys)))


# 7 ---------------------------------------------------------------------------------------------
def test_boilerplate(spark, odd, none):
    rows = [(i, f"menu\nown line {i}\n menu \n\nend", "h1" if i < 8 else None, "x") for i in range(16)] + [(20, None, "h1", "x"), (21, "menu\nmenu", "h2", "x"), (22, "", "h1", "x")]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string, _lines string")
    out = {r["doc_id"]: r for r in boilerplate.drop_boilerplate(df, ratio=0.5, min_pages=5).collect()}
    assert len(out) == len(rows) and out[3]["text"] == "own line 3\n" and out[12]["text"] == "own line 12\n"
    assert out[20]["text"] is None and out[21]["text"] == "menu\nmenu" and out[22]["text"] == ""
    assert (out[3]["_lines_seen"]["n_lines"], out[3]["_lines_seen"]["n_dropped"]) == (5, 3)
    assert boilerplate.drop_boilerplate(none).count() == 0
    assert boilerplate.drop_boilerplate(odd).count() == odd.count()


# 8 ---------------------------------------------------------------------------------------------
def test_quality(spark, sf, odd, none):
    import re

    df = docs(spark, sf, odd)
    got = {r["_id"]: r for r in compression.judge(df).collect()}
    for i, text in texts(df):
        text = text or ""
        words = re.findall(r"[^\x20\x09-\x0D]+", text)
        windows = [tuple(words[k : k + 3]) for k in range(len(words) - 2)]
        often = {w for w, n in __import__("collections").Counter(windows).items() if n > 1}
        inside = {k + d for k, w in enumerate(windows) if w in often for d in range(3)}
        lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        r = got[i]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == (len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text)), len(lines) - len(set(lines)), len(inside))
        assert r["base_failed"] == (len(words) < 50 or 100 * len(inside) > 50 * len(words))
        assert not (r["kept"] and r["base_failed"])
    assert compression.judge(none).count() == 0
    kept = compression.keep_good(odd)
    assert kept.columns == odd.columns and {r["doc_id"] for r in kept.collect()} == {i for i in range(1, 11) if got[i]["kept"]}


def test_bands():
    from zstandard import ZstdCompressor

    compress, bands = ZstdCompressor(level=3).compress, compression.Bands()
    prose = " ".join(str(i * 7919 % 10007) for i in range(2000)).encode()
    noise = np.random.default_rng(1).integers(0, 256, 8000, dtype=np.uint8).tobytes()
    for raw, bad in ((prose, False), (b"again and again " * 500, True), (noise, True), (b"short short short", False)):
        whole, _, _, share = compression.ratios(raw, bands, compress)
        assert compression.outside(len(raw), whole, share, bands) == bad


def test_bands_reject_noise_stored_as_text():
    from zstandard import ZstdCompressor

    compress, bands, rng = ZstdCompressor(level=3).compress, compression.Bands(), np.random.default_rng(8)
    lines = lambda s: "\n".join(s[i : i + 76] for i in range(0, len(s), 76))
    printable = [chr(c) for c in range(33, 127)]
    for size in (1500, 5000, 20_000):
        code = lines(base64.b64encode(rng.bytes(size * 3 // 4)).decode())
        signs = " ".join("".join(rng.choice(printable, 6)) for _ in range(size // 7))
        han = " ".join("".join(map(chr, rng.integers(0x4E00, 0x9000, 4))) for _ in range(size // 13))
        for text in (code, signs, han):
            raw = text.encode()
            whole, _, _, share = compression.ratios(raw, bands, compress)
            assert compression.outside(len(raw), whole, share, bands)


# 9 ---------------------------------------------------------------------------------------------
def test_block_max_is_exact():
    rng = np.random.default_rng(9)
    vectors = []
    for _ in range(700):
        t = rng.choice(30, rng.integers(1, 6), replace=False)
        w = rng.random(len(t))
        vectors.append({int(a): float(b) for a, b in zip(t, w / np.linalg.norm(w))})
    index = toxicity.BlockMaxIndex(vectors, 30, block=16)
    for q in vectors[:60]:
        scores = [(-round(sum(q[t] * v[t] for t in q if t in v), 12), i) for i, v in enumerate(vectors)]
        want = [(i, -s) for s, i in sorted(x for x in scores if x[0] < 0)[:15]]
        got = index.nearest(q, 15)
        assert [s for _, s in got] == pytest.approx([s for _, s in want], abs=1e-9)


def test_block_max_with_long_lists():
    rng = np.random.default_rng(10)
    x = rng.random((3000, 12)) * (rng.random((3000, 12)) < 0.7)
    x[:, 10:] *= rng.random((3000, 2)) < 0.05
    x[:, 0] += 0.01
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    index = toxicity.BlockMaxIndex([{int(t): float(r[t]) for t in np.flatnonzero(r)} for r in x], 12)
    for i, q in enumerate(x[:40]):
        q = q * (np.arange(12) < 10) if i % 2 else q
        got = index.nearest({int(t): float(q[t]) for t in np.flatnonzero(q)}, 15, skip=i)
        score = x @ q
        score[i] = 0
        assert [s for _, s in got] == pytest.approx(sorted(score.tolist(), reverse=True)[:15], abs=1e-9)


def test_toxicity(spark, none):
    rng = np.random.default_rng(2)
    plain = [f"word{i}" for i in range(200)]
    rows, labels = [], []
    for i in range(400):
        bad = i % 8 == 0
        words = list(rng.choice(plain, 30)) + (["slur", "insult"] if bad else [])
        rows.append((i, " ".join(words), "z"))
        if i % 2 == 0:
            labels.append((i, 1, int(bad)))
    rows += [(900, None, "z"), (901, "", "z"), (902, "Slur! INSULT?", "z")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, score string")
    marks = spark.createDataFrame(labels + [(0, 1, 0), (2, 1, None), (None, 1, 1)], "doc_id long, quality int, toxic int")
    got = {r["doc_id"]: r for r in toxicity.score_documents(docs, marks).collect()}
    assert all((got[i]["score"] >= 0.5) == (i % 8 == 0) for i in range(400))
    assert got[902]["score"] >= 0.5 and got[902]["evidence"][0]["label"] == 1 and got[900]["score"] < 0.5 and 0 <= got[901]["score"] <= 1
    kept = toxicity.keep_clean(docs, marks)
    assert kept.columns == docs.columns and {r["doc_id"] for r in kept.collect()} == {i for i in got if got[i]["score"] < 0.5}
    assert toxicity.score_documents(none.select("doc_id", "text"), marks).count() == 0
    assert {r["score"] for r in toxicity.score_documents(docs, marks.where("false")).collect()} == {0.0}


def test_toxicity_examples_are_all_labelled_rows(spark):
    rng = np.random.default_rng(12)
    bag = [f"w{''.join(chr(97 + int(c)) for c in str(i))}" for i in range(120)]
    rows = [(i, " ".join(rng.choice(bag, 12)) + (" vile" if i % 5 == 0 else "")) for i in range(300)]
    marks = spark.createDataFrame([(i, int(i % 5 == 0)) for i in range(200)], "doc_id long, toxic int")
    df = spark.createDataFrame(rows, "doc_id long, text string")
    counts = {i: toxicity.word_counts(t) for i, t in rows}
    seen: dict = {}
    for c in counts.values():
        for w in c:
            seen[w] = seen.get(w, 0) + 1

    def unit(c):
        v = {w: (1 + math.log(n)) * (math.log(301 / (1 + seen[w])) + 1) for w, n in c.items()}
        return {w: x / math.sqrt(sum(y * y for y in v.values())) for w, x in v.items()}

    vectors = {i: unit(c) for i, c in counts.items()}
    got = toxicity.score_documents(df, marks, train=F.lit(True), lean=None).collect()
    assert {e["label"] for r in got for e in r["evidence"]} == {0, 1}
    for r in got[::7]:
        q = vectors[r["doc_id"]]
        want = sorted((sum(x * vectors[i].get(w, 0) for w, x in q.items()) for i in range(200)), reverse=True)[:15]
        assert [e["similarity"] for e in r["evidence"]] == pytest.approx([x for x in want if x > 0], abs=1e-9)


def test_toxicity_terms_are_selected_by_chance():
    pairs = [(n, t) for n in range(2, 30) for t in range(0, min(n, 12) + 1)]
    table = toxicity.pd.DataFrame([(n, t, 1 + n * t % 7) for n, t in pairs], columns=["n", "t", "many"])
    p = {(n, t): sum(math.comb(20, i) * math.comb(180, n - i) for i in range(t, min(n, 20) + 1)) / math.comb(200, n) for n, t in pairs}
    assert toxicity.chance(table["t"].to_numpy(), table["n"].to_numpy(), 20, 200) == pytest.approx([p[x] for x in pairs], rel=1e-6)
    total, good = table["many"].sum(), 0.0
    for x in sorted(p.values()):
        good = x if x <= 0.1 * sum(m for (n, t, m) in table.itertuples(index=False) if p[n, t] <= x) / total else good
    least = toxicity.least_toxic(table, 20, 200, 0.1)
    assert {x for x in pairs if x[0] in least and x[1] >= least[x[0]]} == {(n, t) for n, t in pairs if p[n, t] <= good and t >= toxicity.LIFT * n / 10}
    assert toxicity.least_toxic(table, 0, 200, 0.1) == {} and toxicity.least_toxic(table[:0], 20, 200, 0.1) == {}


def test_toxicity_in_the_selected_space(spark):
    """Neighbours and similarities of every text against vectors over the selected words and beginnings."""
    rng = np.random.default_rng(13)
    tail = lambda: "".join(rng.choice(list("abcdef"), 4))
    rows = [(i, " ".join([*("plain" + tail() for _ in range(8)), *(("grausam" + tail()) for _ in range(3 if i % 4 == 0 else 0)), "ende"])) for i in range(400)]
    marks = spark.createDataFrame([(i, int(i % 4 == 0)) for i in range(300)], "doc_id long, toxic int")
    df = spark.createDataFrame([*rows, (500, None), (501, "ende")], "doc_id long, text string")
    got = {r["doc_id"]: r for r in toxicity.score_documents(df, marks, train=F.lit(True)).collect()}
    scorer = toxicity.fit(df, marks, train=F.lit(True))
    names = [t for t, live in zip(scorer.space.joined.split(), scorer.live) if live]
    assert {"grau*", "grausam*"} <= set(names) and not {"ende", "plai*", "plain*"} & set(names)
    counts = {i: {t: n for t in names if (n := sum((w == t) or (t[-1] == "*" and len(w) > len(t) - 1 >= 4 and w.startswith(t[:-1])) for w in (x or "").split()))} for i, x in [*rows, (500, None), (501, "ende")]}
    seen = {t: sum(t in c for c in counts.values()) for t in names}
    weights = {i: {t: (1 + math.log(n)) * (math.log(403 / (1 + seen[t])) + 1) for t, n in c.items()} for i, c in counts.items()}
    vectors = {i: {t: x / math.sqrt(sum(y * y for y in v.values())) for t, x in v.items()} for i, v in weights.items()}
    for i in list(got)[::9]:
        want = sorted((sum(x * vectors[j].get(t, 0) for t, x in vectors[i].items()) for j in range(300)), reverse=True)[:15]
        assert [e["similarity"] for e in got[i]["evidence"]] == pytest.approx([x for x in want if x > 0], abs=1e-9)
    assert all((r["score"] >= 0.5) == (i % 4 == 0 and i < 400) for i, r in got.items())
    assert got[500]["evidence"] == got[501]["evidence"] == [] and got[500]["score"] == got[501]["score"]


def test_toxicity_caught_by_language(spark, sf):
    """Held-out toxic documents caught and clean ones left alone, in each language of many labels."""
    sf = sf.replace("0.001", "0.1")
    scored = queries.op9_toxic_neighbours(spark, sf).where("held_out").select("doc_id", "predicted")
    known = spark.read.parquet(f"{sf}/labels.parquet").join(spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "lang"), "doc_id")
    rows = scored.join(known, "doc_id").groupBy("lang", "toxic").agg(F.count("*").alias("n"), F.avg("predicted").alias("said")).collect()
    found = {(r["lang"], r["toxic"]): r for r in rows}
    for lang in ("en", "de", "fr", "es"):
        assert found[lang, 0]["said"] <= 0.03
        if found[lang, 1]["n"] >= 10:
            assert found[lang, 1]["said"] >= 0.7
    caught = sum(r["said"] * r["n"] for x, r in found.items() if x[1]) / sum(r["n"] for x, r in found.items() if x[1])
    assert caught >= 0.85


def test_toxicity_held_out(spark, sf):
    sf = sf.replace("0.001", "0.01")
    scored = queries.op9_toxic_neighbours(spark, sf)
    rows = scored.join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").where("held_out").collect()
    y, p = np.array([r["toxic"] for r in rows]), np.array([r["score"] for r in rows])
    wins = (p[y == 1][:, None] > p[y == 0]).mean() + 0.5 * (p[y == 1][:, None] == p[y == 0]).mean()
    assert wins > 0.75 and (p[y == 0] < 0.5).mean() > 0.97


# 10 --------------------------------------------------------------------------------------------
def slow_warc(rows):
    first, out = {}, []
    for i, html in rows:
        d = hashlib.sha1((html or "").encode()).digest()
        first[d] = min(first.get(d, i), i)
    for i, html in rows:
        raw = (html or "").encode()
        d = hashlib.sha1(raw).digest()
        out.append((i, len(raw), base64.b32encode(d).decode(), "response" if first[d] == i else "revisit", None if first[d] == i else first[d]))
    return sorted(out)


def test_warc(spark, sf):
    odd = [(9001, None), (9002, ""), (9003, "a\r\n\r\nWARC/1.0\r\nWARC-Type: response\r\n\r\nb"), (9004, "é🎉\r\n\r\n"), (9005, "x" * 300_000), (9006, "x" * 300_000)]
    given = [(r["page_id"], r["html"]) for r in spark.read.parquet(f"{sf}/pages.parquet").collect()]
    df = spark.createDataFrame([(i, "http://a/\r\nb" if i % 2 else None, h, "z") for i, h in given + odd], "page_id long, url string, html string, type string")
    assert sorted(map(tuple, warc.round_trip(df).collect())) == slow_warc(given + odd)
    assert warc.round_trip(df.where("false")).count() == 0
    twice = spark.createDataFrame([(1, "u", "same"), (1, "u", "same"), (2, "u", "same")], "page_id long, url string, html string")
    assert sorted(r["record_type"] for r in warc.round_trip(twice).collect()) == ["response", "revisit", "revisit"]


def test_warc_foreign_archive(spark, tmp_path):
    def rec(kind, name, block, *more):
        return "\r\n".join(["WARC/1.1", f"WARC-Type: {kind}", f"warc-record-id: <{name}>", *more, f"Content-Length: {len(block)}", "", ""]).encode() + block + b"\r\n\r\n"

    http = b"HTTP/1.1 200 OK\r\nX: y\r\n\r\nbody"
    records = [rec("warcinfo", "w", b"software: x\r\n"), rec("response", "r", http, "Content-Type: application/http; msgtype=response"), rec("request", "q", b"GET / HTTP/1.1\r\n\r\n", "WARC-Concurrent-To: <r>"), rec("request", "q2", b"GET / HTTP/1.1\r\n\r\n", "WARC-Concurrent-To: <none>")]
    (tmp_path / "a.warc.gz").write_bytes(b"".join(gzip.compress(r) for r in records))
    (tmp_path / "b.warc").write_bytes(records[1].replace(b"<r>", b"<r2>"))
    out = {r["record_id"]: r for r in warc.assemble(warc.read_archives(spark, str(tmp_path))).collect()}
    assert set(out) == {"<r>", "<r2>"} and bytes(out["<r>"]["response"]["payload"]) == b"body"
    assert out["<r>"]["request"]["record_id"] == "<q>" and out["<r2>"]["request"] is None


# pipeline --------------------------------------------------------------------------------------
def test_pipeline_stages(spark, sf, odd):
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    held = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        held = corpus_pipeline.cut(stage(spark, held, sf), name)
        assert held.columns == docs.columns
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    toxic = {r["doc_id"] for r in toxicity.score_documents(docs, labels).where("score >= 0.5").collect()}
    left = [(i, t) for i, t in texts(docs) if i not in toxic]
    good = {r["_id"] for r in compression.judge(docs).where("kept").collect()}
    left = docs.where(F.col("doc_id").isin([i for i, _ in left if i in good]))
    lined = boilerplate.drop_boilerplate(left, "source", "text", 0.05, 5)
    groups = slow_components([(i, slow_print(t)) for i, t in texts(lined)], 4)
    assert sorted(r["doc_id"] for r in held.collect()) == sorted(i for i, _, c in groups if i == c)
    pieces = corpus_pipeline.run(spark, sf).collect()
    assert {r["doc_id"] for r in pieces} == {i for i, _, c in groups if i == c}
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, odd.select(docs.columns), sf).count() >= 0
        assert stage(spark, odd.select(docs.columns).where("false"), sf).count() == 0
