"""SQL of the same results for DuckDB: brute force over all pairs that share a token."""

from __future__ import annotations

ITEMS = "SELECT item_id AS rec_id, coalesce(text, '') AS text FROM benchmark"
DOCS = "SELECT doc_id AS rec_id, coalesce(text, '') AS text FROM documents"
EVEN, ODD = DOCS + " WHERE doc_id % 2 = 0", DOCS + " WHERE doc_id % 2 = 1"
PAGES = "SELECT page_id AS rec_id, trim(regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '\\s+', ' ', 'g')) AS text FROM pages"
NAMES = "SELECT c_custkey AS rec_id, c_name AS text FROM customer WHERE c_custkey <= 300"

TOKENS = {
    "word": r"list_filter(regexp_split_to_array(lower(text), '[^\p{L}\p{N}]+'), lambda t: t <> '')",
}


def terms(src: str, tokenizer: str = "word") -> str:
    if tokenizer == "trigram":
        # characters are zipped with the next two, as substrings of a long text take linear time each
        src = rf"SELECT rec_id, string_split(c, '') AS x, c FROM (SELECT rec_id, trim(regexp_replace(lower(text), '\s+', ' ', 'g')) AS c FROM ({src}))"
        toks = "CASE WHEN len(c) = 0 THEN [] WHEN len(x) <= 3 THEN [c] ELSE list_filter(list_transform(list_zip(x, x[2:], x[3:]), lambda z: z[1] || z[2] || z[3]), lambda t: t IS NOT NULL) END"
    else:
        toks = TOKENS["word"]
    return f"SELECT rec_id, token, count(*) AS tf FROM (SELECT rec_id, unnest({toks}) AS token FROM ({src})) GROUP BY rec_id, token"


def sets(a: str, b: str | None, tokenizer: str, weighting: str, measure: str) -> str:
    """CTEs wa, wb(rec_id, token, df, w, total) without the leading WITH."""
    both = "SELECT token FROM ta" + ("" if b is None else " UNION ALL SELECT token FROM tb")
    n = f"(SELECT count(*) FROM ({a}))" + ("" if b is None else f" + (SELECT count(*) FROM ({b}))")
    w = "1.0::DOUBLE" if weighting == "binary" else "tf * ln(1 + (SELECT n FROM nn) / df)"
    norm = "w / sqrt(sum(w * w) OVER (PARTITION BY rec_id))" if measure == "cosine" else "w"
    x = "w * w" if measure == "cosine" else "w"
    side = lambda s: f"w{s} AS (SELECT *, sum({x}) OVER (PARTITION BY rec_id) AS total FROM (SELECT rec_id, token, df, {norm} AS w FROM (SELECT rec_id, token, df, {w} AS w FROM t{s} JOIN dfs USING (token))))"
    out = [f"ta AS ({terms(a, tokenizer)})"]
    if b is not None:
        out.append(f"tb AS ({terms(b, tokenizer)})")
    out += [f"dfs AS (SELECT token, count(*) AS df FROM ({both}) GROUP BY token)", f"nn AS (SELECT CAST({n} AS DOUBLE) AS n)", side("a"), side("b") if b is not None else "wb AS (SELECT * FROM wa)"]
    return ", ".join(out)


def pairs(a: str, b: str | None, tokenizer: str = "word", weighting: str = "tfidf", measure: str = "jaccard") -> str:
    """CTEs that end in ``pairs(a_id, b_id, sim)`` over all pairs that share a token."""
    add = "a.w * b.w" if measure == "cosine" else "least(a.w, b.w)"
    value = {"jaccard": "i / (x + y - i)", "dice": "2 * i / (x + y)"}.get(measure, "i")
    other = " AND a.rec_id <> b.rec_id" if b is None else ""
    return f"""{sets(a, b, tokenizer, weighting, measure)},
met AS (SELECT a.rec_id AS a_id, b.rec_id AS b_id, sum({add}) AS i, any_value(a.total) AS x, any_value(b.total) AS y
  FROM wa a JOIN wb b ON a.token = b.token{other} GROUP BY a.rec_id, b.rec_id),
pairs AS (SELECT a_id, b_id, {value} AS sim FROM met)"""


def conditions(src: str, tau: float, tau_r: float, k: int | None) -> str:
    """A query of the rows of ``src`` that meet the three conditions."""
    k_test = "" if k is None else f" WHERE n <= {k}"
    return f"""SELECT a_id, b_id, sim FROM (
  SELECT *, row_number() OVER (PARTITION BY a_id ORDER BY round(sim, 9) DESC, b_id) AS n FROM (
    SELECT *, max(sim) OVER (PARTITION BY a_id) AS best FROM {src} WHERE sim > 0 AND round(sim, 9) >= {tau})
  WHERE round(sim, 9) >= round(best * {tau_r}, 9)){k_test}"""


def hybrid(a: str, b: str | None, tokenizer: str, weighting: str, measure: str, tau: float = 0.0, tau_r: float = 0.0, k: int | None = None) -> str:
    body = conditions("pairs", tau, tau_r, k)
    if b is None:
        body = f"SELECT least(a_id, b_id) AS a_id, greatest(a_id, b_id) AS b_id, max(sim) AS sim FROM ({body}) GROUP BY ALL"
    return f"WITH {pairs(a, b, tokenizer, weighting, measure)} SELECT a_id, b_id, round(sim, 6) AS sim FROM ({body})"


def running(measure: str, side: str = "a") -> str:
    """A query of (rec_id, token, df, w, total, pre, suf) with sums in the global order."""
    x = "w * w" if measure == "cosine" else "w"
    return f"""SELECT *, coalesce(sum({x}) OVER (PARTITION BY rec_id ORDER BY df, token ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS pre,
  sum({x}) OVER (PARTITION BY rec_id ORDER BY df, token ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS suf FROM w{side}"""


def ranked(a: str, b: str | None, measure: str = "jaccard") -> str:
    """CTEs (binary words) that end in ``log(a_id, b_id, rank, sim, suffix)``."""
    other = " WHERE b.rec_id <> w.rec_id" if b is None else ""
    return f"""{pairs(a, b, 'word', 'binary', measure)},
ra AS ({running(measure, 'a')}), rb AS ({running(measure, 'b')}),
post AS (SELECT *, CASE WHEN pre * count(*) OVER (PARTITION BY token) >= sum(pre) OVER (PARTITION BY token) THEN 1 ELSE 0 END AS half FROM rb),
lists AS (SELECT *, row_number() OVER (PARTITION BY token, half ORDER BY suf, rec_id) AS list_pos, count(*) OVER (PARTITION BY token, half) AS list_len FROM post),
lens AS (SELECT token, half, max(list_len) AS n FROM lists GROUP BY token, half),
walk AS (SELECT ra.rec_id, ra.token, ra.df, ra.suf, lens.half, n, coalesce(sum(n) OVER (PARTITION BY rec_id ORDER BY ra.df, ra.token, lens.half ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS base FROM ra JOIN lens ON lens.token = ra.token),
firsts AS (SELECT w.rec_id AS a_id, b.rec_id AS b_id, arg_min(w.base + b.list_pos, (w.df, w.token)) AS rank, arg_min(w.suf, (w.df, w.token)) AS suffix
  FROM walk w JOIN lists b ON b.token = w.token AND b.half = w.half{other} GROUP BY w.rec_id, b.rec_id),
log AS (SELECT a_id, b_id, CAST(rank AS BIGINT) AS rank, sim, suffix FROM firsts JOIN pairs USING (a_id, b_id))"""
