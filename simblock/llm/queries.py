"""The queries over whole tables that apply this package's operators, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import boilerplate, bpe, compression, hilbert, itq, packing, quotes, simhash, toxicity, warc

SHARDS = 24
SEQUENCE = 4096
END_ID = 2


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_hilbert_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    placed = hilbert.shard_documents(_table(spark, sf_dir, "documents"), SHARDS, ["lang", "source", "n_chars"])
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "hilbert")


def op2_itq_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return itq.near_duplicates(_table(spark, sf_dir, "embeddings"), 0.98)


def op3_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    pieces = packing.token_pieces(_table(spark, sf_dir, "documents"), SEQUENCE, tokenizer_path("word_bpe_49k.json"), END_ID)
    return packing.pack(pieces, SEQUENCE).withColumnRenamed("_id", "doc_id")


def op4_simhash_vantage(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(_table(spark, sf_dir, "documents"), bits=4, width=4)


def op5_quotation_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    linked = quotes.link_quotations(_table(spark, sf_dir, "conversations"))
    return linked.withColumn("reply_md5", F.md5(F.encode("reply_text", "UTF-8"))).drop("reply_text")


def op6_two_tier_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return bpe.round_trip(_table(spark, sf_dir, "documents"), tokenizer_path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)


def op7_site_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = boilerplate.drop_boilerplate(_table(spark, sf_dir, "documents"), "source", "text", 0.05, 5)
    return out.select("doc_id", F.col("_lines_seen.n_lines").alias("n_lines"), F.col("_lines_seen.n_dropped").alias("n_dropped"), F.md5(F.encode("text", "UTF-8")).alias("text_md5"))


def op8_compression_bands(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = compression.judge(_table(spark, sf_dir, "documents"))
    return out.withColumnRenamed("_id", "doc_id")


def op9_toxic_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = toxicity.score_documents(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))
    return scored.select("doc_id", toxicity.held_out("doc_id").alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), "evidence")


def op10_warc_transactions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.round_trip(_table(spark, sf_dir, "pages"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        op1_hilbert_sharding, op2_itq_near_duplicates, op3_best_fit_packing, op4_simhash_vantage, op5_quotation_links,
        op6_two_tier_bpe, op7_site_line_dedup, op8_compression_bands, op9_toxic_neighbours, op10_warc_transactions, pipeline,
    )
}

_OP2 = """
WITH RECURSIVE v AS (
  SELECT vec_id, label, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings
), ok AS (
  SELECT vec_id, label, e FROM v
  WHERE label IS NOT NULL AND e IS NOT NULL AND len(list_filter(e, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0
    AND list_sum(list_transform(e, lambda x: abs(x))) > 0
), links AS (
  SELECT a.vec_id AS a, b.vec_id AS b FROM ok a JOIN ok b
  ON a.label = b.label AND a.vec_id <> b.vec_id AND len(a.e) = len(b.e) AND list_cosine_similarity(a.e, b.e) >= 0.98
), reach(id, root) AS (
  SELECT vec_id, vec_id FROM v
  UNION
  SELECT l.b, r.root FROM reach r JOIN links l ON l.a = r.id
), roots AS (SELECT id, min(root) AS component_id FROM reach GROUP BY id),
n AS (SELECT a, count(*) AS n FROM links GROUP BY a)
SELECT v.vec_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_links, component_id, component_id = v.vec_id AS kept
FROM v JOIN roots ON roots.id = v.vec_id LEFT JOIN n ON n.a = v.vec_id
"""

_OP5 = r"""
WITH RECURSIVE lines AS (
  SELECT conv_id, turn, role, generate_subscripts(l, 1) AS i, unnest(l) AS line
  FROM (SELECT conv_id, turn, role, string_split(coalesce(text, ''), chr(10)) AS l FROM conversations)
), leveled AS (
  SELECT *, len(regexp_replace(regexp_extract(line, '^[ \t]*(>[ \t]*)+'), '[ \t]', '', 'g')) AS lvl,
         regexp_replace(line, '^[ \t]*(>[ \t]*)+', '') AS body FROM lines
), marked AS (
  SELECT *, CASE WHEN lag(lvl) OVER w IS NULL OR lag(lvl) OVER w <> lvl
                   OR (lvl = 0 AND (trim(line) = '' OR trim(lag(line) OVER w) = '')) THEN 1 ELSE 0 END AS fresh
  FROM leveled WINDOW w AS (PARTITION BY conv_id, turn ORDER BY i)
), runs AS (
  SELECT *, sum(fresh) OVER (PARTITION BY conv_id, turn ORDER BY i) AS run FROM marked
), passages0 AS (
  SELECT conv_id, turn, run, lvl, trim(regexp_replace(lower(string_agg(body, chr(10) ORDER BY i)), '\s+', ' ', 'g')) AS p
  FROM runs GROUP BY ALL
), own AS (
  SELECT conv_id, turn, any_value(role) AS role, max(lvl) AS depth,
         regexp_replace(coalesce(string_agg(CASE WHEN lvl = 0 THEN line END, chr(10) ORDER BY i), ''), '^\s+|\s+$', '', 'g') AS reply
  FROM runs GROUP BY conv_id, turn
), units AS (
  SELECT conv_id, turn, p AS u FROM passages0 WHERE lvl = 0
  UNION SELECT conv_id, turn, trim(regexp_replace(lower(line), '\s+', ' ', 'g')) FROM leveled WHERE lvl = 0
  UNION SELECT conv_id, turn, trim(regexp_replace(lower(reply), '\s+', ' ', 'g')) FROM own
), near AS (SELECT u, conv_id, min(turn) AS t FROM units WHERE u <> '' GROUP BY u, conv_id),
far AS (SELECT u, min((conv_id, t)) AS f FROM near GROUP BY u),
quoted AS (
  SELECT p.conv_id, p.turn, run, lvl,
    CASE WHEN n.t < p.turn THEN (p.conv_id, n.t)
         WHEN f.f[1] < p.conv_id AND len(p.p) >= 20 THEN f.f END AS target
  FROM passages0 p LEFT JOIN near n ON n.u = p.p AND n.conv_id = p.conv_id LEFT JOIN far f ON f.u = p.p
  WHERE lvl > 0 AND p.p <> ''
), told AS (
  SELECT conv_id, turn, count(*) AS nq, count(target) AS nl,
         arg_min(target, run) FILTER (WHERE lvl = 1 AND target IS NOT NULL) AS parent
  FROM quoted GROUP BY conv_id, turn
), up(conv_id, turn, rc, rt, hops) AS (
  SELECT conv_id, turn, conv_id, turn, 0 FROM own
  UNION ALL
  SELECT u.conv_id, u.turn, t.parent[1], t.parent[2], u.hops + 1
  FROM up u JOIN told t ON t.conv_id = u.rc AND t.turn = u.rt AND t.parent IS NOT NULL
), roots AS (SELECT conv_id, turn, arg_max(rc, hops) AS thread_id, max(hops) AS hops FROM up GROUP BY conv_id, turn)
SELECT o.conv_id, o.turn, o.role, CAST(o.depth AS BIGINT) AS quote_depth, CAST(coalesce(nq, 0) AS BIGINT) AS n_quotes,
  CAST(coalesce(nl, 0) AS BIGINT) AS n_linked, CAST(t.parent[1] AS BIGINT) AS parent_conv, CAST(t.parent[2] AS BIGINT) AS parent_turn,
  r.thread_id, CAST(r.hops AS BIGINT) AS reply_depth,
  row_number() OVER (PARTITION BY r.thread_id ORDER BY o.conv_id, o.turn) - 1 AS position, md5(o.reply) AS reply_md5
FROM own o LEFT JOIN told t USING (conv_id, turn) LEFT JOIN roots r USING (conv_id, turn)
"""

_OP7 = """
WITH lines AS (
  SELECT doc_id, coalesce(source, chr(0)) AS host, generate_subscripts(l, 1) AS i, unnest(l) AS line
  FROM (SELECT doc_id, source, string_split(text, chr(10)) AS l FROM documents WHERE text IS NOT NULL)
), totals AS (SELECT coalesce(source, chr(0)) AS host, count(*) AS pages FROM documents GROUP BY 1),
often AS (
  SELECT host, trim(line) AS line FROM lines JOIN totals USING (host) WHERE trim(line) <> ''
  GROUP BY host, trim(line), pages HAVING count(DISTINCT doc_id) >= 5 AND count(DISTINCT doc_id) > pages * CAST(0.05 AS DOUBLE)
), kept AS (
  SELECT l.doc_id, count(*) AS n_lines, count(o.line) AS n_dropped,
         coalesce(string_agg(CASE WHEN o.line IS NULL THEN l.line END, chr(10) ORDER BY i), '') AS text
  FROM lines l LEFT JOIN often o ON o.host = l.host AND o.line = trim(l.line) GROUP BY l.doc_id
)
SELECT d.doc_id, CAST(coalesce(n_lines, 0) AS BIGINT) AS n_lines, CAST(coalesce(n_dropped, 0) AS BIGINT) AS n_dropped, md5(k.text) AS text_md5
FROM documents d LEFT JOIN kept k USING (doc_id)
"""

_OP10 = """
WITH p AS (SELECT page_id, coalesce(html, '') AS body, sha1(coalesce(html, '')) AS hex FROM pages),
q AS (SELECT *, min(page_id) OVER (PARTITION BY hex) AS first FROM p)
SELECT page_id, CAST(strlen(body) AS BIGINT) AS payload_bytes,
  list_aggregate(list_transform(range(32), lambda k: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
    1 + CAST(((CAST('0x' || substr(hex, 1 + 5 * (k // 4), 5) AS BIGINT) >> (5 * (3 - k % 4))) & 31) AS INT), 1)), 'string_agg', '') AS payload_digest,
  CASE WHEN first = page_id THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN first <> page_id THEN first END AS refers_to
FROM q
"""

ORACLE_SQL: dict[str, str] = {"op2_itq_near_duplicates": _OP2, "op5_quotation_links": _OP5, "op7_site_line_dedup": _OP7, "op10_warc_transactions": _OP10}
