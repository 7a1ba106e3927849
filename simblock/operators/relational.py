"""One query for each relational operator that users of the methods need, with its SQL."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.stages import fresh_path
from ..sources import load, strip_tags, write_bucketed
from ..tokens import words
from .joins import as_of, band, interval

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def op(name: str, sql: str | None):
    def add(f):
        QUERIES[f"op_{name}"] = f
        if sql is not None:
            ORACLE_SQL[f"op_{name}"] = sql
        return f

    return add


def simple(name: str, sql: str, spark_sql: str | None = None):
    """A query that both engines run from SQL text over temporary views."""
    import re

    text = spark_sql or sql
    tables = [t for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations") if re.search(rf"\b{t}\b", text)]

    def run(spark, sf):
        for t in tables:
            load(spark, sf, t).createOrReplaceTempView(t)
        return spark.sql(text)

    op(name, sql)(run)


# sources and sinks -----------------------------------------------------------------------------
simple("scan_parquet", "SELECT doc_id, source FROM documents WHERE n_chars > 2000")


def _round_trip(kind: str):
    def run(spark, sf):
        df = load(spark, sf, "events").select("event_id", "user_id", "event_type", "props")
        path = fresh_path(spark, kind)
        if kind == "text":
            df.select(F.concat_ws("\t", "event_id", "user_id", "event_type", "props").alias("value")).write.text(path)
            parts = F.split("value", "\t")
            return spark.read.text(path).select(parts[0].cast("long").alias("event_id"), parts[1].cast("long").alias("user_id"), parts[2].alias("event_type"), parts[3].alias("props"))
        df.write.format(kind).options(**({"header": "true", "escape": '"'} if kind == "csv" else {})).save(path)
        return spark.read.schema(df.schema).format(kind).options(**({"header": "true", "escape": '"'} if kind == "csv" else {})).load(path)

    op(f"roundtrip_{kind}", "SELECT event_id, user_id, event_type, props FROM events")(run)


for _k in ("csv", "json", "orc", "text", "parquet"):
    _round_trip(_k)


@op("partitioned_write", "SELECT lang, count(*) AS n FROM documents WHERE lang IN ('en', 'de') GROUP BY lang")
def partitioned_write(spark, sf):
    path = fresh_path(spark, "by_lang")
    load(spark, sf, "documents").select("doc_id", "lang").write.partitionBy("lang").parquet(path)
    return spark.read.parquet(path).where(F.col("lang").isin("en", "de")).groupBy("lang").agg(F.count("*").alias("n"))


@op("bucketed_table", "SELECT o_custkey, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders GROUP BY o_custkey")
def bucketed_table(spark, sf):
    write_bucketed(load(spark, sf, "orders"), "simblock_orders", "o_custkey", 8)
    return spark.table("simblock_orders").groupBy("o_custkey").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


# projections and predicates --------------------------------------------------------------------
simple("project_case", "SELECT p_partkey, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'medium' ELSE 'large' END AS size_class FROM part")
simple("null_safe_eq", "SELECT d.doc_id, l.toxic IS NOT DISTINCT FROM NULL AS unlabelled FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
simple("in_list", "SELECT o_orderkey FROM orders WHERE o_orderpriority IN ('1-URGENT', '2-HIGH')")
simple("like", "SELECT doc_id FROM documents WHERE text LIKE '%License%'")
simple("rlike", "SELECT doc_id FROM documents WHERE regexp_matches(text, '[0-9]{4}')", "SELECT doc_id FROM documents WHERE text RLIKE '[0-9]{4}'")
simple("between", "SELECT o_orderkey FROM orders WHERE o_totalprice BETWEEN 1000 AND 5000")
simple("is_null", "SELECT count(*) AS n FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE l.quality IS NULL")
simple("exclude_empty", "SELECT doc_id FROM documents WHERE text IS NOT NULL AND length(text) > 0")


# joins -----------------------------------------------------------------------------------------
_JOINED = "SELECT n_name, count(*) AS n, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name"


def _hinted(hint: str):
    def run(spark, sf):
        l, o, c, n = (load(spark, sf, t) for t in ("lineitem", "orders", "customer", "nation"))
        o = o.hint(hint)
        j = l.join(o, l.l_orderkey == o.o_orderkey).join(c.hint(hint), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey"))
        return j.groupBy("n_name").agg(F.count("*").alias("n"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"))

    return run


op("merge_join", _JOINED)(_hinted("merge"))
op("shuffle_hash_join", _JOINED)(_hinted("shuffle_hash"))


@op("broadcast_join", "SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def broadcast_join(spark, sf):
    """The smaller side goes to every task, whatever its size is held to be."""
    n, r = load(spark, sf, "nation"), load(spark, sf, "region")
    return n.join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey")).select("n_name", "r_name")


for _n, _j in (("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):
    simple(f"{_n}_outer_join", f"SELECT d.doc_id AS a, l.doc_id AS b, l.quality FROM (SELECT doc_id FROM documents WHERE doc_id % 3 = 0) d {_j} JOIN (SELECT doc_id, quality FROM labels WHERE doc_id % 2 = 0) l ON d.doc_id = l.doc_id")
simple("semi_join", "SELECT doc_id FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id AND toxic = 1)")
simple("anti_join", "SELECT doc_id FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)")
simple("cross_join", "SELECT r_name, n_name FROM region CROSS JOIN nation")


@op("theta_join", "SELECT s_suppkey, c_custkey FROM supplier JOIN customer ON abs(s_acctbal - c_acctbal) <= 5")
def theta_join(spark, sf):
    s, c = load(spark, sf, "supplier").select("s_suppkey", "s_acctbal"), load(spark, sf, "customer").select("c_custkey", "c_acctbal")
    return band(s, c, "s_acctbal", "c_acctbal", 5.0).select("s_suppkey", "c_custkey")


@op("range_join", "SELECT a.doc_id AS a_id, b.doc_id AS b_id FROM documents a JOIN documents b ON abs(a.n_chars - b.n_chars) <= 2 AND a.doc_id < b.doc_id")
def range_join(spark, sf):
    d = load(spark, sf, "documents")
    a, b = d.select(F.col("doc_id").alias("a_id"), F.col("n_chars").alias("x")), d.select(F.col("doc_id").alias("b_id"), F.col("n_chars").alias("y"))
    return band(a, b, "x", "y", 2.0).where("a_id < b_id").select("a_id", "b_id")


@op("asof_join", """SELECT event_id, v AS as_of_value FROM (SELECT e.event_id, c.value AS v, row_number() OVER (PARTITION BY e.event_id ORDER BY c.ts DESC, c.value DESC) AS n
 FROM events e LEFT JOIN (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = 'click' GROUP BY user_id, ts) c ON c.user_id = e.user_id AND c.ts <= e.ts) WHERE n = 1""")
def asof_join(spark, sf):
    e = load(spark, sf, "events").select("event_id", "user_id", "ts", "event_type", "value")
    clicks = e.where("event_type = 'click'").groupBy("user_id", "ts").agg(F.max("value").alias("value"))
    return as_of(e.select("event_id", "user_id", "ts"), clicks, "user_id", "ts", "value").select("event_id", "as_of_value")


@op("interval_join", "SELECT a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 10 MINUTE AND a.event_id <> b.event_id")
def interval_join(spark, sf):
    e = load(spark, sf, "events").select("event_id", "user_id", "ts")
    return interval(e, e, "user_id", "ts", 600).where("l.event_id <> r.event_id").select(F.col("l.event_id").alias("a_id"), F.col("r.event_id").alias("b_id"))


# aggregation -----------------------------------------------------------------------------------
simple("group_agg", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(avg(l_discount), 6) AS disc, min(l_tax) AS low, max(l_tax) AS high FROM lineitem GROUP BY l_returnflag, l_linestatus")
simple("distinct_agg", "SELECT source, count(DISTINCT lang) AS langs FROM documents GROUP BY source")
simple("percentile", "SELECT lang, round(quantile_cont(n_chars, 0.5), 4) AS median FROM documents GROUP BY lang", "SELECT lang, round(percentile(n_chars, 0.5), 4) AS median FROM documents GROUP BY lang")
simple("min_by", "SELECT lang, arg_min(doc_id, n_chars * 1000000 + doc_id) AS shortest FROM documents GROUP BY lang", "SELECT lang, min_by(doc_id, n_chars * 1000000 + doc_id) AS shortest FROM documents GROUP BY lang")
simple("grouping_sets", "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
simple("cube", "SELECT lang, source, count(*) AS n FROM documents GROUP BY CUBE (lang, source)")
simple("rollup", "SELECT lang, source, count(*) AS n FROM documents GROUP BY ROLLUP (lang, source)")
simple("having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey HAVING count(*) > 12")
simple("filter_clause_agg", "SELECT source, count(*) FILTER (WHERE lang = 'en') AS en, sum(n_chars) FILTER (WHERE lang = 'de')::BIGINT AS de FROM documents GROUP BY source", "SELECT source, count(*) FILTER (WHERE lang = 'en') AS en, sum(n_chars) FILTER (WHERE lang = 'de') AS de FROM documents GROUP BY source")
simple("stddev", "SELECT lang, round(stddev_samp(n_chars), 4) AS sd FROM documents GROUP BY lang")
simple("bool_agg", "SELECT source, bool_and(n_chars > 10) AS every, bool_or(n_chars > 10000) AS some FROM documents GROUP BY source")


@op("approx_distinct", "SELECT true AS within")
def approx_distinct(spark, sf):
    d = load(spark, sf, "orders").agg(F.approx_count_distinct("o_custkey", 0.02).alias("a"), F.countDistinct("o_custkey").alias("e"))
    return d.select((F.abs(F.col("a") - F.col("e")) <= 0.1 * F.col("e")).alias("within"))


@op("pivot", "SELECT l_returnflag, sum(CASE WHEN l_linestatus = 'F' THEN 1 END)::BIGINT AS F, sum(CASE WHEN l_linestatus = 'O' THEN 1 END)::BIGINT AS O FROM lineitem GROUP BY l_returnflag")
def pivot(spark, sf):
    return load(spark, sf, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count(F.lit(1)))


# windows, sorts, limits ------------------------------------------------------------------------
_W = "OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)"
simple("rank_functions", f"SELECT o_orderkey, CAST(row_number() {_W} AS BIGINT) AS rn, CAST(rank() {_W} AS BIGINT) AS rk, CAST(dense_rank() {_W} AS BIGINT) AS dr FROM orders")
simple("ntile", f"SELECT o_orderkey, CAST(ntile(4) {_W} AS BIGINT) AS bucket FROM orders")
simple("percent_rank", f"SELECT o_orderkey, round(percent_rank() {_W}, 6) AS pr, round(cume_dist() {_W}, 6) AS cd FROM orders")
simple("lag_lead", f"SELECT o_orderkey, lag(o_orderkey) {_W} AS before, lead(o_orderkey, 2) {_W} AS after FROM orders")
simple("first_last", f"SELECT o_orderkey, first_value(o_orderkey) {_W} AS first, last_value(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last, nth_value(o_orderkey, 2) {_W} AS second FROM orders")
simple("running_sum", "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING), 2) AS total FROM orders")
simple("moving_avg", "SELECT o_orderkey, round(avg(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS mean FROM orders")
simple("range_frame", "SELECT doc_id, count(*) OVER (PARTITION BY source ORDER BY n_chars RANGE BETWEEN 100 PRECEDING AND 100 FOLLOWING) AS near FROM documents")
simple("topk_per_group", f"SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS n FROM orders) t WHERE n <= 3")
simple("global_topk", "SELECT l_orderkey, l_linenumber, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber LIMIT 20")
simple("limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 10 OFFSET 25")
simple("sort_nulls", "SELECT d.doc_id, l.quality FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id ORDER BY l.quality DESC NULLS LAST, d.doc_id LIMIT 40")

# set operations --------------------------------------------------------------------------------
_A, _B = "SELECT doc_id % 50 AS x FROM documents", "SELECT doc_id % 70 AS x FROM labels WHERE doc_id % 70 > 10"
for _n, _s in (("union_all", "UNION ALL"), ("union_distinct", "UNION"), ("intersect", "INTERSECT"), ("except", "EXCEPT"), ("intersect_all", "INTERSECT ALL"), ("except_all", "EXCEPT ALL")):
    simple(_n, f"{_A} {_s} {_B}")
simple("distinct", "SELECT DISTINCT lang, source FROM documents")

# scalar functions ------------------------------------------------------------------------------
simple("string_fns", "SELECT doc_id, upper(substr(source, 1, 2)) AS u, reverse(source) AS r, lpad(source, 8, '*') AS p, replace(source, 'src', 'S') AS x, strpos(source, 'c') AS i, concat_ws('-', lang, source) AS c, translate(source, 's', 'z') AS t FROM documents",
       "SELECT doc_id, upper(substr(source, 1, 2)) AS u, reverse(source) AS r, lpad(source, 8, '*') AS p, replace(source, 'src', 'S') AS x, CAST(instr(source, 'c') AS BIGINT) AS i, concat_ws('-', lang, source) AS c, translate(source, 's', 'z') AS t FROM documents")
simple("regex_extract", "SELECT page_id, regexp_extract(url, '^https?://([^/]+)', 1) AS host FROM pages")
simple("hash_fns", "SELECT doc_id, md5(text) AS m, sha256(text) AS s FROM documents", "SELECT doc_id, md5(encode(text, 'UTF-8')) AS m, sha2(encode(text, 'UTF-8'), 256) AS s FROM documents")
simple("levenshtein", "SELECT a.n_name AS x, b.n_name AS y, CAST(levenshtein(a.n_name, b.n_name) AS INT) AS d FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey")
simple("date_fns", "SELECT o_orderkey, CAST(year(o_orderdate) AS INT) AS y, CAST(month(o_orderdate) AS INT) AS m, date_trunc('month', o_orderdate)::TIMESTAMP AS t, CAST(datediff('day', DATE '1992-01-01', o_orderdate::DATE) AS INT) AS d FROM orders",
       "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, date_trunc('month', o_orderdate) AS t, datediff(o_orderdate, DATE '1992-01-01') AS d FROM orders")
simple("math_fns", "SELECT l_orderkey, l_linenumber, round(sqrt(l_extendedprice), 6) AS r, round(ln(l_extendedprice), 6) AS l, CAST(floor(l_quantity / 7) AS BIGINT) AS f, CAST(ceil(l_quantity / 7) AS BIGINT) AS c, greatest(l_tax, l_discount) AS g, least(l_tax, l_discount) AS m FROM lineitem")
simple("array_fns", "SELECT vec_id, CAST(len(embedding) AS INT) AS n, round(list_max(embedding)::DOUBLE, 5) AS top, round(embedding[1]::DOUBLE, 5) AS first FROM embeddings",
       "SELECT vec_id, size(embedding) AS n, round(CAST(array_max(embedding) AS DOUBLE), 5) AS top, round(CAST(embedding[0] AS DOUBLE), 5) AS first FROM embeddings")
simple("higher_order", "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x))), 5) AS norm, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INT) AS positive FROM embeddings",
       "SELECT vec_id, round(sqrt(aggregate(embedding, 0D, (s, x) -> s + CAST(x AS DOUBLE) * x)), 5) AS norm, size(filter(embedding, x -> x > 0)) AS positive FROM embeddings")
simple("explode", "SELECT item_id, unnest(string_split(text, ' ')) AS w FROM benchmark", "SELECT item_id, explode(split(text, ' ')) AS w FROM benchmark")
simple("posexplode", "SELECT item_id, generate_subscripts(t, 1) - 1 AS pos, unnest(t) AS w FROM (SELECT item_id, string_split(text, ' ') AS t FROM benchmark)", "SELECT item_id, CAST(pos AS BIGINT) AS pos, w FROM (SELECT item_id, posexplode(split(text, ' ')) AS (pos, w) FROM benchmark)")
simple("collect", "SELECT o_custkey, array_to_string(list_sort(list(o_orderkey)), ',') AS orders FROM orders GROUP BY o_custkey", "SELECT o_custkey, array_join(transform(sort_array(collect_list(o_orderkey)), x -> CAST(x AS STRING)), ',') AS orders FROM orders GROUP BY o_custkey")
simple("map_fns", "SELECT event_id, CAST(len(json_keys(props)) AS INT) AS n FROM events", "SELECT event_id, size(map_keys(from_json(props, 'map<string,string>'))) AS n FROM events")
simple("struct_fns", "SELECT s.a AS a, s.b AS b FROM (SELECT struct_pack(a := n_nationkey, b := n_name) AS s FROM nation)", "SELECT s.a AS a, s.b AS b FROM (SELECT named_struct('a', n_nationkey, 'b', n_name) AS s FROM nation)")


@op("json_parse", "SELECT event_id, json_keys(props)[1] AS k, props->>json_keys(props)[1] AS v FROM events")
def json_parse(spark, sf):
    e = load(spark, sf, "events").select("event_id", "props")
    k = F.get(F.json_object_keys("props"), F.lit(0))
    return e.select("event_id", k.alias("k"), F.try_element_at(F.from_json("props", "map<string,string>"), k).alias("v"))


@op("html_strip", "SELECT page_id, md5(trim(regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '\\s+', ' ', 'g'))) AS text FROM pages")
def html_strip(spark, sf):
    return load(spark, sf, "pages").select("page_id", F.md5(F.encode(strip_tags(F.col("html")), "UTF-8")).alias("text"))


# Python surfaces -------------------------------------------------------------------------------
@op("pandas_udf", "SELECT doc_id, CAST(length(text) AS BIGINT) AS n FROM documents")
def pandas_udf(spark, sf):
    @F.pandas_udf("long")
    def size(t: pd.Series) -> pd.Series:
        return t.str.len()

    return load(spark, sf, "documents").select("doc_id", size("text").alias("n"))


@op("map_in_pandas", "SELECT p_partkey, p_size * 2 AS doubled FROM part WHERE p_size > 25")
def map_in_pandas(spark, sf):
    def double(batches):
        for b in batches:
            b = b[b["p_size"] > 25]
            yield pd.DataFrame({"p_partkey": b["p_partkey"], "doubled": b["p_size"] * 2})

    return load(spark, sf, "part").select("p_partkey", "p_size").mapInPandas(double, "p_partkey long, doubled int")


@op("grouped_map", "SELECT source, doc_id, n_chars - min(n_chars) OVER (PARTITION BY source) AS above FROM documents")
def grouped_map(spark, sf):
    def above(g: pd.DataFrame) -> pd.DataFrame:
        return g.assign(above=g["n_chars"] - g["n_chars"].min())[["source", "doc_id", "above"]]

    return load(spark, sf, "documents").select("source", "doc_id", "n_chars").groupBy("source").applyInPandas(above, "source string, doc_id long, above long")


@op("cogroup", "SELECT o_custkey AS k, count(*) AS orders, 1::BIGINT AS customers FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY o_custkey")
def cogroup(spark, sf):
    def both(key, x: pd.DataFrame, y: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"k": [key[0]], "orders": [len(x)], "customers": [len(y)]}) if len(x) and len(y) else pd.DataFrame({"k": [], "orders": [], "customers": []}).astype("int64")

    o, c = load(spark, sf, "orders").select("o_custkey"), load(spark, sf, "customer").select("c_custkey")
    return o.groupBy("o_custkey").cogroup(c.groupBy("c_custkey")).applyInPandas(both, "k long, orders long, customers long")


@op("udtf", "SELECT item_id, CAST(i AS INT) AS i, substr(text, i::INT, 3) AS gram FROM (SELECT item_id, text, unnest(range(1, length(text) - 1)) AS i FROM benchmark)")
def udtf(spark, sf):
    from pyspark.sql.functions import udtf as make

    @make(returnType="i int, gram string")
    class Grams:
        def eval(self, text: str):
            for i in range(len(text) - 2):
                yield i + 1, text[i : i + 3]

    spark.udtf.register("simblock_grams", Grams)
    load(spark, sf, "benchmark").createOrReplaceTempView("benchmark")
    return spark.sql("SELECT item_id, g.i, g.gram FROM benchmark, LATERAL simblock_grams(text) g")


_WORDS = r"list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\p{L}\p{N}]+'), lambda t: t <> '')"


@op("registered_functions", f"WITH d AS (SELECT doc_id, {_WORDS} AS t FROM documents) SELECT a.doc_id, round(CAST(len(list_intersect(a.t, b.t)) AS DOUBLE) / nullif(len(list_distinct(list_concat(a.t, b.t))), 0), 6) AS j FROM d a JOIN d b ON b.doc_id = a.doc_id + 1")
def registered_functions(spark, sf):
    """Word Jaccard of each document and the next one, by the functions of the library."""
    from ..functions import register

    register(spark)
    load(spark, sf, "documents").createOrReplaceTempView("documents")
    return spark.sql("WITH d AS (SELECT doc_id, token_words(text) AS t FROM documents) SELECT a.doc_id, round(set_jaccard(a.t, b.t), 6) AS j FROM d a JOIN d b ON b.doc_id = a.doc_id + 1")


# subqueries and sampling -----------------------------------------------------------------------
simple("correlated_subquery", "SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)")
simple("exists", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 400000)")
simple("cte", "WITH t AS (SELECT o_custkey, sum(o_totalprice) AS s FROM orders GROUP BY o_custkey) SELECT o_custkey FROM t WHERE s > 1500000")
simple("scalar_subquery", "SELECT count(*) AS n FROM documents WHERE n_chars > (SELECT avg(n_chars) FROM documents)")
simple("sample_hash", "SELECT doc_id FROM documents WHERE substr(md5(CAST(doc_id AS VARCHAR)), 1, 1) < '4'", "SELECT doc_id FROM documents WHERE substr(md5(CAST(doc_id AS STRING)), 1, 1) < '4'")


@op("token_overlap_udf_free", "SELECT a.item_id AS a_id, b.item_id AS b_id, CAST(len(list_intersect(list_distinct(string_split(lower(a.text), ' ')), list_distinct(string_split(lower(b.text), ' ')))) AS INT) AS shared FROM benchmark a JOIN benchmark b ON a.item_id < b.item_id")
def token_overlap(spark, sf):
    t = load(spark, sf, "benchmark").select("item_id", F.split(F.lower("text"), " ").alias("t"))
    a, b = t.select(F.col("item_id").alias("a_id"), F.col("t").alias("x")), t.select(F.col("item_id").alias("b_id"), F.col("t").alias("y"))
    return F.broadcast(a).join(b, F.col("a_id") < F.col("b_id")).select("a_id", "b_id", F.size(F.array_intersect("x", "y")).alias("shared"))
