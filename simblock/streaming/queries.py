"""Stream queries, each run to its end; their SQL is the batch equivalent."""

from __future__ import annotations

import time

import pandas as pd
from pyspark.sql import functions as F

from .. import sqltext as S
from .. import workloads as W
from ..join import hybrid_join
from ..plans.stages import cut
from ..sources import load
from ..tokens import term_counts, words
from ..weights import Prepared, TokenModel, prepare, running, unit_norm
from . import drain, incremental_block, replay

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def stream(name: str, sql: str | None = None):
    def add(f):
        QUERIES[f"stream_{name}"] = f
        if sql:
            ORACLE_SQL[f"stream_{name}"] = sql
        return f

    return add


@stream("incremental_block", S.hybrid(S.ITEMS, S.DOCS, "word", "tfidf", "cosine", 0.05, 0.5, 5))
def incremental(spark, sf):
    """Items arrive in batches and probe a static index whose dictionary is frozen."""
    items, docs = W.items(spark, sf), W.docs(spark, sf)
    p = prepare(items, docs, TokenModel("word", "tfidf"), "cosine")
    total = float(p.n_a + p.n_b)

    def block(batch):
        t = term_counts(batch).join(p.vocabulary, "token")
        sets = t.select("rec_id", "key", (F.col("tf") * F.log(1 + F.lit(total) / F.col("df"))).alias("w"))
        a = cut(running(unit_norm(sets), 2), "batch")
        return hybrid_join(Prepared(a, p.b, p.vocabulary, p.n_a, p.n_b, "cosine", False), 0.05, 0.5, 5)

    return incremental_block(replay(spark, items), block).select("a_id", "b_id", F.round("sim", 6).alias("sim"))


def _events(spark, sf, *cols):
    """Events as a stream in time order, so that no row is late, and a far row that closes all windows."""
    e = load(spark, sf, "events").select(F.col("ts").cast("timestamp").alias("ts"), *cols)
    far = e.agg(F.max("ts").alias("ts")).select((F.col("ts") + F.expr("interval 100 days")).alias("ts"))
    path_rows = e.unionByName(far, allowMissingColumns=True)
    from ..plans.stages import fresh_path

    path = fresh_path(spark, "events")
    path_rows.where(F.col(cols[0]).isNotNull()).coalesce(1).write.parquet(path + "/a")
    time.sleep(1.1)  # files are read by their time, in seconds
    path_rows.where(F.col(cols[0]).isNull()).coalesce(1).write.parquet(path + "/b")
    # two directories would be read in any order; the far row comes in a file of later time
    return spark.readStream.schema(path_rows.schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(path)


def _closed(df, *cols):
    return df.where(F.col(cols[0]).isNotNull())


@stream("tumbling", "SELECT event_type, time_bucket(INTERVAL 1 HOUR, ts::TIMESTAMP) AS start, count(*) AS n FROM events GROUP BY ALL")
def tumbling(spark, sf):
    s = _events(spark, sf, "event_type").withWatermark("ts", "1 hour")
    g = s.groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count("*").alias("n"))
    return _closed(drain(g).select("event_type", F.col("window.start").alias("start"), "n"), "event_type")


@stream("sliding", "SELECT event_type, s AS start, count(*) AS n FROM (SELECT event_type, unnest([time_bucket(INTERVAL 30 MINUTE, ts::TIMESTAMP), time_bucket(INTERVAL 30 MINUTE, ts::TIMESTAMP) - INTERVAL 30 MINUTE]) AS s FROM events) GROUP BY ALL")
def sliding(spark, sf):
    s = _events(spark, sf, "event_type").withWatermark("ts", "1 hour")
    g = s.groupBy(F.window("ts", "1 hour", "30 minutes"), "event_type").agg(F.count("*").alias("n"))
    return _closed(drain(g).select("event_type", F.col("window.start").alias("start"), "n"), "event_type")


@stream("session", """WITH g AS (SELECT user_id, ts::TIMESTAMP AS ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS f FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
 s AS (SELECT *, sum(f) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS n FROM g) SELECT user_id, min(ts) AS start, count(*) AS events FROM s GROUP BY user_id, n""")
def session(spark, sf):
    s = _events(spark, sf, "user_id").withWatermark("ts", "1 hour")
    g = s.groupBy(F.session_window("ts", "30 minutes"), "user_id").agg(F.count("*").alias("events"))
    return _closed(drain(g).select("user_id", F.col("session_window.start").alias("start"), "events"), "user_id")


@stream("dedup", "SELECT DISTINCT md5(text) AS h FROM documents")
def dedup(spark, sf):
    s = replay(spark, W.docs(spark, sf).select(F.md5(F.encode("text", "UTF-8")).alias("h")))
    return drain(s.dropDuplicates(["h"]))


@stream("token_df", f"SELECT token, count(*) AS df FROM ({S.terms(S.ITEMS)}) GROUP BY token")
def token_df(spark, sf):
    """Document frequencies kept up to date; the last update of each token."""
    s = replay(spark, W.items(spark, sf)).select(F.explode(F.array_distinct(words(F.col("text")))).alias("token")).groupBy("token").agg(F.count("*").alias("df"))
    return drain(s, "update").groupBy("token").agg(F.max("df").alias("df"))


@stream("static_join", "SELECT d.doc_id, l.toxic FROM documents d JOIN labels l ON d.doc_id = l.doc_id")
def static_join(spark, sf):
    labels = load(spark, sf, "labels").select("doc_id", "toxic")
    return drain(replay(spark, load(spark, sf, "documents").select("doc_id")).join(labels, "doc_id"))


@stream("interval_join", "SELECT a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 HOUR")
def interval_join(spark, sf):
    e = load(spark, sf, "events").select("event_id", "user_id", "event_type", F.col("ts").cast("timestamp").alias("ts"))
    a = replay(spark, e.where("event_type = 'click'"), 1).select(F.col("event_id").alias("a_id"), F.col("user_id").alias("u"), F.col("ts").alias("t")).withWatermark("t", "10 days")
    b = replay(spark, e.where("event_type = 'purchase'"), 1).select(F.col("event_id").alias("b_id"), F.col("user_id").alias("v"), F.col("ts").alias("s")).withWatermark("s", "10 days")
    return drain(a.join(b, F.expr("u = v AND s BETWEEN t AND t + INTERVAL 1 HOUR"))).select("a_id", "b_id")


@stream("late_drop", "SELECT CAST(0 AS BIGINT) AS late")
def late_drop(spark, sf):
    """Rows older than the watermark are left out: a very old row in a later batch adds no window.

    Late rows are judged by the watermark of the batch before, so the old row comes two batches
    after the one that moved it.
    """
    from ..plans.stages import fresh_path

    path = fresh_path(spark, "late")
    for i, when in enumerate(("2020-01-01 00:00:00", "2020-02-01 00:00:00", "2020-02-02 00:00:00", "2020-01-01 00:10:00", "2020-03-01 00:00:00")):
        spark.createDataFrame([(when, i)], "ts string, n int").select(F.to_timestamp("ts").alias("ts"), "n").coalesce(1).write.mode("append").parquet(path)
        time.sleep(1.1)
    s = spark.readStream.schema("ts timestamp, n int").option("maxFilesPerTrigger", 1).parquet(path).withWatermark("ts", "1 hour")
    got = drain(s.groupBy(F.window("ts", "1 hour")).agg(F.max("n").alias("n")))
    return got.agg(F.count_if(F.col("n") == 3).alias("late"))


@stream("running_topk", "SELECT user_id, round(sum(value), 4) AS top3 FROM (SELECT user_id, value, row_number() OVER (PARTITION BY user_id ORDER BY value DESC) AS n FROM events) WHERE n <= 3 GROUP BY user_id")
def running_topk(spark, sf):
    """Per user the three largest values, held as state over all batches."""

    def top(key, frames, state):
        best = list(state.get[0]) if state.exists else []
        for f in frames:
            best += f["value"].tolist()
        best = sorted(best, reverse=True)[:3]
        state.update((best,))
        yield pd.DataFrame({"user_id": [key[0]], "top3": [sum(best)]})

    s = replay(spark, load(spark, sf, "events").select("user_id", "value"))
    g = s.groupBy("user_id").applyInPandasWithState(top, "user_id long, top3 double", "best array<double>", "update", "NoTimeout")
    out = drain(g, "update")
    return out.groupBy("user_id").agg(F.round(F.max_by("top3", "_batch"), 4).alias("top3"))
