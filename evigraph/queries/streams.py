"""Streaming queries; the twin in SQL is the batch answer."""

from __future__ import annotations

from pyspark.sql import functions as F

from evigraph.operators import textprep
from evigraph.queries.method import count_sql
from evigraph.runtime import scratch
from evigraph.sources import corpora
from evigraph.streaming import streams as st

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def stamp(df, *cols):
    """Times as whole seconds, which both engines print alike."""
    for c in cols:
        df = df.withColumn(c, F.unix_seconds(c))
    return df


@query("SELECT epoch(date_trunc('day', ts))::BIGINT AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_tumbling(spark, d):
    return stamp(st.drain(st.tumbling(st.in_thirds(spark, st.events(spark, d))), "complete"), "start")


@query("SELECT epoch(date_trunc('day', ts))::BIGINT - 86400 * k AS start, count(*) AS n FROM events, (VALUES (0), (1)) v(k) GROUP BY 1")
def stream_sliding(spark, d):
    return stamp(st.drain(st.sliding(st.in_thirds(spark, st.events(spark, d))), "complete"), "start")


@query(
    "WITH e AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 1 HOUR THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM e) SELECT user_id, floor(epoch(min(ts)))::BIGINT AS start, count(*) AS n FROM s GROUP BY user_id, g"
)
def stream_session(spark, d):
    return stamp(st.drain(st.sessions(st.in_thirds(spark, st.events(spark, d))), "complete"), "start")


@query("SELECT event_id, user_id FROM events")
def stream_dedup(spark, d):
    e = st.events(spark, d).select("event_id", "user_id", "ts")
    twice = st.replay(spark, e, [F.lit(True), F.col("event_id") % 3 == 0], "twice")
    return st.drain(twice.withWatermark("ts", "4000 days").dropDuplicatesWithinWatermark(["event_id"])).select("event_id", "user_id")


@query("SELECT c_nationkey, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY c_nationkey")
def stream_static_join(spark, d):
    c = corpora.table(spark, d, "customer").select("c_custkey", "c_nationkey")
    s = st.in_thirds(spark, st.events(spark, d).select("event_id", "user_id"))
    return st.drain(s.join(c, s["user_id"] == c["c_custkey"]).groupBy("c_nationkey").agg(F.count("*").alias("n")), "complete")


@query("SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase'")
def stream_interval_join(spark, d):
    e = st.events(spark, d)
    a = st.replay(spark, e.where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u"), F.col("ts").alias("t0")), [F.lit(True)], "clicks").withWatermark("t0", "4000 days")
    b = st.replay(spark, e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "user_id", F.col("ts").alias("t1")), [F.lit(True)], "purchases").withWatermark("t1", "4000 days")
    return st.drain(a.join(b, F.expr("u = user_id and t1 >= t0 and t1 <= t0 + interval 1 hour"))).select("click", "purchase")


@query("WITH m AS (SELECT max(ts) AS m FROM events) SELECT count(*) AS n FROM events, m WHERE ts >= date_trunc('day', m - INTERVAL 2 DAY)")
def stream_late(spark, d):
    """The newest rows first, then the rest: rows of windows that the watermark of two days has closed are dropped."""
    e = st.events(spark, d).select("event_id", "ts", "event_type")
    top = e.agg(F.max("ts").alias("m")).first()["m"]
    if top is None:
        return spark.createDataFrame([(0,)], "n long")
    newest = F.col("ts") >= F.lit(top) - F.expr("interval 1 hour")
    recent = F.col("ts") >= F.lit(top) - F.expr("interval 1 day")
    # A batch's rows are held against the watermark of the batch before the last one, so late rows come in the third file.
    s = st.replay(spark, e, [newest, recent & ~newest, ~recent], "late").withWatermark("ts", "2 days")
    state = scratch(spark, "late")

    def keep(batch, i):
        batch.write.mode("overwrite").parquet(f"{state}/b={i}")

    st.drain(s.groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n")), "update", keep)
    return spark.read.parquet(state).groupBy("w.start").agg(F.max("n").alias("n")).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"))


DF_TWIN = "WITH " + count_sql(1) + " SELECT term, count(*) AS df FROM counts GROUP BY term"


@query(DF_TWIN)
def stream_df_counts(spark, d):
    """Document frequencies kept up to date while documents arrive in four files."""
    docs = corpora.documents(spark, d)
    s = st.replay(spark, docs, [F.pmod(F.col("doc_key").cast("long"), F.lit(4)) == i for i in range(4)], "documents")
    words = textprep.chunk(s).select("chunk_key", F.explode(F.array_distinct("tokens")).alias("term"))
    return st.drain(words.groupBy("term").agg(F.count("*").alias("df")), "complete")


@query(DF_TWIN)
def stream_index_upsert(spark, d):
    docs = corpora.documents(spark, d)
    path = scratch(spark, "index")
    s = st.replay(spark, docs, [F.pmod(F.col("doc_key").cast("long"), F.lit(4)) == i for i in range(4)], "documents")
    st.drain(s, "append", st.upsert_index(spark, docs, path))
    return textprep.doc_freq(spark.read.parquet(f"{path}/counts"))
