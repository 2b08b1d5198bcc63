"""Streaming operators: each drains a stream over the events and equals its batch twin in SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..model import init_model
from ..streaming import events as st
from ..tensor import TensorFrame
from .relational import Query
from .tensor_queries import DIMS, STATS_SQL, one_row, r, sine_model

TABLE: dict[str, tuple[Query, str | None]] = {}


def query(name: str, sql: str | None = None):
    def add(f: Query) -> Query:
        TABLE[name] = (f, sql)
        return f

    return add


@query("st_source", "SELECT event_id, user_id FROM events")
def _(spark, d):
    return st.drain(st.event_stream(spark, d, 2).select("event_id", "user_id"))


@query("st_watermark", "SELECT count(*) AS n FROM events")
def _(spark, d):
    s = st.event_stream(spark, d).withWatermark("ts", "1 hour").select("event_id", "ts")
    return st.drain(s).agg(F.count("*").alias("n"))


@query("st_tumbling", "SELECT strftime(CAST(ts AS DATE), '%Y-%m-%d') AS day, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def _(spark, d):
    return st.drain(st.tumbling(st.event_stream(spark, d)), "complete").select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "n", "total")


@query("st_sliding", "SELECT strftime(time_bucket(INTERVAL 6 HOUR, ts) - o * INTERVAL 6 HOUR, '%Y-%m-%d %H') AS start, count(*) AS n FROM events, range(4) t(o) GROUP BY ALL")
def _(spark, d):
    return st.drain(st.sliding(st.event_stream(spark, d)), "complete").select(F.date_format("start", "yyyy-MM-dd HH").alias("start"), "n")


@query("st_session", "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM g) SELECT user_id, count(*) AS n FROM s GROUP BY user_id, sid")
def _(spark, d):
    return st.drain(st.sessions(st.event_stream(spark, d)), "complete").select("user_id", "n")


@query("st_dedupe", "SELECT DISTINCT event_id FROM events")
def _(spark, d):
    s = st.event_stream(spark, d)
    return st.drain(st.dedupe(s.union(s)).select("event_id"))


_SPLIT = "SELECT min(ts) + (max(ts) - min(ts)) / 2 AS cut FROM events"


@query("st_late", f"WITH c AS ({_SPLIT}), w AS (SELECT max(ts) - INTERVAL 1 HOUR AS mark FROM events, c WHERE ts >= cut AND event_id % 2 = 0) SELECT (SELECT count(*) FROM events, c, w WHERE ts >= cut OR ts > mark) AS kept, (SELECT count(*) FROM events, c, w WHERE ts < cut AND ts <= mark) AS dropped")
def _(spark, d):
    """The later half of the events comes first; of the earlier half, rows behind the watermark are dropped and counted."""
    kept, dropped = st.late_rows(spark, d)
    return one_row(spark, kept=kept, dropped=dropped)


@query("st_static_join", "SELECT event_id, n_name FROM events JOIN nation ON user_id % 25 = n_nationkey")
def _(spark, d):
    n = spark.read.parquet(f"{d}/nation.parquet").select("n_nationkey", "n_name")
    return st.drain(st.event_stream(spark, d).join(F.broadcast(n), F.col("user_id") % 25 == F.col("n_nationkey")).select("event_id", "n_name"))


@query("st_stream_join", "SELECT a.event_id AS view_id, b.event_id AS click_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'click' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 30 MINUTE")
def _(spark, d):
    return st.drain(st.views_to_clicks(st.event_stream(spark, d))).select("view_id", "click_id")


def _cells(df):
    from ..workloads import K

    return df.select((F.col("user_id") % 7).alias("i_1"), (F.hour("ts") % 6).cast("long").alias("i_2"), (K() % 5).alias("i_3"), (F.col("value") / 100).alias("y"))


_RAW = STATS_SQL.replace("round(avg(value) / 100, 6) AS y FROM events GROUP BY ALL", "value / 100 AS y FROM events")



@query("st_stats", f"WITH {_RAW} SELECT round(g11, 4) AS g11, round(h1, 4) AS h1, round(s, 4) AS s, n FROM s")
def _(spark, d):
    acc = st.StreamStats(sine_model(), DIMS)
    st.for_each(_cells(st.event_stream(spark, d)), acc.merge)
    s = acc.stats()
    return one_row(spark, g11=r(s.g[0, 0], 4), h1=r(s.h[0], 4), s=r(s.s, 4), n=s.n)


@query("st_fit")
def _(spark, d):
    """Bounds after each gradient step of each micro-batch."""
    t = TensorFrame(_cells(st.batch_events(spark, d)), DIMS)
    fit = st.StreamFit(init_model(t, 2, 8), DIMS)
    st.for_each(_cells(st.event_stream(spark, d)), fit.merge)
    return spark.createDataFrame([(i, int(b), float(v)) for i, (b, v) in enumerate(fit.trace)], "step int, batch int, bound double")


@query("st_state", "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS clicks, count(*) FILTER (WHERE event_type = 'view') AS views FROM events GROUP BY user_id")
def _(spark, d):
    # updates of every micro-batch: the last of a user has the largest counts
    out = st.drain(st.user_counters(st.event_stream(spark, d)), "update")
    return out.groupBy("user_id").agg(F.max("clicks").alias("clicks"), F.max("views").alias("views"))


@query("st_sinks", "SELECT sink, event_type, count(*) AS n FROM events, (VALUES ('append'), ('complete'), ('update')) t(sink) GROUP BY ALL")
def _(spark, d):
    """Counts by way of three output modes: Parquet with a stop and a restart from the checkpoint, memory, and a batch function that
    upserts."""
    from ..sources.tables import scratch

    s = st.event_stream(spark, d).select("event_id", "event_type")
    out, ckpt = scratch(spark, "sink"), scratch(spark, "ckpt")
    write = s.writeStream.format("parquet").option("checkpointLocation", ckpt)
    write.trigger(once=True).start(out).awaitTermination()
    write.trigger(availableNow=True).start(out).awaitTermination()
    append = spark.read.parquet(out).groupBy("event_type").agg(F.count("*").alias("n"))
    counts = lambda: st.event_stream(spark, d).groupBy("event_type").agg(F.count("*").alias("n"))
    complete = st.drain(counts(), "complete")
    state: dict[str, int] = {}

    def upsert(df, batch_id):
        state.update({r.event_type: r.n for r in df.collect()})

    counts().writeStream.outputMode("update").foreachBatch(upsert).option("checkpointLocation", scratch(spark, "ckpt")).trigger(availableNow=True).start().awaitTermination()
    update = spark.createDataFrame(list(state.items()), "event_type string, n bigint")
    parts = [df.select(F.lit(name).alias("sink"), "event_type", "n") for name, df in (("append", append), ("complete", complete), ("update", update))]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])
