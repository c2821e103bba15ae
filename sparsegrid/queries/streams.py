"""Queries that run as streams; the SQL is the batch form."""

from __future__ import annotations

from pyspark.sql import functions as F

from sparsegrid.queries.registry import query
from sparsegrid.sources import tables as src
from sparsegrid.streaming import streams as st


def _events(spark, folder):
    return st.stream_events(spark, f"{folder}/events.parquet")


@query("SELECT CAST(epoch(time_bucket(INTERVAL 1 DAY, ts)) AS BIGINT) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling(spark, folder):
    return st.run_to_table(st.tumbling(_events(spark, folder), "1 day"))


@query("SELECT CAST(epoch(time_bucket(INTERVAL 1 DAY, ts)) AS BIGINT) - 86400 * k AS start, event_type, count(*) AS n FROM events, range(0, 2) t(k) GROUP BY 1, 2")
def stream_sliding(spark, folder):
    return st.run_to_table(st.tumbling(_events(spark, folder), "2 days", "1 day"))


@query("""WITH g AS (SELECT user_id, ts, CASE WHEN lag(ts) OVER w IS NULL OR ts - lag(ts) OVER w >= INTERVAL 12 HOUR THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS start, count(*) AS n FROM s GROUP BY user_id, k""")
def stream_session(spark, folder):
    return st.run_to_table(st.sessions(_events(spark, folder), "12 hours"))


@query("SELECT user_id, count(*) AS nz FROM events GROUP BY 1")
def stream_nnz(spark, folder):
    return st.run_to_table(st.profile(_events(spark, folder)))


@query("SELECT count(DISTINCT event_id) AS n FROM events")
def stream_dedup(spark, folder):
    """Every event sent twice and kept once."""
    e = _events(spark, folder)
    doubled = e.select("*", F.explode(F.array(F.lit(0), F.lit(1))).alias("copy")).drop("copy")
    return st.run_to_table(st.distinct_events(doubled).select("event_id"), "append").agg(F.count("*").alias("n"))


@query("SELECT user_id, count(*) AS n, max(event_id) AS last FROM events GROUP BY 1")
def stream_stateful_counts(spark, folder):
    out = st.run_to_table(st.running_degrees(_events(spark, folder)), "update")
    return out.groupBy("user_id").agg(F.max("n").alias("n"), F.max("last").alias("last"))


@query("SELECT a.event_id AS e1, b.event_id AS e2 FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def stream_wedges(spark, folder):
    return st.run_to_table(st.wedges_within(_events(spark, folder), 3600), "append")


@query("SELECT c_nationkey, count(*) AS n FROM events JOIN customer ON c_custkey = user_id GROUP BY 1")
def stream_static_join(spark, folder):
    return st.run_to_table(st.with_customers(_events(spark, folder), src.load_table(spark, folder, "customer")))


@query("""WITH e AS (SELECT CAST(floor(epoch(ts) / 86400) AS BIGINT) * 86400 AS start, user_id AS u, lead(user_id) OVER (PARTITION BY CAST(floor(epoch(ts) / 86400) AS BIGINT) ORDER BY ts, event_id) AS v FROM events),
d AS (SELECT DISTINCT start, u, v FROM e WHERE v IS NOT NULL AND u <> v)
SELECT start, count(*) AS edges, count(DISTINCT u) AS sources FROM d GROUP BY 1""")
def daily_snapshots(spark, folder):
    """The hand-off graph of every day: edges and sources."""
    events = src.load_table(spark, folder, "events").withColumn("at", st.instant("ts"))
    return st.snapshots(events, 86400, lambda e: e.groupBy("start").agg(F.count("*").alias("edges"), F.countDistinct("src").alias("sources")))


@query("""WITH e AS (SELECT CAST(floor(epoch(ts) / 86400) AS BIGINT) * 86400 AS start, user_id AS u, lead(user_id) OVER (PARTITION BY CAST(floor(epoch(ts) / 86400) AS BIGINT) ORDER BY ts, event_id) AS v FROM events),
d AS MATERIALIZED (SELECT DISTINCT start, u, v FROM e WHERE v IS NOT NULL AND u <> v),
t AS (SELECT a.start, count(*) AS triangles FROM d a JOIN d b ON a.start = b.start AND a.v = b.u JOIN d c ON c.start = a.start AND b.v = c.u AND c.v = a.u WHERE a.u < a.v AND a.u < b.v GROUP BY 1)
SELECT d.start, count(*) AS edges, CAST(coalesce(any_value(triangles), 0) AS BIGINT) AS triangles FROM d LEFT JOIN t USING (start) GROUP BY 1""")
def stream_window_triangles(spark, folder):
    """A triangle count for every day's hand-offs as the stream closes the day."""
    return st.closed_windows(_events(spark, folder), 86400, 3600, st.triangles_by_window)[0]
