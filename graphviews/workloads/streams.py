"""Streaming workloads; each ends in the same rows as its batch form."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import functions as F

from graphviews.maintenance.network import Network
from graphviews.sources.commerce import EDGES, VERTICES, read_tables
from graphviews.sources.graph import PropertyGraph
from graphviews.sources.shared import new_path
from graphviews.streaming.runner import corrected, folder_stream, last_result, maintain, table_stream, timed
from graphviews.streaming.stateful import running_counts

QUERIES: dict[str, Callable] = {}
ORACLE_SQL: dict[str, str] = {}


def register(name: str, sql: str):
    def keep(run):
        QUERIES[name], ORACLE_SQL[name] = run, sql
        return run

    return keep


def _text(column: str):
    return F.date_format(column, "yyyy-MM-dd HH:mm")


@register("s_tumbling", "SELECT event_type AS kind, strftime(time_bucket(INTERVAL 6 HOUR, ts), '%Y-%m-%d %H:%M') AS start, count(*)::BIGINT AS n FROM events GROUP BY 1, 2")
def _tumbling(spark, sf_dir):
    e = timed(table_stream(spark, sf_dir, "events"))
    out = last_result(e.groupBy(F.window("ts", "6 hours").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")))
    return out.select(F.col("event_type").alias("kind"), _text("w.start").alias("start"), "n")


@register("s_sliding", "SELECT strftime(s, '%Y-%m-%d %H:%M') AS start, count(*)::BIGINT AS n FROM (SELECT unnest([time_bucket(INTERVAL 3 HOUR, ts), time_bucket(INTERVAL 3 HOUR, ts) - INTERVAL 3 HOUR]) AS s FROM events) GROUP BY 1")
def _sliding(spark, sf_dir):
    e = timed(table_stream(spark, sf_dir, "events"))
    out = last_result(e.groupBy(F.window("ts", "6 hours", "3 hours").alias("w")).agg(F.count(F.lit(1)).alias("n")))
    return out.select(_text("w.start").alias("start"), "n")


@register("s_session", """SELECT user_id AS u, count(*)::BIGINT AS n FROM (SELECT user_id, s, count(*) FROM (SELECT *, sum(brk) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s
FROM (SELECT *, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 4 HOUR > ts THEN 0 ELSE 1 END AS brk FROM events)) GROUP BY 1, 2) GROUP BY 1""")
def _session(spark, sf_dir):
    e = timed(table_stream(spark, sf_dir, "events"))
    out = last_result(e.groupBy(F.session_window("ts", "4 hours").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("k")))
    return out.groupBy(F.col("user_id").alias("u")).agg(F.count(F.lit(1)).alias("n"))


@register("s_interval_join", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'purchase' AND b.event_type = 'error' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 12 HOUR")
def _interval(spark, sf_dir):
    e = timed(table_stream(spark, sf_dir, "events"))
    a = e.where("event_type = 'purchase'").select(F.col("event_id").alias("a"), F.col("user_id").alias("u"), F.col("ts").alias("ta"))
    b = e.where("event_type = 'error'").select(F.col("event_id").alias("b"), F.col("user_id").alias("v"), F.col("ts").alias("tb"))
    return last_result(a.join(b, F.expr("u = v and tb >= ta and tb <= ta + interval 12 hours")).select("a", "b"), "append")


@register("s_dedup", "SELECT event_id AS e, event_type AS kind FROM events")
def _dedup(spark, sf_dir):
    e = table_stream(spark, sf_dir, "events")
    twice = timed(e.withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2)))))
    return last_result(twice.dropDuplicatesWithinWatermark(["event_id"]).select(F.col("event_id").alias("e"), F.col("event_type").alias("kind")), "append")


def _files(spark, sf_dir, files: int, by: str = "event_id"):
    """The events dealt to so many files by a number, one a micro-batch; by id, rows come in no order of time."""
    events = read_tables(spark, sf_dir, ["events"])["events"]
    path = new_path(spark, "events")
    for i in range(files):
        events.where(F.pmod(F.expr(by), F.lit(files)) == i).coalesce(1).write.mode("append").parquet(path)
    return path, events.schema


@register("s_late_correction", "SELECT event_type AS kind, count(*)::BIGINT AS n FROM events GROUP BY 1")
def _late(spark, sf_dir):
    out = corrected(folder_stream(spark, *_files(spark, sf_dir, 3)), "ts", ["event_type"], "1 hour")
    return out.select(F.col("event_type").alias("kind"), "n")


@register("s_stateful_count", "SELECT user_id AS u, count(*)::BIGINT AS n FROM events GROUP BY 1")
def _stateful(spark, sf_dir):
    updates = last_result(running_counts(folder_stream(spark, *_files(spark, sf_dir, 2)), "user_id"), "update")
    return updates.groupBy(F.col("user_id").alias("u")).agg(F.max("n").alias("n"))


def _streamed_view(spark, sf_dir, text: str):
    t = read_tables(spark, sf_dir)
    path, schema = _files(spark, sf_dir, 3, "unix_date(to_date(ts))")  # whole days come together
    graph = PropertyGraph(spark, {**t, "events": t["events"].limit(0)}, VERTICES, EDGES)
    network = Network(graph, graph.plans(text).flat, label="streamed").load()
    maintain(folder_stream(spark, path, schema), "events", network)
    return network.read()


@register("s_network", "SELECT user_id AS u, count(*)::BIGINT AS n FROM (SELECT *, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS t FROM events) WHERE event_type = 'purchase' AND t = 'error' GROUP BY 1")
def _network(spark, sf_dir):
    return _streamed_view(spark, sf_dir, "MATCH (a:Event)-[:FOLLOWS]->(b:Event) WHERE a.etype = 'purchase' AND b.etype = 'error' MATCH (c:Customer)-[:DID]->(a) RETURN c.key AS u, count(*) AS n")


@register("w_stream_did", "SELECT c_mktsegment AS s, event_type AS kind, count(*)::BIGINT AS n FROM events JOIN customer ON c_custkey = user_id GROUP BY 1, 2")
def _did(spark, sf_dir):
    return _streamed_view(spark, sf_dir, "MATCH (c:Customer)-[d:DID]->(e:Event) RETURN c.segment AS s, d.etype AS kind, count(*) AS n")
