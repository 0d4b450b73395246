"""Streams, each run to its end and compared with its batch twin in SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from rambler import oracles as O
from rambler.operators.walk import WalkConfig
from rambler.queries import MODELS, query
from rambler.sources.catalog import load_graph
from rambler.streaming import streams as T


@query("stream_node_stats", "SELECT epoch(date_trunc('day', ts))::BIGINT AS start, user_id, count(*) AS n, round(sum(value), 6) AS total, max(value) AS top FROM events GROUP BY 1, 2")
def node_stats(s, d):
    return T.run(T.stream_node_stats(T.event_stream(s, d)), "complete").select(F.unix_seconds("w.start").alias("start"), "user_id", "n", F.round("total", 6).alias("total"), "top")


@query("stream_sliding_edges", "SELECT (epoch(date_trunc('hour', ts))::BIGINT - 3600 * k) AS start, count(*) AS n FROM events, unnest(range(6)) x(k) GROUP BY 1")
def sliding(s, d):
    return T.run(T.stream_sliding_edges(T.event_stream(s, d)), "complete").select(F.unix_seconds("w.start").alias("start"), "n")


@query("stream_session_users", """SELECT user_id, count(*) AS n FROM (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k
FROM (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, k""")
def sessions(s, d):
    return T.run(T.stream_session_users(T.event_stream(s, d)), "complete").select("user_id", "n")


@query("stream_dedup_edges", "SELECT DISTINCT event_id FROM events")
def dedup(s, d):
    return T.run(T.stream_dedup_edges(T.event_stream(s, d)), "append").select("event_id")


@query("stream_walk_queries", O.walk("g6", "node2vec_w", "keys", 3, starts="SELECT DISTINCT user_id AS start FROM events"))
def walk_queries(s, d):
    """Every user of the stream asks for a walk; the id of the walk is the user's."""
    asked = T.event_stream(s, d).select(F.col("user_id").alias("walk_id"), F.col("user_id").alias("start")).dropDuplicates(["walk_id", "start"])
    return T.serve_walk_queries(asked, load_graph(s, d, "g6").stored(), MODELS["node2vec_w"], WalkConfig(steps=3, mode="superstep")).select("walk_id", "step", "node")


@query("stream_node_stats_closed", """SELECT epoch(date_trunc('day', ts))::BIGINT AS start, user_id, count(*) AS n, round(sum(value), 6) AS total, max(value) AS top FROM events
GROUP BY 1, 2 HAVING epoch(date_trunc('day', any_value(ts))) + 86400 <= (SELECT epoch(max(ts)) - 7200 FROM events)""")
def node_stats_closed(s, d):
    """The windows that the watermark has closed: append mode, whose state is dropped with them."""
    return T.run(T.stream_node_stats(T.event_stream(s, d)), "append").select(F.unix_seconds("w.start").alias("start"), "user_id", "n", F.round("total", 6).alias("total"), "top")


@query("stream_interval_join", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def interval_join(s, d):
    """A click and a purchase of the same user within the hour after it, as two streams meet."""
    return T.run(T.stream_interval_join(T.event_stream(s, d).where("event_type = 'click'"), T.event_stream(s, d).where("event_type = 'purchase'")), "append")


@query("stream_transition_edges", "SELECT * FROM (SELECT event_id, user_id, lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS came_from, event_type FROM events) WHERE came_from IS NOT NULL")
def transitions(s, d):
    """A user's next kind of event."""
    return T.transition_edges(T.event_stream(s, d))
