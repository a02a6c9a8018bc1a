"""Queries over the event stream: every streaming operator's batch twin with its oracle, and the stream itself."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..plans import sqlgen as q
from ..plans.registry import graph, register
from . import stream as st

register("st_tumbling_batch", lambda s, sf: st.tumbling(st.batch_events(s, sf)), "SELECT user_id, CAST(epoch(date_trunc('hour', ts)) AS BIGINT) AS start, count(*) AS n FROM events GROUP BY 1, 2")
register("st_tumbling_stream", lambda s, sf: st.drain(st.tumbling(st.stream_events(s, sf)), "complete"), "SELECT user_id, CAST(epoch(date_trunc('hour', ts)) AS BIGINT) AS start, count(*) AS n FROM events GROUP BY 1, 2")
_SLIDE = "SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) - 3600 * k AS start, user_id, count(*) AS n FROM events, range(2) r(k) GROUP BY 1, 2"
register("st_sliding_batch", lambda s, sf: st.sliding(st.batch_events(s, sf)), _SLIDE)
register("st_sliding_stream", lambda s, sf: st.drain(st.sliding(st.stream_events(s, sf)), "complete"), _SLIDE)
_SESSION = "SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS start, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events) a) b GROUP BY user_id, k"
register("st_sessions_batch", lambda s, sf: st.sessions(st.batch_events(s, sf)), _SESSION)
register("st_sessions_stream", lambda s, sf: st.drain(st.sessions(st.stream_events(s, sf)), "complete"), _SESSION)
_EDGES = "SELECT DISTINCT user_id AS u, CAST(json_extract_string(props, '$.k') AS BIGINT) AS v FROM events"
register("st_distinct_edges_batch", lambda s, sf: st.distinct_edges(st.batch_events(s, sf)), _EDGES)
register("st_distinct_edges_stream", lambda s, sf: st.drain(st.distinct_edges(st.stream_events(s, sf))), _EDGES)
_CHAIN = "SELECT event_id AS u, v FROM (SELECT event_id, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS v FROM events) z WHERE v IS NOT NULL"
register("st_chain_batch", lambda s, sf: graph(s, sf, "event_chain").tuples, _CHAIN)
register("st_chain_stream", lambda s, sf: st.drain(st.chain_edges(st.stream_events(s, sf))), _CHAIN)
_CO = "SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON x.user_id = y.user_id AND y.ts > x.ts AND y.ts <= x.ts + INTERVAL 600 SECOND"
register("st_co_activity_batch", lambda s, sf: st.co_activity(st.batch_events(s, sf)), _CO)
register("st_co_activity_stream", lambda s, sf: st.drain(st.co_activity(st.stream_events(s, sf))), _CO)


def _users(s, sf):
    return st.batch_events(s, sf).select("user_id").distinct().select("user_id", (F.col("user_id") * 10 + 1).alias("vid"))


_ENRICHED = "SELECT event_id, user_id * 10 + 1 AS vid FROM events"
register("st_enriched_batch", lambda s, sf: st.enriched(st.batch_events(s, sf), _users(s, sf)), _ENRICHED)
register("st_enriched_stream", lambda s, sf: st.drain(st.enriched(st.stream_events(s, sf), _users(s, sf))), _ENRICHED)


def _kept_directory(s, sf):
    g = graph(s, sf, "user_key")
    users = g.source
    edges = st.distinct_edges(st.stream_events(s, sf)).select("u", (F.col("v") + users).alias("v"))
    return st.DirectoryKeeper(g).follow(edges)


register("st_directory_stream", _kept_directory, q.query(q.base("user_key"), "SELECT needer_block, owner_block, slot FROM needs"))


def _searched(s, sf):
    """Level sizes of the search after the last micro-batch, from the edges that the stream has written."""
    g = graph(s, sf, "user_key")
    edges = st.stream_events(s, sf).select(F.col("user_id").alias("u"), (F.get_json_object("props", "$.k").cast("long") + g.source).alias("v"))
    return st.SearchKeeper(g.n, g.p, g.source, s).follow(edges).groupBy("level").agg(F.count("*").alias("n"))


register("st_search_after_batch", _searched, q.tree_sql("user_key", "SELECT level, count(*) AS n FROM tree GROUP BY level"))
