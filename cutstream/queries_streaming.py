"""Streaming queries: windows, duplicates, stateful buffers, and the live partitioner against the batch engine."""

from __future__ import annotations

from cutstream import scratch
from cutstream.operators import measures as M
from cutstream.params import PartitionParams
from cutstream.plans.graph import Graph
from cutstream.queries_graph import graph_cte
from cutstream.streaming import live
from cutstream.twins import multilevel_sql


def _live(s, d, graph="docline", k=8, delta=128):
    g = Graph.load(s, d, graph)
    p = PartitionParams(k=k, delta=delta)
    at = scratch.path(s, "vertices")
    live.write_vertex_files(g, delta, at)
    return g, p, live.partition_stream(s, live.stream_vertices(s, at), g.n, g.m, p, scratch.path(s, "mark"))


def stream_docline(s, d):
    """Blocks that the live partitioner gives; its twin is that of the batch method."""
    return _live(s, d)[2].select("pos", "block")


def stream_partition(s, d):
    g, p, out = _live(s, d, "userflow", 4, 64)
    return M.summary(g, out, p.k, p.eps).select("cut", "cut_pct", "max_load", "feasible")


QUERIES = {
    "stream_tumbling": live.tumbling,
    "stream_sliding": live.sliding,
    "stream_sessions": live.sessions,
    "stream_dedup": live.deduplicated,
    "stream_lane_buffers": live.lane_buffers,
    "stream_docline": stream_docline,
    "stream_partition": stream_partition,
}
ORACLES = {
    "stream_tumbling": "SELECT epoch_us(date_trunc('hour', ts)) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2",
    "stream_sliding": "SELECT epoch_us(w) AS start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 6 HOUR, ts), time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 6 HOUR, time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 12 HOUR, time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 18 HOUR]) AS w FROM events) GROUP BY 1",
    "stream_sessions": "WITH g AS (SELECT *, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS sid FROM g) SELECT epoch_us(min(ts)) AS start, user_id, count(*) AS n FROM s GROUP BY user_id, sid",
    "stream_dedup": "SELECT DISTINCT user_id, event_type FROM events",
    "stream_lane_buffers": "SELECT lane, unnest(range(n // 500)) AS flush, CAST(500 AS BIGINT) AS rows FROM (SELECT user_id % 4 AS lane, count(*) AS n FROM events GROUP BY 1)",
    "stream_docline": multilevel_sql(graph_cte("docline"), 8, "128"),
}
