"""Streaming workloads, each against batch SQL over the same events."""

from __future__ import annotations

from pyspark.sql import functions as F

from boundpath.streaming import linkstate as L
from boundpath.topology import networks as N

_C = "c AS (SELECT event_id, ts, user_id % 97 AS link_id, CAST(ceil(value) AS BIGINT) AS amount FROM events)"
# windows that the watermark has not yet passed when the input ends are not emitted in append mode
_MARK = "(SELECT max(ts) - INTERVAL 10 MINUTE FROM c)"


def load_tumbling(spark, d):
    return L.run_once(L.tumbling_load(L.event_stream(spark, d)), "complete")


def load_sliding(spark, d):
    return L.run_once(L.sliding_load(L.event_stream(spark, d)), "complete")


def load_session(spark, d):
    return L.run_once(L.session_load(L.event_stream(spark, d)), "complete")


def stream_distinct(spark, d):
    """A stream read twice keeps each event once."""
    twice = L.event_stream(spark, d).unionByName(L.event_stream(spark, d))
    return L.run_once(L.distinct_events(twice).select("event_id", "link_id", "amount"))


def stream_static_join(spark, d):
    """Claims joined with their (static) vertex's coordinates."""
    nodes = N.supplier_nodes(spark, d)
    return L.run_once(L.event_stream(spark, d).join(nodes, F.col("link_id") == F.col("v")).select("event_id", "link_id", "x"))


def timeout_idle(spark, d):
    return load_session(spark, d).groupBy("link_id").agg(F.count("*").alias("sessions"), F.max("n").alias("longest"))


def timeout_hard(spark, d):
    return L.run_once(L.hard_timeout(L.event_stream(spark, d)))


QUERIES = {f.__name__: f for f in (load_tumbling, load_sliding, load_session, stream_distinct, stream_static_join, timeout_idle, timeout_hard)}
_SESS = f"""WITH {_C}, marked AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY link_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM c),
 numbered AS (SELECT *, sum(fresh) OVER (PARTITION BY link_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM marked),
 sess AS (SELECT min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS "end", link_id, CAST(sum(amount) AS BIGINT) AS load, count(*) AS n FROM numbered GROUP BY link_id, s)"""
ORACLES = {
    "load_tumbling": f"WITH {_C} SELECT date_trunc('hour', ts) AS start, link_id, CAST(sum(amount) AS BIGINT) AS load FROM c GROUP BY 1, 2",
    "load_sliding": f"WITH {_C}, w AS (SELECT date_trunc('hour', ts) - INTERVAL (k) HOUR AS start, link_id, amount FROM c, (VALUES (0), (1)) t(k)) SELECT start, link_id, CAST(sum(amount) AS BIGINT) AS load FROM w GROUP BY 1, 2",
    "load_session": _SESS + ' SELECT start, "end", link_id, load, n FROM sess',
    "timeout_idle": _SESS + " SELECT link_id, count(*) AS sessions, max(n) AS longest FROM sess GROUP BY link_id",
    "timeout_hard": f"""WITH RECURSIVE {_C}, held AS (SELECT link_id, min(ts) AS opened FROM c GROUP BY link_id
   UNION ALL SELECT h.link_id, min(c.ts) FROM held h JOIN c ON c.link_id = h.link_id AND c.ts >= h.opened + INTERVAL 1 HOUR GROUP BY h.link_id),
 spans AS (SELECT link_id, opened, lead(opened) OVER (PARTITION BY link_id ORDER BY opened) AS next FROM held)
SELECT s.link_id, epoch_us(s.opened) AS opened, CAST(sum(c.amount) AS BIGINT) AS load, count(*) AS n FROM spans s JOIN c ON c.link_id = s.link_id AND c.ts >= s.opened AND (s.next IS NULL OR c.ts < s.next)
WHERE s.next IS NOT NULL OR s.opened + INTERVAL 1 HOUR < {_MARK} GROUP BY s.link_id, s.opened""",
    "stream_distinct": f"WITH {_C} SELECT event_id, link_id, amount FROM c",
    "stream_static_join": f"WITH {_C}, s AS (SELECT s_suppkey AS v, (s_suppkey * 7919 + CAST(s_nationkey AS BIGINT) * 104729) % 1000 AS x FROM supplier) SELECT event_id, link_id, x FROM c JOIN s ON v = link_id",
}
