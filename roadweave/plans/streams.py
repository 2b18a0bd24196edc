"""Streaming queries; where the stream's last word equals a batch query, its SQL says so."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..sources.tables import table
from ..streaming import flows
from .registry import Catalog

catalog = Catalog()
add = catalog.add


@add("SELECT user_id AS t, json_extract(props, '$.k')::BIGINT AS s, count(*) AS n FROM events GROUP BY 1, 2")
def stream_edges_update(spark, d):
    return flows.latest(flows.run(flows.edge_counts(flows.events(spark, d)), "edges", mode="complete"))


@add("SELECT time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01') AS start, count(*) AS n, round(sum(value), 4) AS value FROM events GROUP BY 1")
def stream_tumbling(spark, d):
    own = flows.latest(flows.run(flows.tumbling(flows.events(spark, d), "1 day"), "tumbling", mode="complete"))
    return own.withColumn("start", F.col("start").cast("timestamp_ntz"))


@add("SELECT time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '1970-01-01') - INTERVAL 12 HOUR * i AS start, count(*) AS n, round(sum(value), 4) AS value FROM events, (SELECT unnest([0, 1]) AS i) GROUP BY 1")
def stream_sliding(spark, d):
    own = flows.latest(flows.run(flows.tumbling(flows.events(spark, d), "24 hours", "12 hours"), "sliding", mode="complete"))
    return own.withColumn("start", F.col("start").cast("timestamp_ntz"))


@add("WITH g AS (SELECT user_id, ts, CASE WHEN lag(ts) OVER w IS NULL OR ts - lag(ts) OVER w >= INTERVAL 24 HOUR THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), x AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS trip FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM x GROUP BY user_id, trip")
def stream_session(spark, d):
    own = flows.latest(flows.run(flows.sessions(flows.events(spark, d), "24 hours"), "session", mode="complete"))
    return own.withColumn("start", F.col("start").cast("timestamp_ntz"))


@add(
    "WITH w AS (SELECT time_bucket(INTERVAL 1 HOUR, ts, TIMESTAMP '1970-01-01') AS start, count(*) AS n, round(sum(value), 4) AS value FROM events GROUP BY 1) "
    "SELECT * FROM w WHERE start + INTERVAL 1 HOUR <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)"
)
def stream_watermark_late_drop(spark, d):
    """Windows that the watermark has closed; what comes after it is dropped."""
    own = flows.run(flows.tumbling(flows.events(spark, d).withWatermark("ts", "1 hour"), "1 hour"), "late")
    return own.withColumn("start", F.col("start").cast("timestamp_ntz"))


@add("SELECT event_id, user_id FROM events")
def stream_dedup(spark, d):
    """Events that come twice count once."""
    own = flows.events(spark, d)
    return flows.run(own.union(own).withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"), "dedup")


@add("SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")
def stream_static_join(spark, d):
    people = table(spark, d, "customer").select("c_custkey", "c_mktsegment")
    own = flows.events(spark, d).join(people, F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment")
    return flows.run(own, "static")


@add("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 2 HOUR")
def stream_stream_interval_join(spark, d):
    own = flows.events(spark, d)
    clicks = own.where("event_type = 'click'").select(F.col("event_id").alias("a"), F.col("user_id").alias("u"), F.col("ts").alias("early")).withWatermark("early", "3 hours")
    buys = own.where("event_type = 'purchase'").select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("late")).withWatermark("late", "3 hours")
    return flows.run(clicks.join(buys, F.expr("u = user_id and late >= early and late <= early + interval 2 hours")).select("a", "b"), "interval")


@add("WITH x AS (SELECT user_id % 4 AS ct, (json_extract(props, '$.k')::BIGINT // 25) AS cs, count(*) AS m FROM events GROUP BY 1, 2), p AS (SELECT ct, cs, m / sum(m) OVER () AS p, sum(m) OVER (PARTITION BY ct) / sum(m) OVER () AS pt, sum(m) OVER (PARTITION BY cs) / sum(m) OVER () AS ps FROM x) SELECT ct, cs, round(p * ln(p / (pt * ps)), 6) AS mi FROM p")
def stream_mi_monitor(spark, d):
    block = flows.latest(flows.run(flows.monitor(flows.events(spark, d)), "monitor", mode="complete"))
    return flows.monitored(block).select("ct", "cs", F.round("mi", 6).alias("mi"))


@add(
    "WITH g AS (SELECT user_id, event_id, ts, CASE WHEN lag(ts) OVER w IS NULL OR ts - lag(ts) OVER w > INTERVAL 24 HOUR THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), x AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS trip FROM g), "
    "trips AS (SELECT user_id, trip, epoch(min(ts)) AS first, epoch(max(ts)) AS last, count(*) AS n, lead(trip) OVER (PARTITION BY user_id ORDER BY trip) AS next FROM x GROUP BY user_id, trip) "
    "SELECT user_id, first, last, n FROM trips WHERE next IS NOT NULL OR last + 86400 <= (SELECT epoch(max(ts)) - 3600 FROM events)"
)
def stream_trip_state(spark, d):
    """Trips that state of our own has closed."""
    return flows.run(flows.trip_states(flows.events(spark, d)), "trips")


@add()
def stream_assign(spark, d):
    """New trips go to the clusters of a model fitted on earlier ones."""
    from ..model import BipartiteGraph
    from ..operators import cocluster
    from ..sources.tables import session_cells

    model = cocluster.fit(session_cells(spark, d), restarts=0, refine=False)
    counts = flows.latest(flows.run(flows.edge_counts(flows.events(spark, d)), "assign", mode="complete"))
    return cocluster.assign(model, BipartiteGraph(counts.withColumn("length", F.lit(1.0))))
