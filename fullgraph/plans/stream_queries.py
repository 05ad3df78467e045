"""Streams drained over the replayed events; their SQL is the batch twin."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import aggregate
from ..sources import graphs
from ..sources.tables import load
from ..streaming import events as ev
from .graph_queries import FEAT_SQL, G2_SQL, as_sums, g2_features, query

# Complete output: every window is final once the source is drained.
query("stream_tumbling", "SELECT date_trunc('hour', ts) AS start, event_type, count(*)::BIGINT AS n, sum(round(value * 100)::BIGINT)::BIGINT AS cents FROM events GROUP BY 1, 2")(
    lambda s, d: ev.drained(ev.tumbling(ev.replay(s, d)), "complete").withColumn("start", F.col("start").cast("timestamp_ntz"))
)
query("stream_sliding", "SELECT date_trunc('hour', ts) - to_hours(o) AS start, count(*)::BIGINT AS n FROM events, (VALUES (0), (1)) t(o) GROUP BY 1")(
    lambda s, d: ev.drained(ev.sliding(ev.replay(s, d)), "complete").withColumn("start", F.col("start").cast("timestamp_ntz"))
)
query(
    "stream_session",
    """WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events),
n AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g) SELECT user_id, min(ts) AS start, count(*)::BIGINT AS n FROM n GROUP BY user_id, k""",
)(lambda s, d: ev.drained(ev.sessions(ev.replay(s, d)), "complete").withColumn("start", F.col("start").cast("timestamp_ntz")))
query("stream_dedup", "SELECT DISTINCT event_id, user_id FROM events")(lambda s, d: ev.drained(ev.unique_events(ev.replay(s, d))))
query("stream_static_join", "SELECT event_id, user_id, (user_id % 8)::INT AS part FROM events")(
    lambda s, d: ev.drained(ev.with_part(ev.replay(s, d), load(s, d, "events").select(F.col("user_id").alias("id")).distinct().select("id", F.pmod("id", F.lit(8)).cast("int").alias("part"))))
)
query("stream_stream_join", "SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")(
    lambda s, d: (lambda r: ev.drained(ev.click_to_purchase(r, r)))(ev.replay(s, d))
)
query("stream_user_state", "SELECT user_id, count(*)::BIGINT AS n, epoch_us(max(ts))::BIGINT AS last_micros FROM events GROUP BY 1")(lambda s, d: ev.final_user_counts(ev.replay(s, d)))


@query(
    "incremental_refresh",
    f"WITH {G2_SQL}, {FEAT_SQL} SELECT e.dst, k, sum(x + CASE WHEN e.src % 10 = 0 THEN 1048576 ELSE 0 END)::BIGINT AS s FROM e JOIN fx ON fx.id = e.src GROUP BY e.dst, k",
)
def incremental_refresh(s: SparkSession, d: str) -> DataFrame:
    e = graphs.part_supplier(s, d).edges
    f = g2_features(s, d)
    old = as_sums(aggregate.spmm(e, f))
    changed = f.filter("id % 10 = 0").select("id", F.explode(F.array(F.lit(0), F.lit(1), F.lit(2))).alias("k"), F.lit(1 << 20).cast("long").alias("dx"))
    return ev.refresh_sums(e, old, changed)
