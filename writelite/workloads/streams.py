"""Streams drained to the end, against the batch SQL of the same events."""

from __future__ import annotations

from pyspark.sql import functions as F

from writelite.streaming import flows
from writelite.workloads.sorting import table

_CLICKS = "SELECT event_id, user_id FROM events WHERE event_type = 'click'"
_TUMBLING = "SELECT epoch(date_trunc('hour', ts))::BIGINT AS start, event_type, count(*)::BIGINT AS cnt FROM events GROUP BY 1, 2"
_SLIDING = "SELECT start::BIGINT AS start, count(*)::BIGINT AS cnt FROM (SELECT unnest([q, q - 900, q - 1800, q - 2700]) AS start FROM (SELECT (floor(epoch(ts) / 900) * 900)::BIGINT AS q FROM events)) GROUP BY 1"

QUERIES = {
    "stream_scan_watermark": lambda spark, d: flows.run(flows.scan_watermark(flows.source(spark, d))),
    "stream_tumbling": lambda spark, d: flows.latest(flows.run(flows.tumbling(flows.source(spark, d)), "update"), "start", "event_type"),
    "stream_sliding": lambda spark, d: flows.latest(flows.run(flows.sliding(flows.source(spark, d)), "update"), "start"),
    "stream_session": lambda spark, d: flows.run(flows.sessions(flows.source(spark, d))),
    "stream_dedup": lambda spark, d: flows.run(flows.dedup(flows.source(spark, d))),
    "stream_pq": lambda spark, d: flows.run(flows.queue(flows.source(spark, d), flows.BetaQueue())).select("shard", "seq", "k1", "k2"),
    "stream_lazy_compaction": lambda spark, d: flows.run(flows.queue(flows.source(spark, d), flows.BetaQueue())).groupBy("shard").agg(F.max("puts").alias("lazy")).join(flows.run(flows.queue(flows.source(spark, d), flows.EagerQueue())).groupBy("shard").agg(F.max("puts").alias("eager")), "shard").agg(F.lit("lazy_compaction").alias("measure"), (F.sum("lazy") < F.sum("eager")).alias("ok")),
    "stream_timed_compaction": lambda spark, d: flows.run(flows.queue(flows.source(spark, d, 4), flows.TimedQueue(), "EventTime")).where("seq >= 0").select("shard", "seq", "k1", "k2"),
    "stream_static_join": lambda spark, d: flows.run(flows.static_join(flows.source(spark, d), table(spark, d, "customer").select("c_custkey", "c_mktsegment"))),
    "stream_stream_interval_join": lambda spark, d: flows.run(flows.interval_join(flows.source(spark, d))),
    "stream_late_data": flows.dropped_late,
    "stream_running_topk": lambda spark, d: flows.running_top(spark, flows.source(spark, d, 3)),
    "stream_output_modes": lambda spark, d: flows.latest(flows.run(flows.source(spark, d).groupBy("event_type").agg(F.count(F.lit(1)).alias("cnt")), "complete"), "event_type"),
    "stream_restart": flows.restart,
}

SQL = {
    "stream_scan_watermark": _CLICKS,
    "stream_tumbling": _TUMBLING,
    "stream_sliding": _SLIDING,
    "stream_dedup": "SELECT event_id FROM events",
    "stream_lazy_compaction": "SELECT 'lazy_compaction' AS measure, true AS ok",
    "stream_static_join": "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey",
    "stream_stream_interval_join": "SELECT a.event_id AS click_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR",
    "stream_late_data": "SELECT 'late' AS measure, true AS ok",
    "stream_running_topk": "SELECT value, event_id FROM events ORDER BY value DESC, event_id LIMIT 20",
    "stream_output_modes": "SELECT event_type, count(*)::BIGINT AS cnt FROM events GROUP BY 1",
    "stream_restart": _CLICKS,
}
