"""Streams over events, drained in the query; SQL gives the batch result."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from weftgraph.catalog import query
from weftgraph.plans.common import shared_dir, table
from weftgraph.streaming import feeds


def _source(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, str]:
    events = table(spark, sf_dir, "events")
    path = feeds.replay(spark, events)
    return feeds.stream(spark, path, events.schema), f"{shared_dir(spark).rstrip('/')}/feed-{uuid.uuid4().hex}"


CHANGES = "ch AS (SELECT CASE WHEN event_type = 'error' THEN 'delete' ELSE 'upsert' END AS op, user_id AS src, 1000000 + (props->>'$.k')::BIGINT AS dst, floor(value * 100)::BIGINT AS weight, ts, event_id FROM events), last AS (SELECT src, dst, arg_max(op, (ts, event_id)) AS op, arg_max(weight, (ts, event_id)) AS weight FROM ch GROUP BY src, dst)"


@query(f"WITH {CHANGES} SELECT src, dst, weight FROM last WHERE op = 'upsert'")
def stream_final_state(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges after the upsert feed has been drained in four batches."""
    source, home = _source(spark, sf_dir)
    feed = feeds.UpsertFeed(spark, f"{home}/state")
    feed.run(feeds.changes(source), f"{home}/checkpoint")
    return feed.edges()


@query(f"WITH {CHANGES} SELECT src, dst, weight FROM last WHERE op = 'upsert'")
def batch_final_state(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same feed applied as one batch."""
    return feeds.final_state(None, feeds.changes(table(spark, sf_dir, "events")))


@query("SELECT date_trunc('day', ts) AS start, event_type, count(*) AS n FROM events WHERE ts < date_trunc('day', (SELECT max(ts) FROM events) - INTERVAL 1 HOUR) GROUP BY ALL")
def stream_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily counts that the watermark has closed."""
    source, home = _source(spark, sf_dir)
    return feeds.drain(feeds.windowed_counts(source), "w", "append", f"{home}/checkpoint")


@query("SELECT s AS start, event_type, count(*) AS n FROM (SELECT event_type, unnest([time_bucket(INTERVAL 6 HOUR, ts) - i * INTERVAL 6 HOUR FOR i IN range(4)]) AS s FROM events) t GROUP BY ALL")
def batch_sliding_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts in windows of a day that slide by six hours."""
    return feeds.windowed_counts(table(spark, sf_dir, "events"), "1 day", "6 hours")


SESSIONS = "s AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w >= INTERVAL 2 HOUR THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), g AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM s), t AS (SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 2 HOUR AS \"end\", count(*) AS n FROM g GROUP BY user_id, k)"


@query(f"WITH {SESSIONS} SELECT user_id, start, \"end\", n FROM t")
def batch_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Trips: sessions of a user without a pause of two hours."""
    return feeds.trips(table(spark, sf_dir, "events"))


@query(f"WITH {SESSIONS} SELECT user_id, start, \"end\", n FROM t WHERE \"end\" <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)")
def stream_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Trips that the watermark has closed."""
    source, home = _source(spark, sf_dir)
    return feeds.drain(feeds.trips(source), "s", "append", f"{home}/checkpoint")


@query("SELECT a.user_id, a.event_id AS origin_id, b.event_id AS dest_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR WHERE a.event_type = 'signup' AND b.event_type = 'purchase'")
def stream_interval_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Purchases within six hours of a sign-up, joined as streams."""
    source, home = _source(spark, sf_dir)
    pairs = feeds.interval_pairs(source.where("event_type = 'signup'"), source.where("event_type = 'purchase'"))
    return feeds.drain(pairs, "p", "append", f"{home}/checkpoint")


@query("SELECT count(*) AS n, count(DISTINCT event_id) AS ids FROM events")
def stream_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every event sent twice comes out once."""
    events = table(spark, sf_dir, "events")
    path = feeds.replay(spark, events.unionByName(events))
    home = f"{shared_dir(spark).rstrip('/')}/feed-{uuid.uuid4().hex}"
    got = feeds.drain(feeds.once(feeds.stream(spark, path, events.schema), late="1 day"), "d", "append", f"{home}/checkpoint")
    return got.agg(F.count("*").alias("n"), F.countDistinct("event_id").alias("ids"))


@query(f"WITH {CHANGES}, h AS (SELECT src, arg_max(dst, (ts, event_id)) AS head FROM ch WHERE op = 'upsert' GROUP BY src), d AS (SELECT src, count(*) FILTER (WHERE op = 'upsert') AS degree FROM last GROUP BY src) SELECT src, degree, head FROM d JOIN h USING (src)")
def stream_degrees(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Degree and latest edge of each node, kept as stream state."""
    source, home = _source(spark, sf_dir)
    name = f"deg_{uuid.uuid4().hex}"
    rows = feeds.drain(feeds.degrees(feeds.changes(source)).withColumn("batch_ms", F.lit(0)), name, "update", f"{home}/checkpoint")
    # the memory sink appends updates in order of batches; a node's last row has seen the most
    indexed = rows.drop("batch_ms").withColumn("i", F.monotonically_increasing_id())
    return indexed.groupBy("src").agg(F.max_by(F.struct("degree", "head"), "i").alias("m")).select("src", "m.degree", "m.head")
