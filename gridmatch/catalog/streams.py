"""Streams drained over the events table, against the same result in batch."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from ..durable import shared_dir
from ..search.core import ranked
from ..search.shards import hits_of
from ..stream import tiles as S
from ..stream.standing import grow, grown, standing
from ..tables import load
from .base import K, REGION, SPEC, exact_sql, hits, patch, tiles, topk_sql

QUERIES: dict = {}
ORACLES: dict = {}
THETA = 400


def _events(spark, d):
    return S.source(spark, d, "events.parquet")


def _plain(df):
    return df.withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss"))


def stream_tiles(spark, d):
    return _plain(S.drained(S.tile_counts(_events(spark, d))))


def stream_sliding(spark, d):
    return _plain(S.drained(S.tile_counts(_events(spark, d), "24 hours", "4 hours")))


def stream_sessions(spark, d):
    return _plain(S.drained(S.session_strips(_events(spark, d))))


def stream_dedup(spark, d):
    twice = _events(spark, d).union(_events(spark, d))
    return S.drained(S.deduplicated(twice), "append").groupBy("event_type").agg(F.count("*").alias("n"))


def stream_static_join(spark, d):
    """Events as they come, joined with a table that does not change."""
    known = load(spark, d, "customer", "c_custkey", "c_mktsegment")
    joined = _events(spark, d).join(known, F.col("user_id") == F.col("c_custkey"))
    return S.drained(joined.groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.sum(F.floor("value")).alias("v")))


def stream_followed(spark, d):
    """Errors and the purchases of the same user within an hour of them, as two streams."""
    of = lambda kind: _events(spark, d).filter(F.col("event_type") == kind)
    return S.drained(S.followed(of("error"), of("purchase")), "append")


def stream_update(spark, d):
    """Each batch gives the windows it changed; the newest row of a window counts."""
    return _plain(S.drained(S.tile_counts(_events(spark, d)), "update", ["user_id", "start"]))


def stream_standing(spark, d):
    """A standing query over tiles as they come: alerts are the regions of the range search."""
    t = tiles(spark, d)
    path = f"{shared_dir(spark).rstrip('/')}/tiles-{uuid.uuid4().hex}"
    t.write.parquet(path)
    found = standing(spark.readStream.schema(t.schema).parquet(path), patch(t), THETA, SPEC)
    return hits(S.drained(found, "append"))


def stream_grown_store(spark, d):
    """A store that a stream of tiles grew, searched."""
    t = tiles(spark, d)
    path = f"{shared_dir(spark).rstrip('/')}/tiles-{uuid.uuid4().hex}"
    t.write.parquet(path)
    grow(spark.readStream.schema(t.schema).parquet(path), f"{path}.store").awaitTermination()
    found = grown(spark, f"{path}.store").search([patch(t)], K, SPEC, "scan_pruned")
    return hits(ranked(hits_of(found), K))


QUERIES |= {"stream_followed": stream_followed, "stream_update": stream_update, "stream_standing": stream_standing, "stream_grown_store": stream_grown_store}
ORACLES["stream_followed"] = "SELECT a.user_id, a.event_id first_id, b.event_id then_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'error' AND b.event_type = 'purchase'"
QUERIES |= {"stream_static_join": stream_static_join}
ORACLES["stream_static_join"] = "SELECT c_mktsegment, count(*) n, CAST(sum(floor(value)) AS BIGINT) v FROM events JOIN customer ON user_id = c_custkey GROUP BY 1"
QUERIES |= {"stream_tiles": stream_tiles, "stream_sliding": stream_sliding, "stream_sessions": stream_sessions, "stream_dedup": stream_dedup}
ORACLES["stream_tiles"] = "SELECT user_id, strftime(time_bucket(INTERVAL 4 HOUR, ts, TIMESTAMP '2024-01-01'), '%Y-%m-%d %H:%M:%S') start, count(*) n, CAST(sum(floor(value)) AS BIGINT) v FROM events GROUP BY 1, 2"
ORACLES["stream_sliding"] = "SELECT user_id, strftime(time_bucket(INTERVAL 4 HOUR, ts, TIMESTAMP '2024-01-01') - to_hours(CAST(4 * k AS INTEGER)), '%Y-%m-%d %H:%M:%S') start, count(*) n, CAST(sum(floor(value)) AS BIGINT) v FROM events, range(6) g(k) GROUP BY 1, 2"
ORACLES["stream_sessions"] = "WITH a AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(b) OVER (PARTITION BY user_id ORDER BY ts, b DESC ROWS UNBOUNDED PRECEDING) k FROM a) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') start, count(*) n FROM s GROUP BY user_id, k"
ORACLES["stream_dedup"] = "SELECT event_type, count(*) n FROM events GROUP BY 1"
ORACLES["stream_update"] = ORACLES["stream_tiles"]
ORACLES["stream_standing"] = f"WITH {exact_sql('p22')} SELECT image_id, dr, dc, {REGION} FROM best WHERE b.s >= {THETA}"
ORACLES["stream_grown_store"] = topk_sql(exact_sql("p22"))
