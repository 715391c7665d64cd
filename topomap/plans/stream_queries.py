"""Registered streaming queries and their batch twins."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..config import MapConfig
from ..functions.features import drop_invalid
from ..operators.distance import find_winners
from ..operators.grid import grid_frame, init_gradient
from ..sources import workloads
from ..sources.io import load
from ..sources.scratch import scratch_path
from ..streaming import streams
from . import twins as T
from .catalogue import query, r6

_EVENT_FEATURES = "event_v AS (SELECT event_id, row_number() OVER (ORDER BY event_id) - 1 AS sample_index, [hour(ts) / 24.0::DOUBLE, least(1.0::DOUBLE, value / 200.0::DOUBLE)] AS features FROM events)"


def _events(spark, sf_dir):
    return load(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))


def _event_features(df):
    return df.withColumn("features", F.array(F.hour("ts") / 24.0, F.least(F.lit(1.0), F.col("value") / 200.0)))


def _window_sql(starts: str) -> str:
    return f"SELECT user_id, start, count(*) AS n, round(sum(value), 2) AS total FROM ({starts}) GROUP BY user_id, start"


def _windows(spark, sf_dir, *window):
    grouped = _events(spark, sf_dir).groupBy("user_id", F.window("ts", *window).alias("w")).agg(F.count("*").alias("n"), F.round(F.sum("value"), 2).alias("total"))
    return grouped.select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n", "total")


@query(_window_sql("SELECT user_id, value, date_trunc('day', ts)::TIMESTAMP AS start FROM events"))
def event_windows_tumbling(spark, sf_dir):
    return _windows(spark, sf_dir, "1 day")


@query(_window_sql("SELECT user_id, value, time_bucket(INTERVAL '6 hours', ts, TIMESTAMP '1970-01-01') - INTERVAL '6 hours' * k.range AS start FROM events, range(4) k"))
def event_windows_sliding(spark, sf_dir):
    return _windows(spark, sf_dir, "1 day", "6 hours")


@query(
    "SELECT user_id, min(ts) AS start, max(ts) + INTERVAL '30 minutes' AS \"end\", count(*) AS n, round(sum(value), 2) AS total FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s "
    "FROM (SELECT *, (lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) IS NULL OR ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL '30 minutes')::INT AS new FROM events)) GROUP BY user_id, s"
)
def event_windows_session(spark, sf_dir):
    sessions = streams.session_counts(_events(spark, sf_dir), late=None)
    return sessions.select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), F.col("end").cast("timestamp_ntz").alias("end"), "n", F.round("total", 2).alias("total"))


def _stream(spark, sf_dir):
    return streams.read_events(spark, f"{sf_dir}/events*.parquet", load(spark, sf_dir, "events").schema)


@query(T.with_(_EVENT_FEATURES, T.gradient(2), T.winners("won", "event_v", 2)) + "SELECT event_id, node::INT AS node, round(distance, 6) AS distance FROM won")
def stream_classify_events(spark, sf_dir):
    classified = streams.classify_stream(_event_features(_stream(spark, sf_dir)), init_gradient(4, 3, 2)).select("event_id", "node", r6("distance").alias("distance"))
    out = scratch_path(spark, "stream-out")
    streams.run_available(classified, out, scratch_path(spark, "stream-checkpoint"))
    return spark.read.schema(classified.schema).parquet(out)


@query(T.with_(_EVENT_FEATURES, T.gradient(2), T.winners("won", "event_v", 2)) + "SELECT event_id, (node // 3)::INT AS row, (node % 3)::INT AS col FROM won")
def stream_regime_attributes(spark, sf_dir):
    """Stream-static join: each arriving event with the place of its regime on the grid."""
    classified = streams.classify_stream(_event_features(_stream(spark, sf_dir)), init_gradient(4, 3, 2))
    out = scratch_path(spark, "stream-out")
    joined = streams.with_regime_attributes(classified, grid_frame(spark, 4, 3)).select("event_id", "row", "col")
    streams.run_available(joined, out, scratch_path(spark, "stream-checkpoint"))
    return spark.read.schema(joined.schema).parquet(out)


@query("SELECT a.user_id, a.event_id AS left_id, b.event_id AS right_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL '1 hour'")
def stream_views_with_purchases(spark, sf_dir):
    """Stream-stream join: purchases of a user at most an hour after a view."""
    views, purchases = (_stream(spark, sf_dir).where(F.col("event_type") == kind) for kind in ("view", "purchase"))
    pairs = streams.joined_within(views, purchases, "user_id").select("user_id", "left_id", "right_id")
    out = scratch_path(spark, "stream-out")
    streams.run_available(pairs, out, scratch_path(spark, "stream-checkpoint"))
    return spark.read.schema(pairs.schema).parquet(out)


@query(
    T.with_("event_day AS (SELECT epoch_us(date_trunc('day', ts)::TIMESTAMP) AS g, row_number() OVER (PARTITION BY date_trunc('day', ts) ORDER BY event_id) - 1 AS sample_index, [hour(ts) / 24.0::DOUBLE, least(1.0::DOUBLE, value / 200.0::DOUBLE)] AS features FROM events)", "days AS (SELECT count(DISTINCT g) AS n, max(g) AS last FROM event_day)")
    + "SELECT make_timestamp(g)::TIMESTAMP AS day, count(*) AS n FROM event_day, days WHERE g < last GROUP BY g, last"
)
def stream_online_map(spark, sf_dir):
    """Days that the watermark closes, each a training list of its own: all but the last."""
    store, out = scratch_path(spark, "open-days"), scratch_path(spark, "day-maps")
    streams.run_online_map(_event_features(_stream(spark, sf_dir)).select("event_id", "ts", "features"), MapConfig(2, 2, max_passes=1), store, out, scratch_path(spark, "stream-checkpoint"))
    return spark.read.schema("day timestamp, n bigint, fingerprint string").parquet(f"{out}/batch=*").select(F.col("day").cast("timestamp_ntz").alias("day"), "n")


@query(T.with_(T.EVENTS) + f"SELECT user_id, day::TIMESTAMP AS start, n, {T.rounded('features')} AS features FROM events_f")
def stream_window_histogram(spark, sf_dir):
    a, b = workloads.event_classes()
    histograms = streams.window_histograms(_stream(spark, sf_dir), a, b, counted=F.col("event_type") != "error")
    rows = histograms.select("user_id", F.col("window.start").cast("timestamp_ntz").alias("start"), "n", F.transform("features", lambda x: F.round(x, 6)).alias("features"))
    out = scratch_path(spark, "stream-out")

    def keep(batch, _):
        batch.write.mode("overwrite").parquet(out)  # complete mode: the last batch holds every window

    streams.run_available(rows, out, scratch_path(spark, "stream-checkpoint"), "complete", keep)
    return spark.read.schema(rows.schema).parquet(out)


@query(T.with_(T.EVENTS, T.gradient(42), T.winners("won", "events_v", 42)) + "SELECT node::INT AS node, count(*) AS n FROM won GROUP BY node")
def event_day_regimes(spark, sf_dir):
    return find_winners(drop_invalid(workloads.events(spark, sf_dir)), init_gradient(4, 3, 42)).groupBy("node").agg(F.count("*").alias("n"))
