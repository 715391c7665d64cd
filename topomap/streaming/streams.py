"""Streams of samples: classification, event-time histograms, and an online map whose result doesn't depend on micro-batch cuts."""

from __future__ import annotations

import json
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.types import IntegerType, StructField, StructType

from ..config import MapConfig
from ..functions.features import joint_histogram
from ..operators.distance import feature_matrix, find_winners
from ..operators.fold import fold_map
from ..operators.model import fingerprint


def read_events(spark: SparkSession, path: str, schema, files_per_trigger: int | None = None) -> DataFrame:
    """Event files as a stream; ``ts`` becomes a timestamp, which watermarks need (session in UTC)."""
    reader = spark.readStream.schema(schema)
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    return reader.parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def classify_stream(stream: DataFrame, prototypes: np.ndarray, features: str = "features") -> DataFrame:
    """Each arriving sample with its node: stateless, K x D constants in the plan."""
    return find_winners(stream, prototypes, features=features)


def without_repeats(stream: DataFrame, late: str = "2 hours") -> DataFrame:
    """One row per event_id among those that arrive within the watermark."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def window_histograms(stream: DataFrame, a, b, *, keys: list[str] = ["user_id"], size: str = "1 day", slide: str | None = None, late: str | None = "2 hours", counted=None) -> DataFrame:  # noqa: B006
    """Joint histograms per key and tumbling or sliding window; rows later than the watermark are dropped."""
    timed = stream.withWatermark("ts", late) if late and stream.isStreaming else stream
    windowed = timed.withColumn("window", F.window("ts", size, slide) if slide else F.window("ts", size))
    return joint_histogram(windowed, [*keys, "window"], a, b, counted=counted)


def session_counts(stream: DataFrame, gap: str = "30 minutes", late: str | None = "2 hours") -> DataFrame:
    """(user_id, start, end, n, total) of sessions that end after ``gap`` of silence."""
    timed = stream.withWatermark("ts", late) if late and stream.isStreaming else stream
    grouped = timed.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return grouped.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "total")


def online_map(stream: DataFrame, cfg: MapConfig, *, features: str = "features", size_days: int = 1, late: str = "2 hours") -> DataFrame:
    """(day, n, fingerprint): each closed day is one training list in the order of event_id, folded when the watermark passes its end.

    What is folded depends on event time only: rows wait in state until their day is closed, however micro-batches cut the stream.
    ``stream`` has event_id, ts and ``features``.
    """
    timed = stream.withWatermark("ts", late).withColumn("day", F.date_trunc("day", "ts"))

    def step(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            ids, flat, dim = state.get
            order = np.argsort(np.array(ids), kind="stable")
            x = np.array(flat).reshape(-1, dim)[order]
            model = fold_map(x, cfg)
            state.remove()
            yield pd.DataFrame({"day": [key[0]], "n": [len(x)], "fingerprint": [fingerprint(model.prototypes)]})
            return
        ids, flat, dim = state.get if state.exists else ([], [], 0)
        ids, flat = list(ids), list(flat)
        for part in parts:
            ids += part["event_id"].tolist()
            for f in part[features]:
                flat += [float(v) for v in f]
                dim = len(f)
        state.update((ids, flat, dim))
        close = int(pd.Timestamp(key[0]).timestamp() * 1000) + size_days * 86_400_000
        state.setTimeoutTimestamp(max(close, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({"day": [], "n": [], "fingerprint": []})

    return timed.select("event_id", "day", "ts", features).groupBy("day").applyInPandasWithState(
        step, "day timestamp, n long, fingerprint string", "ids array<long>, flat array<double>, dim int", "append", GroupStateTimeout.EventTimeTimeout
    )


def fold_days(rows: DataFrame, cfg: MapConfig, features: str = "features") -> DataFrame:
    """(day, n, fingerprint): a map per day, each folded in a task of its own in the order of event_id."""

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by("event_id")
        model = fold_map(feature_matrix(table.column(features).combine_chunks()), cfg)
        return pa.table({"day": table.column("day").slice(0, 1), "n": pa.array([len(table)], pa.int64()), "fingerprint": [fingerprint(model.prototypes)]})

    return rows.select("day", "event_id", features).groupBy("day").applyInArrow(run, "day timestamp, n bigint, fingerprint string")


def run_online_map(stream: DataFrame, cfg: MapConfig, store: str, out: str, checkpoint: str, *, features: str = "features", late: str = "2 hours") -> None:
    """``online_map`` for days that no state holds: open days wait in a table, and what is kept in memory doesn't grow with a day.

    A micro-batch goes to the folder of its number in ``store``; days that its watermark closes are read from there, folded, and written to the folder of
    its number in ``out`` as (day, n, fingerprint). Rows of a closed day are late and dropped. Both writes replace what a batch that failed has left, so a
    restart from ``checkpoint`` gives the same rows.
    """
    spark = stream.sparkSession
    timed = stream.withColumn("day", F.date_trunc("day", "ts"))
    schema = StructType([*timed.schema.fields, StructField("batch", IntegerType())])

    def closed_by(batch: int) -> DataFrame:
        """(day) with rows in ``store`` that lie behind the watermark of the batches up to ``batch``."""
        held = spark.read.schema(schema).parquet(store).where(F.col("batch") <= batch)
        mark = held.agg((F.max("ts") - F.expr(f"INTERVAL {late}")).alias("mark")).first()["mark"]
        return held.select("day").distinct().where(F.lit(mark).isNotNull() & (F.col("day") + F.expr("INTERVAL 1 DAY") <= F.lit(mark)))

    def each(batch: DataFrame, number: int) -> None:
        on_time = batch
        if number:
            on_time = batch.join(F.broadcast(closed_by(number - 1)), "day", "left_anti")
        on_time.write.mode("overwrite").parquet(f"{store}/batch={number}")
        closed = closed_by(number)
        if number:
            closed = closed.join(closed_by(number - 1), "day", "left_anti")
        rows = spark.read.schema(schema).parquet(store).where(F.col("batch") <= number).join(F.broadcast(closed), "day")
        fold_days(rows, cfg, features).write.mode("overwrite").parquet(f"{out}/batch={number}")

    timed.writeStream.option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(each).start().awaitTermination()


def late_rows(progress: list[dict]) -> int:
    """Rows that stateful operators dropped as later than the watermark, from a stream's progress reports."""
    return sum(op["numRowsDroppedByWatermark"] if isinstance(op, dict) else op.numRowsDroppedByWatermark for p in progress for op in p["stateOperators"])


def regime_changes(classified: DataFrame, late: str = "2 hours") -> DataFrame:
    """(user_id, before, after, n): transitions between the nodes of a user's events in time order, kept in state across micro-batches."""
    timed = classified.withWatermark("ts", late)

    def step(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        last = state.get[0] if state.exists else -1
        rows = pd.concat(list(parts)).sort_values(["ts", "event_id"])
        nodes = [last, *rows["node"].tolist()] if last >= 0 else rows["node"].tolist()
        state.update((int(nodes[-1]),))
        pairs = pd.DataFrame({"before": nodes[:-1], "after": nodes[1:]})
        counts = pairs.groupby(["before", "after"]).size().reset_index(name="n")
        counts.insert(0, "user_id", key[0])
        yield counts

    return timed.select("user_id", "event_id", "ts", "node").groupBy("user_id").applyInPandasWithState(step, "user_id long, before long, after long, n long", "last int", "update", GroupStateTimeout.NoTimeout)


def with_regime_attributes(stream: DataFrame, attributes: DataFrame) -> DataFrame:
    """Stream-static join: a regime's attributes beside each classified sample."""
    return stream.join(F.broadcast(attributes), "node", "left")


def joined_within(left: DataFrame, right: DataFrame, key: str, interval: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """Stream-stream join: right events of the same key at most ``interval`` after a left one."""
    a = left.withWatermark("ts", late).select(F.col(key), F.col("event_id").alias("left_id"), F.col("ts").alias("left_ts"))
    b = right.withWatermark("ts", late).select(F.col(key).alias("right_key"), F.col("event_id").alias("right_id"), F.col("ts").alias("right_ts"))
    near = (F.col(key) == F.col("right_key")) & (F.col("right_ts") >= F.col("left_ts")) & (F.col("right_ts") <= F.col("left_ts") + F.expr(f"INTERVAL {interval}"))
    return a.join(b, near).drop("right_key")


def run_available(stream: DataFrame, path: str, checkpoint: str, mode: str = "append", each: Callable | None = None) -> list[dict]:
    """Runs what is there into Parquet files (or ``each(batch, id)``) and stops; gives the progress reports."""
    writer = stream.writeStream.option("checkpointLocation", checkpoint).trigger(availableNow=True).outputMode(mode)
    started = writer.foreachBatch(each).start() if each else writer.format("parquet").option("path", path).start()
    started.awaitTermination()
    return [p if isinstance(p, dict) else json.loads(p.json) for p in started.recentProgress]
