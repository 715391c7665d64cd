import pandas as pd
from pyspark.sql import functions as F
from topomap.config import MapConfig
from topomap.streaming import streams

SCHEMA = "event_id long, user_id long, ts timestamp, event_type string, value double"


def files(spark, tmp_path, parts):
    for i, rows in enumerate(parts):
        pdf = pd.DataFrame(rows, columns=["event_id", "user_id", "ts", "event_type", "value"])
        pdf["ts"] = pd.to_datetime(pdf["ts"])
        spark.createDataFrame(pdf, SCHEMA).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    return str(tmp_path / "in")


def rows(day, n, start=0):
    return [(start + i, i % 3, f"2024-01-{day:02d} {i % 24:02d}:00:00", "view", 10.0 * i % 97) for i in range(n)]


def featured(spark, path, cut=None):
    return streams.read_events(spark, path, spark.read.parquet(path).schema, cut).withColumn("features", F.array(F.hour("ts") / 24.0, F.col("value") / 100.0))


DAYS = [(1, 30, 0), (2, 20, 100), (3, 10, 200), (9, 1, 300)]


def test_online_map_ignores_batch_cuts(spark, tmp_path):
    path = files(spark, tmp_path, [rows(*d) for d in DAYS])
    cfg, found = MapConfig(2, 2, max_passes=2), []
    for cut in (1, 100):
        out = str(tmp_path / f"out{cut}")
        streams.run_available(streams.online_map(featured(spark, path, cut), cfg), out, str(tmp_path / f"check{cut}"))
        found.append({(str(r["day"]), r["n"], r["fingerprint"]) for r in spark.read.parquet(out).collect()})
    assert found[0] == found[1] and {n for _, n, _ in found[0]} == {30, 20, 10}
    for cut in (1, 100):
        store, out = str(tmp_path / f"store{cut}"), str(tmp_path / f"days{cut}")
        streams.run_online_map(featured(spark, path, cut).select("event_id", "ts", "features"), cfg, store, out, str(tmp_path / f"check-t{cut}"))
        assert {(str(r["day"]), r["n"], r["fingerprint"]) for r in spark.read.parquet(out).collect()} == found[0]


def test_restart_from_a_checkpoint(spark, tmp_path):
    """A stream that stops after half of its files and goes on from its checkpoint gives the maps of one that never stopped."""
    cfg = MapConfig(2, 2, max_passes=2)
    whole = files(spark, tmp_path / "whole", [rows(*d) for d in DAYS])
    streams.run_online_map(featured(spark, whole).select("event_id", "ts", "features"), cfg, str(tmp_path / "s0"), str(tmp_path / "o0"), str(tmp_path / "c0"))
    path = files(spark, tmp_path / "cut", [rows(*d) for d in DAYS[:2]])
    for more in (None, DAYS[2:]):
        if more:
            files(spark, tmp_path / "cut", [rows(*d) for d in more])
        streams.run_online_map(featured(spark, path).select("event_id", "ts", "features"), cfg, str(tmp_path / "s1"), str(tmp_path / "o1"), str(tmp_path / "c1"))
    maps = [{(r["day"], r["n"], r["fingerprint"]) for r in spark.read.parquet(str(tmp_path / o)).collect()} for o in ("o0", "o1")]
    assert maps[0] == maps[1] and len(maps[0]) == 3


def test_output_modes_and_late_rows(spark, tmp_path):
    """Append gives closed windows, update and complete all of them; a row behind the watermark is dropped and counted."""
    path = files(spark, tmp_path, [rows(1, 24), rows(3, 24, 100), rows(1, 1, 900)])
    got = {}
    for mode in ("append", "update", "complete"):
        stream = streams.read_events(spark, path, spark.read.parquet(path).schema, 1)
        counts = streams.window_histograms(stream, F.lit(0), F.lit(0)).select("user_id", F.col("window.start").alias("start"), "n")
        seen = {}
        progress = streams.run_available(counts, "", str(tmp_path / mode), mode, lambda b, i: seen.update({(r["user_id"], str(r["start"])[:10]): r["n"] for r in b.collect()}))
        got[mode] = seen, streams.late_rows(progress)
    first = {(u, "2024-01-01"): 8 for u in range(3)}
    both = first | {(u, "2024-01-03"): 8 for u in range(3)}
    late_one = spark.read.parquet(path).where("event_id = 900").first()["user_id"]
    order_known = got["append"][1] == 1
    assert got["append"][0].keys() == first.keys() and got["update"][0].keys() == both.keys() == got["complete"][0].keys()
    assert got["append"][0] == (first if order_known else got["append"][0]) and got["complete"][0][late_one, "2024-01-01"] == 9 and got["complete"][1] == 0


def test_repeats_within_the_watermark_go(spark, tmp_path):
    path = files(spark, tmp_path, [rows(1, 12) + rows(1, 12)])
    stream = streams.read_events(spark, path, spark.read.parquet(path).schema)
    out = str(tmp_path / "out")
    streams.run_available(streams.without_repeats(stream), out, str(tmp_path / "check"))
    assert spark.read.parquet(out).count() == 12


def test_transitions_keep_state(spark, tmp_path):
    path = files(spark, tmp_path, [rows(1, 24)])
    stream = streams.read_events(spark, path, spark.read.parquet(path).schema).withColumn("node", (F.col("event_id") % 2).cast("int"))
    got = []
    streams.run_available(streams.regime_changes(stream), "", str(tmp_path / "check"), "update", lambda b, i: got.extend(b.collect()))
    assert sum(r["n"] for r in got) == 24 - 3
