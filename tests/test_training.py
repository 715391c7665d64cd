from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F
from topomap.config import MapConfig
from topomap.operators import schedule, train
from topomap.operators.fold import fold_map, show
from topomap.operators.grid import init_gradient, initial_radius, neighbourhood
from topomap.operators.model import MapModel
from topomap.operators.train import fit_map
from topomap.sources import workloads

TOY = np.array(workloads.TOYBLOBS)
CFG = MapConfig(3, 1, max_passes=24)


def test_gradient_start():
    assert init_gradient(2, 2, 1).ravel().tolist() == [0.0, 1 / np.sqrt(2), 1 / np.sqrt(2), 1.0]
    assert init_gradient(1, 1, 3).tolist() == [[0.0, 0.0, 0.0]]
    assert init_gradient(4, 3, 42)[-1].tolist() == [1.0] * 42


def test_schedules():
    assert schedule.radius_at(0, 40, initial_radius(4, 3)) == 1.5
    assert schedule.radius_at(40, 40, 1.5) == 1.0 and schedule.radius_at(40, 40, 0.5) == 1.0
    assert schedule.rate_at(40, 40, 0.1) == pytest.approx(0.1 / np.e)
    w = schedule.weights_at(0, 40, 4, 3, 0.1)
    assert np.diag(w).tolist() == [0.1] * 12 and (w >= 0).all() and (w <= 0.1).all()
    assert sorted(neighbourhood(4, 1.0, 4, 3)) == [1, 3, 4, 5, 7]
    assert len(neighbourhood(4, 1.5, 4, 3)) == 9 and len(neighbourhood(4, 1.0, 4, 3, "square")) == 9


def test_one_update_by_hand():
    v = np.array([[0.0, 0.0], [1.0, 1.0]])
    winners = np.array([-1])
    assert show(v, np.array([[0.2, 0.4]]), [0], np.array([[0.5, 0.25], [0.25, 0.5]]), winners) == 1
    assert v.tolist() == [[0.1, 0.2], [0.8, 0.85]] and winners.tolist() == [0]


@pytest.mark.parametrize("grid,moves", [((2, 2), [24, 0]), ((3, 1), [24, 8, 0]), ((3, 2), [24, 8, 1, 7, 0]), ((4, 3), [24, 0])])
def test_nothing_moves_on_separate_blobs(grid, moves):
    state = fold_map(TOY, MapConfig(*grid, max_passes=24))
    assert [h["moves"] for h in state.history] == moves and state.stop_reason == "no_moves"


def test_ties_go_to_the_lowest_node():
    state = fold_map(np.array([[0.5]]), MapConfig(2, 2, max_passes=1, horizon=2))
    assert state.winners.tolist() == [1]


def test_prototypes_stay_in_the_unit_cube():
    p = fold_map(TOY, MapConfig(4, 3, max_passes=10, initial_rate=1.0)).prototypes
    assert p.min() >= 0 and p.max() <= 1


def test_modes_agree_to_the_bit(spark):
    df = workloads.toy(spark)
    prints = {fit_map(df, CFG, key=["sample_id"], mode=m, **o).fingerprint for m, o in (("fold", {}), ("relay", {"block": 7}), ("expr", {}))}
    assert prints == {fit_map(df, CFG, key=["sample_id"]).fingerprint}


@pytest.mark.parametrize("settings", [{}, {"selection": "sequential", "moves": "frozen"}, {"clock": "sample"}, {"selection": "random", "seed": 1}])
def test_longer_lists_keep_the_serial_semantics(spark, monkeypatch, settings):
    df = workloads.toy(spark)
    cfg = replace(CFG, max_passes=3, **settings)
    exact = fit_map(df, cfg, key=["sample_id"], mode="fold")
    monkeypatch.setattr(train, "FOLD_NUMBERS", TOY.size // 3)
    model = fit_map(df, cfg, key=["sample_id"])
    assert model.fingerprint == exact.fingerprint and [h["moves"] for h in model.history] == [h["moves"] for h in exact.history]


def test_layout_does_not_matter_and_seeds_do(spark):
    df = workloads.toy(spark)
    cfg = replace(CFG, max_passes=3)
    prints = {fit_map(d, cfg, key=["sample_id"]).fingerprint for d in (df, df.repartition(5), df.orderBy(F.desc("sample_id")), df.select("features", "sample_id"))}
    assert len(prints) == 1
    seeded = [fit_map(df, replace(cfg, init="random", selection="random", seed=s), key=["sample_id"]).fingerprint for s in (1, 2, 1)]
    assert seeded[0] == seeded[2] != seeded[1]
    batch = {fit_map(d, replace(cfg, max_passes=2), key=["sample_id"], mode="batch").fingerprint for d in (df, df.repartition(5))}
    shards = {fit_map(d, cfg, key=["sample_id"], mode="shards", shards=3).fingerprint for d in (df, df.repartition(5))}
    assert len(batch) == len(shards) == 1


def test_bad_records(spark):
    rows = [(0, [0.1, 0.2]), (1, None), (2, [0.0, 0.0]), (3, [float("nan"), 0.1]), (4, [None, 0.2]), (5, [0.3, 0.4])]
    df = spark.createDataFrame(rows, "sample_id long, features array<double>")
    assert [h["moves"] for h in fit_map(df, MapConfig(1, 1, max_passes=1), key=["sample_id"]).history] == [2]
    with pytest.raises(Exception, match="all zero"):
        fit_map(df, MapConfig(1, 1, max_passes=1, on_missing="error"), key=["sample_id"])
    with pytest.raises(ValueError, match="components"):
        fit_map(spark.createDataFrame([(0, [0.1]), (1, [0.1, 0.2])], df.schema), CFG, key=["sample_id"])
    with pytest.raises(ValueError, match="empty"):
        fit_map(df.limit(0), CFG, key=["sample_id"])
    with pytest.raises(ValueError, match="scale"):
        fit_map(spark.createDataFrame([(0, [1.5])], df.schema), CFG, key=["sample_id"])


def test_model_round_trip(spark, tmp_path):
    model = fit_map(workloads.toy(spark), CFG, key=["sample_id"])
    model.save(spark, str(tmp_path / "m"))
    again = MapModel.load(spark, str(tmp_path / "m"))
    assert again.fingerprint == model.fingerprint and again.cfg == model.cfg and again.stop_reason == "no_moves"


def test_estimator_and_winner_function(spark):
    from topomap.plans.sqlapi import TopologyMap, register, register_winner

    df = workloads.toy(spark)
    fitted = TopologyMap("sample_id", rows=3, cols=1, max_passes=24).fit(df)
    nodes = {r["sample_id"]: r["node"] for r in fitted.transform(df).collect()}
    register_winner(spark, "toy_winner", fitted.model.prototypes)
    df.createOrReplaceTempView("toy_points")
    assert nodes == {r[0]: r[1] for r in spark.sql("SELECT sample_id, toy_winner(features) FROM toy_points").collect()}
    register(spark)
    assert spark.sql("SELECT * FROM grid(2, 3)").count() == 6


def test_kmeans_against_numpy(spark):
    from topomap.operators.baselines import fit_kmeans

    df = workloads.toy(spark).withColumnRenamed("sample_id", "sample_index")
    centers, _ = fit_kmeans(df, 3, init="maxmin")
    x, c = TOY, TOY[[0]]
    while len(c) < 3:
        c = np.vstack([c, x[((x[:, None] - c[None]) ** 2).sum(2).min(1).argmax()]])
    for _ in range(20):
        w = ((x[:, None] - c[None]) ** 2).sum(2).argmin(1)
        c = np.array([x[w == k].mean(0) for k in range(3)])
    assert np.allclose(centers, c, atol=1e-6)


def test_registered_sketch_has_the_default_sample(spark):
    from topomap.plans import catalogue

    sf = "/root/testdata/sf0.01"
    docs = catalogue.docs_v(spark, sf)
    rows = lambda df: sorted(map(tuple, df.collect()))
    small = catalogue._trained(docs, ["doc_id"], catalogue.SHORT, mode="sketch", sample=300)[1]
    whole = catalogue._trained(docs, ["doc_id"], catalogue.SHORT, mode="sketch")[1]
    assert rows(catalogue.queries()["sketch_map_docs"](spark, sf)) == rows(whole) != rows(small)


def test_relay_visits_are_few(spark, monkeypatch):
    """Twelve blocks a pass are at most eight jobs a pass, and give the bits of a fold."""
    labels, real = [], train.written
    monkeypatch.setattr(train, "written", lambda df, label: (labels.append(label), real(df, label))[1])
    cfg = replace(CFG, max_passes=2)
    model = fit_map(workloads.toy(spark), cfg, key=["sample_id"], mode="relay", block=2)
    assert model.fingerprint == fit_map(workloads.toy(spark), cfg, key=["sample_id"]).fingerprint and labels.count("relay-visit") <= 16
