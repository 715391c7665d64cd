"""Training in its physical modes.

``fold``, ``relay`` and ``expr`` keep the serial semantics and give the same bits, and ``auto`` takes fold or, for longer lists, relay: fold runs all passes in one task, relay carries the
prototypes from block to block of a list that fits no task, expr is one Catalyst expression for small lists. ``batch``, ``shards`` and
``sketch`` are extensions for lists too long for a serial method, for callers who name them: order-free rounds with exact sums, a merge of maps of index ranges, and a hash sample
followed by batch rounds.
"""

from __future__ import annotations

import json
import time
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import MapConfig, grid_from_density
from ..sources.scratch import discard, written
from .distance import feature_matrix, find_winners, nearest_two
from .fold import fold_map, history_row, pass_weights, show, start_prototypes
from .grid import distance_matrix
from .model import MapModel
from .ordering import dense_index, order_of, staggered_position, start_index
from .schedule import influence, radius_at, weights_at

#: Training lists up to so many numbers (8 bytes each) fold in one task.
FOLD_NUMBERS = 200_000_000
#: Samples in a block of a longer list, or fewer where so many don't fit a task.
RELAY_ROWS = 1_000_000
#: Jobs of a pass over a longer list.
VISITS = 8
SKETCH_ROWS = 100_000
EXPR_ROWS = 100_000
#: Fixed point of order-free sums: features in [0, 1] times this, as integers.
FIXED = 1 << 24


def checked(df: DataFrame, features: str, on_missing: str) -> DataFrame:
    """Without null, ragged-null, NaN and all-zero records; ``error`` raises instead."""
    x = F.col(features)
    good = x.isNotNull() & ~F.exists(x, lambda v: v.isNull() | F.isnan(v)) & F.exists(x, lambda v: v != 0)
    if on_missing == "error":
        return df.where(F.when(F.coalesce(good, F.lit(False)), F.lit(True)).otherwise(F.raise_error(F.lit("a record is null, has a null or NaN component, or is all zero")).cast("boolean")))
    return df.where(F.coalesce(good, F.lit(False)))


def shape_of(df: DataFrame, features: str) -> tuple[int, int]:
    """(rows, components); components must be equal throughout and lie in [0, 1]."""
    row = df.agg(F.count("*").alias("n"), F.min(F.size(features)).alias("lo"), F.max(F.size(features)).alias("hi"), F.min(F.array_min(features)).alias("least"), F.max(F.array_max(features)).alias("most")).first()
    if not row["n"]:
        raise ValueError("an empty training list has no map")
    if row["lo"] != row["hi"]:
        raise ValueError(f"records have {row['lo']} to {row['hi']} components")
    if row["least"] < 0 or row["most"] > 1:
        raise ValueError("features must lie in [0, 1]; scale them first")
    return row["n"], row["lo"]


def fit_map(df: DataFrame, cfg: MapConfig, *, key: list[str], features: str = "features", mode: str = "auto", given: np.ndarray | None = None, **options) -> MapModel:
    """Trains a map on ``df``; the training list is ``df`` in the order of ``key``, which must be unique."""
    data = checked(df.select(*key, features), features, cfg.on_missing)
    n, dim = shape_of(data, features)
    cfg = cfg.resolved(n)
    if mode == "auto":
        mode = "fold"
        # the same bits, in blocks that fit a task; a random order has no blocks
        if n * dim > FOLD_NUMBERS and cfg.selection in ("staggered", "sequential"):
            mode, options = "relay", {"block": max(1, min(RELAY_ROWS, FOLD_NUMBERS // dim))} | options
    if mode == "fold":
        return _fit_fold(data, cfg, key, features, given)
    if mode == "batch":
        return fit_batch(data, cfg, features, dim, given, **options)
    indexed = dense_index(data, key).select("sample_index", F.col(features).alias("features"))
    return {"relay": fit_relay, "expr": fit_expr, "shards": fit_shards, "sketch": fit_sketch}[mode](indexed, cfg, n, dim, given, **options)


def fit_self_tuned(df: DataFrame, per_node: float, initial_rate: float, *, key: list[str], features: str = "features", **options) -> MapModel:
    """Only samples per node and the initial rate are given: the grid follows from the list length, and so does the horizon."""
    n = checked(df, features, "drop").count()
    rows, cols = grid_from_density(n, per_node)
    return fit_map(df, MapConfig(rows, cols, initial_rate, **options), key=key, features=features)


def _fit_fold(data: DataFrame, cfg: MapConfig, key: list[str], features: str, given) -> MapModel:
    """One task sorts the list and folds all passes; K x D numbers and the history come back."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [feature_matrix(b.column(features)) for b in batches if len(b)]
        if parts:
            state = fold_map(np.concatenate(parts), cfg, given)
            yield pa.RecordBatch.from_arrays([pa.array([state.prototypes.ravel().tolist()]), pa.array([json.dumps({"history": state.history, "stop": state.stop_reason})])], ["prototypes", "log"])

    row = data.repartition(1).sortWithinPartitions(*key).select(features).mapInArrow(run, "prototypes array<double>, log string").first()
    log = json.loads(row["log"])
    return MapModel(np.array(row["prototypes"]).reshape(cfg.nodes, -1), cfg, log["history"], log["stop"])


def iter_blocks(t: int, n: int, block: int) -> list[tuple[int, int, int]]:
    """(first index, last index, step) pieces of a staggered pass over blocks of ``block`` samples: the first block may come twice, as its tail and its head."""
    start, step = start_index(t, n), 1 if t % 2 == 0 else -1
    out, left, i = [], n, start
    while left:
        edge = min(n - 1, (i // block + 1) * block - 1) if step > 0 else (i // block) * block
        take = min(left, abs(edge - i) + 1)
        out.append((i, i + step * (take - 1), step))
        left -= take
        i = (i + step * take) % n
    return out


def fit_relay(indexed: DataFrame, cfg: MapConfig, n: int, dim: int, given=None, *, block: int = RELAY_ROWS) -> MapModel:
    """The list is written once; a pass shows its blocks in order and carries the prototypes on.

    A pass is at most ``VISITS`` jobs of consecutive blocks, whatever their number. A job is one task that sorts its rows on disk and shows them batch by
    batch, so it holds no more than a batch. Winners of a pass are written and joined to the next one; the driver sees prototypes and counts only.
    """
    if cfg.selection not in ("staggered", "sequential"):
        raise ValueError("relay shows blocks in staggered or sequential order")
    listed = written(indexed.select("sample_index", "features"), "relay-list")
    prototypes, history, reason = start_prototypes(cfg, dim, given), [], ""
    winners: DataFrame | None = None
    at = F.col("sample_index")
    for t in range(cfg.max_passes):
        began, moves, seen, shown, before = time.perf_counter(), 0, [], 0, prototypes
        turn = t if cfg.selection == "staggered" else 0
        pieces = iter_blocks(turn, n, block)
        weights = pass_weights(cfg, t, n)
        size = -(-len(pieces) // VISITS)
        for visit in (pieces[i : i + size] for i in range(0, len(pieces), size)):
            length = sum(abs(hi - lo) + 1 for lo, hi, _ in visit)
            place = staggered_position(at, n, turn)
            rows = listed.where(_inside(visit))
            if winners is not None:
                rows = rows.join(winners.where(_inside(visit)), "sample_index", "left")
            else:
                rows = rows.withColumn("winner", F.lit(-1))
            rows = rows.select("sample_index", "features", F.coalesce("winner", F.lit(-1)).alias("winner"), place.alias("place"))
            rows = rows.repartition(1).sortWithinPartitions("place").select("sample_index", "features", "winner")
            out = written(rows.mapInArrow(_relay_step(prototypes, weights, shown), "sample_index bigint, winner int, prototypes array<double>, moves bigint"), "relay-visit")
            told = out.where("prototypes is not null").first()
            prototypes, moves = np.array(told["prototypes"]).reshape(cfg.nodes, dim), moves + told["moves"]
            seen.append(out)
            shown += length
        if winners is not None:
            discard(*last)
        last, winners = seen, reduce(DataFrame.union, [s.where("prototypes is null").select("sample_index", "winner") for s in seen])
        if cfg.moves == "frozen":
            moves = _frozen_moves(listed, prototypes, before) if t else n
        history.append(history_row(cfg, t, n, moves, time.perf_counter() - began))
        if cfg.stop == "no_moves" and t and not moves:
            reason = "no_moves"
            break
    discard(listed, *last)
    return MapModel(prototypes, cfg, history, reason or ("horizon" if cfg.max_passes == cfg.horizon else "max_passes"))


def _inside(pieces: list[tuple[int, int, int]]) -> Column:
    """Samples of consecutive pieces, as few ranges of the index: a pass wraps around once."""
    ranges: list[list[int]] = []
    for lo, hi in sorted((min(a, b), max(a, b)) for a, b, _ in pieces):
        if ranges and lo == ranges[-1][1] + 1:
            ranges[-1][1] = hi
        else:
            ranges.append([lo, hi])
    return reduce(Column.__or__, [F.col("sample_index").between(lo, hi) for lo, hi in ranges])


def _frozen_moves(blocks: DataFrame, now: np.ndarray, before: np.ndarray) -> int:
    """Samples whose nearest prototype after a pass isn't the one before it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if len(b):
                x = feature_matrix(b.column("features"))
                yield pa.RecordBatch.from_arrays([pa.array([int((nearest_two(x, now)[0] != nearest_two(x, before)[0]).sum())], pa.int64())], ["moves"])

    return blocks.select("features").mapInArrow(run, "moves bigint").agg(F.sum("moves")).first()[0]


def _relay_step(prototypes: np.ndarray, weights, shown: int):
    """Rows in the order of the pass, ``shown`` of which came before: their winners, then a row with the prototypes and the number of moves."""
    names = ["sample_index", "winner", "prototypes", "moves"]
    kinds = [pa.int64(), pa.int32(), pa.list_(pa.float64()), pa.int64()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        moved, moves, done = prototypes.copy(), 0, shown
        for b in batches:
            if not len(b):
                continue
            winners = b.column("winner").to_numpy(zero_copy_only=False).astype(np.int64)
            moves += show(moved, feature_matrix(b.column("features")), range(len(b)), (lambda i, done=done: weights(done + i)) if callable(weights) else weights, winners)
            done += len(b)
            none = [None] * len(b)
            yield pa.RecordBatch.from_arrays([b.column("sample_index"), pa.array(winners.astype(np.int32)), pa.array(none, kinds[2]), pa.array(none, kinds[3])], names)
        yield pa.RecordBatch.from_arrays([pa.array([-1], kinds[0]), pa.array([-1], kinds[1]), pa.array([moved.ravel().tolist()], kinds[2]), pa.array([moves], kinds[3])], names)

    return run


def fit_expr(indexed: DataFrame, cfg: MapConfig, n: int, dim: int, given=None) -> MapModel:
    """A pass is ``aggregate`` over the sorted list with the prototypes as its state: no Python worker. For lists of up to ``EXPR_ROWS`` samples, which are one row."""
    if n > EXPR_ROWS:
        raise ValueError(f"mode expr holds the list in one row: {n} samples are more than {EXPR_ROWS}; use fold or relay")
    prototypes, history, reason = start_prototypes(cfg, dim, given), [], ""
    listed = written(indexed.agg(F.array_sort(F.collect_list(F.struct("sample_index", "features"))).alias("samples")), "expr-list")
    last: list[int] = [-1] * n
    for t in range(cfg.max_passes):
        began = time.perf_counter()
        weights = F.array(*[F.array(*[F.lit(float(x)) for x in row]) for row in weights_at(t, cfg.horizon, cfg.rows, cfg.cols, cfg.initial_rate, cfg.base, cfg.neighbourhood)])
        order = F.array(*[F.lit(int(i)) for i in order_of(cfg.selection, n, t, cfg.seed)])
        start = F.struct(F.array(*[F.array(*[F.lit(float(x)) for x in p]) for p in prototypes]).alias("v"), F.array().cast("array<int>").alias("w"))
        row = listed.select(F.aggregate(order, start, lambda s, i: _expr_step(s, F.get("samples", i)["features"], weights)).alias("s")).first()["s"]
        prototypes = np.array(row["v"])
        winners = [0] * n
        for i, w in zip(order_of(cfg.selection, n, t, cfg.seed), row["w"]):
            winners[int(i)] = w
        moves = sum(a != b for a, b in zip(winners, last))
        last = winners
        history.append(history_row(cfg, t, n, moves, time.perf_counter() - began))
        if cfg.stop == "no_moves" and t and not moves:
            reason = "no_moves"
            break
    return MapModel(prototypes, cfg, history, reason or ("horizon" if cfg.max_passes == cfg.horizon else "max_passes"))


def _expr_step(state: Column, f: Column, weights: Column) -> Column:
    d2 = F.transform(state["v"], lambda v: F.aggregate(F.zip_with(v, f, lambda a, b: (b - a) * (b - a)), F.lit(0.0), lambda s, x: s + x))
    winner = F.array_position(d2, F.array_min(d2)) - 1
    moved = F.zip_with(state["v"], F.get(weights, winner.cast("int")), lambda v, w: F.zip_with(v, f, lambda a, b: a + w * (b - a)))
    return F.struct(moved.alias("v"), F.concat(state["w"], F.array(winner.cast("int"))).alias("w"))


def exact_node_sums(assigned: DataFrame, dim: int, features: str = "features") -> dict[int, tuple[int, np.ndarray]]:
    """Members and component sums per node, in fixed point: the same whatever the task order. K rows reach the driver."""
    fixed = [F.sum(F.round(F.get(features, i) * FIXED).cast("long")).alias(f"s{i}") for i in range(dim)]
    rows = assigned.groupBy("node").agg(F.count("*").alias("n"), *fixed).collect()
    return {r["node"]: (r["n"], np.array([r[f"s{i}"] for i in range(dim)], dtype=np.float64) / FIXED) for r in rows}


def fit_batch(data: DataFrame, cfg: MapConfig, features: str, dim: int, given=None, *, rounds: int | None = None) -> MapModel:
    """Order-free rounds: winners, exact sums per node, influence-weighted means. One shuffle of at most tasks x K rows a round."""
    prototypes, history, before = start_prototypes(cfg, dim, given), [], None
    distance = distance_matrix(cfg.rows, cfg.cols, cfg.neighbourhood)
    rounds = rounds or cfg.max_passes
    # every round scans the records: what makes them runs once
    data = written(data.select(F.col(features).alias("features")), "batch-records")
    features = "features"
    for t in range(rounds):
        began = time.perf_counter()
        sums = exact_node_sums(find_winners(data.select(features), prototypes, features=features), dim, features)
        radius = radius_at(t, cfg.horizon, min(cfg.rows, cfg.cols) / 2)
        h = np.where(distance <= radius, np.round(influence(distance, radius, cfg.base), 12), 0.0)
        n = int(sum(s[0] for s in sums.values()))
        # samples whose winner isn't the one of the round before
        moves = n if before is None else _frozen_moves(data, prototypes, before)
        moved = prototypes.copy()
        for k in range(cfg.nodes):
            mass = sum(h[j, k] * sums[j][0] for j in sorted(sums))
            if mass > 0:
                moved[k] = sum(h[j, k] * sums[j][1] for j in sorted(sums)) / mass
        before, prototypes = prototypes, moved
        history.append(history_row(cfg, t, max(1, n), moves, time.perf_counter() - began))
        if cfg.stop == "no_moves" and not moves:
            return MapModel(prototypes, cfg, history, "no_moves")
    return MapModel(prototypes, cfg, history, "max_passes")


def fit_shards(indexed: DataFrame, cfg: MapConfig, n: int, dim: int, given=None, *, shards: int = 8) -> MapModel:
    """Index ranges fold side by side; a node's prototype is the mean of the shards' ones, weighted by how much each moved it.

    Shards are ranges of the sample index, never physical partitions, and merge in their order: the result doesn't depend on the layout.
    """
    size = -(-n // shards)
    if size * dim > FOLD_NUMBERS:
        raise ValueError(f"a shard of {size} records fits no task: ask for {-(-n * dim // FOLD_NUMBERS)} shards or more")
    with_shard = indexed.withColumn("shard", F.floor(F.col("sample_index") / size).cast("int"))

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by("sample_index")
        x = feature_matrix(table.column("features").combine_chunks())
        state = fold_map(x, cfg, given)
        mass = np.zeros(cfg.nodes)
        for t in range(len(state.history)):
            weights = pass_weights(cfg, t, len(x))
            mass += np.bincount(state.winners, minlength=cfg.nodes) @ (weights if not callable(weights) else weights(0))
        return pa.table({"shard": pa.array([table.column("shard")[0].as_py()], pa.int32()), "prototypes": pa.array([state.prototypes.ravel().tolist()]), "mass": pa.array([mass.tolist()])})

    rows = sorted(with_shard.groupBy("shard").applyInArrow(run, "shard int, prototypes array<double>, mass array<double>").collect(), key=lambda r: r["shard"])
    start, top, bottom = start_prototypes(cfg, dim, given), np.zeros((cfg.nodes, dim)), np.zeros(cfg.nodes)
    for r in rows:
        mass = np.array(r["mass"])
        top += mass[:, None] * np.array(r["prototypes"]).reshape(cfg.nodes, dim)
        bottom += mass
    merged = np.where(bottom[:, None] > 0, top / np.maximum(bottom, 1e-300)[:, None], start)
    return MapModel(merged, cfg, [], "max_passes")


def fit_sketch(indexed: DataFrame, cfg: MapConfig, n: int, dim: int, given=None, *, sample: int = SKETCH_ROWS, rounds: int = 2) -> MapModel:
    """Folds about ``sample`` records chosen by a hash of their index, then runs batch rounds over all of them.

    Only the sample's size is bounded, as a stated parameter; the rounds and every later classification read all records.
    """
    drawn = indexed.where(F.pmod(F.xxhash64("sample_index"), F.lit(max(1, n // max(1, sample)))) == 0)
    first = _fit_fold(drawn, cfg, ["sample_index"], "features", given)
    if not rounds:
        return first
    from dataclasses import replace

    polished = fit_batch(indexed, replace(cfg, init="given"), "features", dim, first.prototypes, rounds=rounds)
    return MapModel(polished.prototypes, cfg, first.history + polished.history, polished.stop_reason)


def count_moves(before: DataFrame, now: DataFrame, key: list[str]) -> DataFrame:
    """Samples whose node changed, new and vanished ones included, as a one-row table."""
    joined = before.select(*key, F.col("node").alias("was")).join(now.select(*key, F.col("node").alias("is")), key, "full")
    return joined.agg(F.count_if(~F.col("was").eqNullSafe(F.col("is"))).alias("moves"))


__all__ = ["fit_map", "fit_self_tuned", "fit_batch", "count_moves", "exact_node_sums", "iter_blocks", "nearest_two", "checked", "shape_of"]
