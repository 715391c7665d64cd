"""What the reproducible map is compared with: seeded random runs, k-means, and other learners with the same devices."""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import replace
from functools import reduce
from operator import or_

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import MapConfig
from .distance import feature_matrix, find_winners
from .fold import fold_map, fold_samples
from .model import MapModel
from .train import FOLD_NUMBERS, checked, exact_node_sums, fit_map, shape_of

#: The ablation: standard, with gradient start, with both devices, and the corner left out.
VARIANTS = {
    "standard": {"init": "random", "selection": "random"},
    "gradient": {"init": "gradient", "selection": "random"},
    "gradient_staggered": {"init": "gradient", "selection": "staggered"},
    "random_staggered": {"init": "random", "selection": "staggered"},
}


def variant(cfg: MapConfig, name: str, seed: int = 1) -> MapConfig:
    return replace(cfg, **VARIANTS[name], seed=seed)


def fit_many(df: DataFrame, configs: dict[str, MapConfig], *, key: list[str], features: str = "features") -> dict[str, MapModel]:
    """Several trainings side by side, each a serial fold in a task of its own; the list is sent to each. Lists that fit no task train one after another."""
    spark = df.sparkSession
    n, dim = shape_of(checked(df.select(*key, features), features, "drop"), features)
    if n * dim > FOLD_NUMBERS:
        return {name: fit_map(df, cfg, key=key, features=features) for name, cfg in configs.items()}
    names = spark.createDataFrame([(name,) for name in configs], "run string")
    data = checked(df.select(*key, features), features, "drop")

    def run(table: pa.Table) -> pa.Table:
        name = table.column("run")[0].as_py()
        table = table.sort_by([(k, "ascending") for k in key])
        cfg = configs[name].resolved(len(table))
        state = fold_map(feature_matrix(table.column(features).combine_chunks()), cfg)
        log = json.dumps({"history": state.history, "stop": state.stop_reason})
        return pa.table({"run": [name], "prototypes": pa.array([state.prototypes.ravel().tolist()]), "log": [log]})

    rows = data.crossJoin(F.broadcast(names)).groupBy("run").applyInArrow(run, "run string, prototypes array<double>, log string").collect()
    out = {}
    for r in rows:
        log = json.loads(r["log"])
        cfg = configs[r["run"]]
        out[r["run"]] = MapModel(np.array(r["prototypes"]).reshape(cfg.nodes, -1), cfg, log["history"], log["stop"])
    return out


def standard_runs(df: DataFrame, cfg: MapConfig, seeds: list[int], *, key: list[str]) -> dict[str, MapModel]:
    """The standard map several times with the same parameters but its randomness."""
    return fit_many(df, {str(s): variant(cfg, "standard", s) for s in seeds}, key=key)


def maps_per_group(df: DataFrame, group: str, cfg: MapConfig, *, key: list[str], features: str = "features") -> DataFrame:
    """(group, node, prototype, n): a map per group, each in a task of its own; groups that fit no task, of which there are few, train by relay."""
    kind = df.schema[group].dataType.simpleString()
    counts = df.groupBy(group).agg(F.count("*").alias("n"), F.max(F.size(features)).alias("dim"))
    large = [(r[group], r["n"]) for r in counts.where(F.col("n") * F.col("dim") > FOLD_NUMBERS).collect()]
    if large:
        parts = []
        for value, n in large:
            model = fit_map(df.where(F.col(group).eqNullSafe(F.lit(value))), cfg, key=key, features=features)
            parts.append(model.frame(df.sparkSession).select(F.lit(value).cast(kind).alias(group), "node", "prototype", F.lit(n).cast("long").alias("n")))
        rest = df.where(~reduce(or_, [F.col(group).eqNullSafe(F.lit(v)) for v, _ in large]))
        return reduce(DataFrame.unionByName, [maps_per_group(rest, group, cfg, key=key, features=features), *parts])

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by([(k, "ascending") for k in key])
        x = feature_matrix(table.column(features).combine_chunks())
        state = fold_map(x, cfg)
        k = cfg.nodes
        return pa.table({group: pa.array([table.column(group)[0].as_py()] * k, table.schema.field(group).type), "node": pa.array(range(k), pa.int32()), "prototype": pa.array([p.tolist() for p in state.prototypes]), "n": pa.array([len(x)] * k, pa.int64())})

    return df.select(*dict.fromkeys([group, *key, features])).groupBy(group).applyInArrow(run, f"{group} {kind}, node int, prototype array<double>, n bigint")


def kmeans_start(indexed: DataFrame, k: int, init: str = "first", features: str = "features", seed: int = 0) -> np.ndarray:
    """``first``: the k lowest indices; ``maxmin``: farthest first from index 0, smallest index among equals; ``random``: by a seeded hash."""
    if init == "first":
        rows = indexed.where(F.col("sample_index") < k).orderBy("sample_index").select(features).collect()
        return np.array([r[0] for r in rows])
    if init == "random":
        rows = indexed.orderBy(F.xxhash64(F.lit(seed), "sample_index"), "sample_index").limit(k).select(features).collect()
        return np.array([r[0] for r in rows])
    centers = np.array([indexed.where("sample_index = 0").select(features).first()[0]])
    while len(centers) < k:
        far = find_winners(indexed.select("sample_index", features), centers, features=features, strategy="arrow").orderBy(F.desc("distance"), "sample_index").select(features).first()
        centers = np.vstack([centers, far[0]])
    return centers


def fit_kmeans(indexed: DataFrame, k: int = 10, *, init: str = "first", rounds: int = 20, features: str = "features", seed: int = 0) -> tuple[np.ndarray, int]:
    """Lloyd rounds with exact sums: (centroids, rounds run). ``indexed`` has sample_index. An empty cluster keeps its centroid.

    A round is a scan, a broadcast of k centroids and one shuffle of at most tasks x k rows.
    """
    centers = kmeans_start(indexed, k, init, features, seed)
    for done in range(1, rounds + 1):
        sums = exact_node_sums(find_winners(indexed.select(features), centers, features=features), centers.shape[1], features)
        moved = centers.copy()
        for node, (n, total) in sums.items():
            moved[node] = total / n
        if np.array_equal(moved, centers):
            return centers, done
        centers = moved
    return centers, rounds


def fit_ml_kmeans(df: DataFrame, k: int = 10, *, seed: int = 1, rounds: int = 20, features: str = "features") -> np.ndarray:
    """Spark ML's k-means, as a cross-check."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    model = KMeans(k=k, seed=seed, maxIter=rounds, featuresCol="v").fit(df.select(array_to_vector(features).alias("v")))
    return np.array(model.clusterCenters())


def _folded(df: DataFrame, key: list[str], columns: list[str], learn) -> np.ndarray:
    """What ``learn`` makes of the whole list in the order of ``key``, in one task: serial learners have no other way, so a list that fits no task is refused."""
    n, dim = shape_of(df, columns[0])
    if n * dim > FOLD_NUMBERS:
        raise ValueError(f"{n} records of {dim} numbers fit no task; a serial learner takes at most {FOLD_NUMBERS} numbers")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [b for b in batches if len(b)]
        if parts:
            out = learn(pa.Table.from_batches(parts).combine_chunks())
            yield pa.RecordBatch.from_arrays([pa.array([np.asarray(out).ravel().tolist()]), pa.array([list(np.shape(out))], pa.list_(pa.int64()))], ["state", "shape"])

    row = df.repartition(1).sortWithinPartitions(*key).select(*columns).mapInArrow(run, "state array<double>, shape array<bigint>").first()
    return np.array(row["state"]).reshape(row["shape"])


def fit_online_kmeans(df: DataFrame, k: int, *, key: list[str], order: str = "staggered", init: str = "first", passes: int = 1, seed: int = 1, features: str = "features") -> np.ndarray:
    """Sequential k-means: each sample pulls its nearest centre by one over the centre's count. Starts from the k first samples, or a gradient."""

    def learn(table: pa.Table) -> np.ndarray:
        x = feature_matrix(table.column(features).combine_chunks())
        start = x[:k].copy() if init == "first" else np.repeat((np.arange(k) / max(1, k - 1))[:, None], x.shape[1], axis=1)

        def step(state, row, i, t):
            centers, counts = state
            gap = row - centers
            w = int(np.cumsum(gap * gap, axis=1)[:, -1].argmin())
            counts[w] += 1
            centers[w] += gap[w] / counts[w]
            return state

        return fold_samples(x, (start, np.zeros(k)), step, selection=order, seed=seed, passes=passes)[0]

    return _folded(checked(df, features, "drop").select(*key, features), key, [features], learn)


def fit_sgd_linear(df: DataFrame, label: str, *, key: list[str], order: str = "staggered", l0: float = 0.1, passes: int = 1, seed: int = 1, features: str = "features") -> np.ndarray:
    """Linear least-squares weights (the last is the intercept) by single-sample gradient steps from zero."""

    def learn(table: pa.Table) -> np.ndarray:
        x = feature_matrix(table.column(features).combine_chunks())
        y = table.column(label).to_numpy().astype(np.float64)
        x = np.hstack([x, np.ones((len(x), 1))])

        def step(w, row, i, t):
            miss = y[i] - float(np.cumsum(w * row)[-1])
            return w + (l0 * miss) * row

        return fold_samples(x, np.zeros(x.shape[1]), step, selection=order, seed=seed, passes=passes)

    return _folded(checked(df, features, "drop").select(*key, features, label), key, [features, label], learn)
