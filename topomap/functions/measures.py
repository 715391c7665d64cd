"""Cost and accuracy measures of a map and of a comparison of maps."""

from __future__ import annotations

import math
import statistics
import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.grid import distance_matrix


def timed(action: Callable[[], object], repeats: int = 3, warm_up: int = 1) -> float:
    """Median seconds of ``repeats`` runs after a warm-up."""
    for _ in range(warm_up):
        action()
    seconds = []
    for _ in range(repeats):
        began = time.perf_counter()
        action()
        seconds.append(time.perf_counter() - began)
    return statistics.median(seconds)


def quantization_error(assigned: DataFrame) -> DataFrame:
    """Mean distance of samples to their winners."""
    return assigned.agg(F.avg("distance").alias("quantization_error"))


def topographic_error(assigned: DataFrame, rows: int, cols: int) -> DataFrame:
    """Share of samples whose two nearest nodes aren't neighbours on the grid, diagonal ones included; needs ``second``."""
    gaps = distance_matrix(rows, cols)
    near = F.array(*[F.array(*[F.lit(bool(g <= math.sqrt(2) + 1e-9)) for g in row]) for row in gaps])
    return assigned.agg(F.avg((~F.get(F.get(near, F.col("node")), F.col("second"))).cast("double")).alias("topographic_error"))


def prototype_gap(centroids: DataFrame, prototypes: DataFrame) -> DataFrame:
    """(node, gap): Euclidean distance of a prototype from its members' mean; NULL without members."""
    both = prototypes.join(centroids.select(F.col("regime").alias("node"), "centroid"), "node", "left")
    d2 = F.aggregate(F.zip_with("prototype", "centroid", lambda p, c: (p - c) * (p - c)), F.lit(0.0), lambda s, v: s + v)
    return both.select("node", F.when(F.col("centroid").isNotNull(), F.sqrt(d2)).alias("gap"))


def contingency(assigned: DataFrame, other: str) -> DataFrame:
    return assigned.groupBy("node", other).agg(F.count("*").alias("n"))


def purity(assigned: DataFrame, group: str) -> DataFrame:
    """Share of samples in their regime's largest group."""
    most = contingency(assigned, group).groupBy("node").agg(F.max("n").alias("most"), F.sum("n").alias("all"))
    return most.agg((F.sum("most") / F.sum("all")).alias("purity"))


def adjusted_rand(table: DataFrame, a: str, b: str, n: str = "n") -> DataFrame:
    """(rand, adjusted_rand) from a contingency table: pairs of samples that two groupings treat alike, plain and against chance."""
    choose = lambda x: x * (x - 1) / 2
    cells = table.agg(F.sum(choose(F.col(n).cast("double"))).alias("both"), F.sum(n).cast("double").alias("n"))
    side = lambda c, name: table.groupBy(c).agg(F.sum(n).cast("double").alias("m")).agg(F.sum(choose(F.col("m"))).alias(name))
    one = cells.crossJoin(side(a, "in_a")).crossJoin(side(b, "in_b"))  # three one-row tables
    all_pairs = choose(F.col("n"))
    expected = F.col("in_a") * F.col("in_b") / all_pairs
    best = (F.col("in_a") + F.col("in_b")) / 2
    return one.select(
        ((all_pairs + 2 * F.col("both") - F.col("in_a") - F.col("in_b")) / all_pairs).alias("rand"),
        F.when(best == expected, 1.0).otherwise((F.col("both") - expected) / (best - expected)).alias("adjusted_rand"),
    )


def run_agreement(first: DataFrame, second: DataFrame, key: list[str]) -> DataFrame:
    """Rand and adjusted Rand of two runs' assignments."""
    joined = first.select(*key, F.col("node").alias("wa")).join(second.select(*key, F.col("node").alias("wb")), key)
    return adjusted_rand(joined.groupBy("wa", "wb").agg(F.count("*").alias("n")), "wa", "wb")


def node_shift(a: np.ndarray, b: np.ndarray) -> float:
    """Largest distance of a prototype from the one of the same node."""
    return float(np.sqrt(((a - b) ** 2).sum(axis=1)).max())


def best_match(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """For each prototype of ``a`` its highest histogram correlation with one of ``b``; NaN where all are constant."""
    x, y = a - a.mean(axis=1, keepdims=True), b - b.mean(axis=1, keepdims=True)
    scale = np.sqrt((x * x).sum(axis=1))[:, None] * np.sqrt((y * y).sum(axis=1))[None, :]
    corr = np.divide(x @ y.T, scale, out=np.full(scale.shape, np.nan), where=scale > 1e-9)
    return np.nanmax(corr, axis=1)


def node_balance(assigned: DataFrame, nodes: int, wanted: float) -> DataFrame:
    """(node, n, ratio) with empty nodes, n over the samples per node asked for."""
    counts = assigned.groupBy("node").agg(F.count("*").alias("n"))
    every = assigned.sparkSession.range(nodes).select(F.col("id").cast("int").alias("node"))
    n = F.coalesce("n", F.lit(0))
    return every.join(counts, "node", "left").select("node", n.alias("n"), (n / F.lit(float(wanted))).alias("ratio"))


def never_won(assigned: DataFrame, nodes: int) -> DataFrame:
    every = assigned.sparkSession.range(nodes).select(F.col("id").cast("int").alias("node"))
    return every.join(assigned.select("node").distinct(), "node", "left_anti")
