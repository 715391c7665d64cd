"""The node grid, its start values and its neighbourhoods."""

from __future__ import annotations

import hashlib
import math

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def grid_frame(spark: SparkSession, rows: int, cols: int) -> DataFrame:
    """(node, row, col), numbered row by row."""
    node = F.col("id").cast("int").alias("node")
    return spark.range(rows * cols).select(node, F.floor(F.col("id") / cols).cast("int").alias("row"), (F.col("id") % cols).cast("int").alias("col"))


def grid_distances(spark: SparkSession, rows: int, cols: int) -> DataFrame:
    """(node_a, node_b, distance): Euclidean distance on the grid of every pair; a table of nodes, whatever the data."""
    a = grid_frame(spark, rows, cols).toDF("node_a", "row_a", "col_a")
    b = grid_frame(spark, rows, cols).toDF("node_b", "row_b", "col_b")
    gap = F.sqrt(F.pow(F.col("row_a") - F.col("row_b"), 2) + F.pow(F.col("col_a") - F.col("col_b"), 2))
    return a.crossJoin(F.broadcast(b)).select("node_a", "node_b", gap.alias("distance"))


def distance_matrix(rows: int, cols: int, shape: str = "circle") -> np.ndarray:
    """Grid distances as K x K; for ``square`` neighbourhoods the larger of both steps."""
    at = np.array([(r, c) for r in range(rows) for c in range(cols)], dtype=np.float64)
    gap = np.abs(at[:, None, :] - at[None, :, :])
    return gap.max(axis=2) if shape == "square" else np.sqrt((gap**2).sum(axis=2))


def initial_radius(rows: int, cols: int) -> float:
    return min(rows, cols) / 2


def gradient_values(rows: int, cols: int) -> list[float]:
    """One value per node: its distance from the first node over that of the last, so equally distant nodes are equal."""
    far = math.sqrt((rows - 1) ** 2 + (cols - 1) ** 2)
    return [math.sqrt(r * r + c * c) / far if far else 0.0 for r in range(rows) for c in range(cols)]


def init_gradient(rows: int, cols: int, dim: int) -> np.ndarray:
    return np.repeat(np.array(gradient_values(rows, cols))[:, None], dim, axis=1)


def drawn(*parts: int) -> int:
    """52 bits drawn from a hash of the parts, the same here, in Catalyst and in SQL."""
    return int(hashlib.md5(":".join(map(str, parts)).encode()).hexdigest()[:13], 16)


def init_random(rows: int, cols: int, dim: int, seed: int, low: float = 0.0, high: float = 1.0) -> np.ndarray:
    """Uniform values, each drawn from a hash of seed, node and component."""
    unit = np.array([[drawn(seed, k, i) / 2.0**52 for i in range(dim)] for k in range(rows * cols)])
    return low + (high - low) * unit


def init_gradient_frame(spark: SparkSession, rows: int, cols: int, dim: int) -> DataFrame:
    """(node, row, col, prototype) of the gradient start, as a plan."""
    far = math.sqrt((rows - 1) ** 2 + (cols - 1) ** 2)
    value = F.sqrt(F.pow(F.col("row"), 2) + F.pow(F.col("col"), 2)) / F.lit(far) if far else F.lit(0.0)
    return grid_frame(spark, rows, cols).withColumn("prototype", F.array_repeat(value, dim))


def init_random_frame(spark: SparkSession, rows: int, cols: int, dim: int, seed: int) -> DataFrame:
    """A random start from a hash of seed, node and component: equal for equal seeds on any cluster."""

    def value(i: Column) -> Column:
        hashed = F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("node").cast("string"), i.cast("string")).cast("binary"))
        return F.conv(F.substring(hashed, 1, 13), 16, 10).cast("double") / F.lit(float(1 << 52))

    return grid_frame(spark, rows, cols).withColumn("prototype", F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), value))


def neighbourhood(winner: int, radius: float, rows: int, cols: int, shape: str = "circle") -> list[int]:
    """Nodes within the radius of the winner, the border included."""
    return np.flatnonzero(distance_matrix(rows, cols, shape)[winner] <= radius).tolist()
