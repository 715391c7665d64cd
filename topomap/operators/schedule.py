"""Decay of radius, rate and influence. Only the horizon is free, and the staggered order fixes that."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .grid import distance_matrix, grid_distances, initial_radius

#: Weights are rounded to so many decimals: pow differs in its last bit between engines.
DECIMALS = 12


def radius_at(t: float, horizon: int, r0: float) -> float:
    """From ``r0`` at 0 to 1 at the horizon; the base of the exponential decay cancels."""
    return r0 ** (1 - t / horizon)


def rate_at(t: float, horizon: int, l0: float, base: float = math.e) -> float:
    return l0 * base ** (-t / horizon)


def influence(distance, radius: float, base: float = math.e):
    return base ** (-np.asarray(distance) / (2 * radius))


def weights_at(t: float, horizon: int, rows: int, cols: int, l0: float, base: float = math.e, shape: str = "circle") -> np.ndarray:
    """K x K: how far each node moves for each winner; 0 outside the radius."""
    distance, radius = distance_matrix(rows, cols, shape), radius_at(t, horizon, initial_radius(rows, cols))
    return np.where(distance <= radius, np.round(rate_at(t, horizon, l0, base) * influence(distance, radius, base), DECIMALS), 0.0)


def schedule_frame(spark: SparkSession, horizon: int, rows: int, cols: int, l0: float, base: float = math.e) -> DataFrame:
    """(t, radius, rate) for each pass up to the horizon."""
    part = F.col("t") / F.lit(float(horizon))
    return spark.range(horizon).withColumnRenamed("id", "t").select("t", F.pow(F.lit(initial_radius(rows, cols)), 1 - part).alias("radius"), (F.lit(l0) * F.pow(F.lit(base), -part)).alias("rate"))


def weight_frame(spark: SparkSession, t: int, horizon: int, rows: int, cols: int, l0: float, base: float = math.e) -> DataFrame:
    """(winner, node, weight) of pass ``t``."""
    radius, rate = radius_at(t, horizon, initial_radius(rows, cols)), rate_at(t, horizon, l0, base)
    weight = F.when(F.col("distance") <= radius, F.round(F.lit(rate) * F.pow(F.lit(base), -F.col("distance") / (2 * radius)), DECIMALS)).otherwise(0.0)
    return grid_distances(spark, rows, cols).select(F.col("node_a").alias("winner"), F.col("node_b").alias("node"), weight.alias("weight"))
