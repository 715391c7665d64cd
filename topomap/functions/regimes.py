"""Regimes: trained nodes read as mean histograms, with cloud fraction, frequency maps and their comparisons."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

FIXED = 1 << 24


def exact_mean(value: Column) -> Column:
    """Mean of values in [0, 1] by a fixed-point sum: the same whatever the task order."""
    return F.sum(F.round(value * FIXED).cast("long")) / F.lit(float(FIXED)) / F.count("*")


def regime_centroids(assigned: DataFrame, dim: int, *, features: str = "features") -> DataFrame:
    """(regime, n, cloud_fraction, rfo, centroid) of every regime that has members."""
    means = [exact_mean(F.get(features, i)).alias(f"m{i}") for i in range(dim)]
    sums = assigned.groupBy(F.col("node").alias("regime")).agg(F.count("*").alias("n"), *means)
    centroid = F.array(*[F.col(f"m{i}") for i in range(dim)])
    share = F.col("n") / F.sum("n").over(Window.partitionBy())
    return sums.select("regime", "n", F.aggregate(centroid, F.lit(0.0), lambda s, v: s + v).alias("cloud_fraction"), share.alias("rfo"), centroid.alias("centroid"))


def rfo(assigned: DataFrame) -> DataFrame:
    """(regime, n, rfo): relative frequency of each regime."""
    counts = assigned.groupBy(F.col("node").alias("regime")).agg(F.count("*").alias("n"))
    return counts.withColumn("rfo", F.col("n") / F.sum("n").over(Window.partitionBy()))


def rfo_map(assigned: DataFrame, cell: str, regimes: int, *, denominator: DataFrame | None = None) -> DataFrame:
    """(cell, regime, n, rfo) for every cell and regime, zero where a cell never had the regime.

    ``denominator``: (cell, total) to divide by, for all days; else valid records count.
    """
    # one aggregate by cell: a count per regime, then a row per cell and regime
    sums = assigned.groupBy(cell).agg(F.count("*").alias("total"), *[F.count_if(F.col("node") == k).alias(f"__{k}") for k in range(regimes)])
    if denominator is not None:
        sums = denominator.select(cell, F.col("total").alias("__total")).join(sums.drop("total"), cell, "left").withColumnRenamed("__total", "total")
    counts = F.array(*[F.coalesce(F.col(f"__{k}"), F.lit(0)) for k in range(regimes)])
    return sums.select(cell, "total", F.posexplode(counts).alias("regime", "n")).select(cell, "regime", "n", (F.col("n") / F.col("total")).alias("rfo"))


def pair_correlation(values: DataFrame, regime: str, place: str, value: str) -> DataFrame:
    """(regime_a, regime_b, corr) of every pair a < b over a long table (regime, place, value). NULL where one side is constant."""
    a = values.select(F.col(regime).alias("regime_a"), F.col(place).alias("p"), F.col(value).alias("x"))
    b = values.select(F.col(regime).alias("regime_b"), F.col(place).alias("p"), F.col(value).alias("y"))
    both = a.join(b, "p").where("regime_a < regime_b")
    return both.groupBy("regime_a", "regime_b").agg(pearson("x", "y").alias("corr"))


def pearson(x: str, y: str) -> Column:
    """Correlation from plain sums, as in the SQL twins; NULL if a side has no variance."""
    n = F.count("*").cast("double")
    sx, sy = F.sum(x), F.sum(y)
    top = n * F.sum(F.col(x) * F.col(y)) - sx * sy
    vx, vy = n * F.sum(F.col(x) * F.col(x)) - sx * sx, n * F.sum(F.col(y) * F.col(y)) - sy * sy
    return F.when((vx > 1e-15) & (vy > 1e-15), top / (F.sqrt(vx) * F.sqrt(vy)))


def regime_correlation(centroids: DataFrame) -> DataFrame:
    """(regime_a, regime_b, histogram_corr) over bins."""
    return pair_correlation(centroids.select("regime", F.posexplode("centroid").alias("bin", "value")), "regime", "bin", "value").withColumnRenamed("corr", "histogram_corr")


def rfo_correlation(frequency: DataFrame, cell: str) -> DataFrame:
    """(regime_a, regime_b, map_corr) over grid cells."""
    return pair_correlation(frequency, "regime", cell, "rfo").withColumnRenamed("corr", "map_corr")


def similar_regimes(histograms: DataFrame, maps: DataFrame, histogram_min: float = 0.6, map_min: float = 0.74) -> DataFrame:
    """Pairs whose histograms and maps both correlate at least so much: regimes too alike to be two."""
    return histograms.join(maps, ["regime_a", "regime_b"]).where((F.col("histogram_corr") >= histogram_min) & (F.col("map_corr") >= map_min))


def coverage(of: DataFrame, by: DataFrame) -> DataFrame:
    """(regime, best, corr): for each centroid of ``of`` the one of ``by`` with the highest histogram correlation, the smaller id among equals."""
    x = of.select("regime", F.posexplode("centroid").alias("p", "x"))
    y = by.select(F.col("regime").alias("other"), F.posexplode("centroid").alias("p", "y"))
    pairs = x.join(y, "p").groupBy("regime", "other").agg(F.round(pearson("x", "y"), 9).alias("corr"))
    first = F.row_number().over(Window.partitionBy("regime").orderBy(F.desc_nulls_last("corr"), "other"))
    return pairs.withColumn("k", first).where("k = 1").select("regime", F.col("other").alias("best"), "corr")


def regime_kind(centroids: DataFrame, *, high_rows: int = 3, clear: float = 0.4, high_share: float = 0.5, width: int = 7) -> DataFrame:
    """``centroids`` with kind: semi-clear below ``clear`` cloud fraction, else high or low by the share of the first ``high_rows`` histogram rows."""
    top = F.aggregate(F.slice("centroid", 1, high_rows * width), F.lit(0.0), lambda s, v: s + v)
    return centroids.withColumn("kind", F.when(F.col("cloud_fraction") < clear, "semi-clear").when(top >= high_share * F.col("cloud_fraction"), "high").otherwise("low"))


def rank_regimes(frequencies: DataFrame) -> DataFrame:
    return frequencies.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("n"), "regime")))


def regime_transitions(assigned: DataFrame, cell: str, period: str) -> DataFrame:
    """(before, after, n): how often a cell's next record has another or the same regime."""
    lagged = assigned.withColumn("before", F.lag("node").over(Window.partitionBy(cell).orderBy(period)))
    return lagged.where("before is not null").groupBy("before", F.col("node").alias("after")).agg(F.count("*").alias("n"))
