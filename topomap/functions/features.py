"""Feature vectors: classes, joint histograms, scaling, validity."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SHAPE = (6, 7)
BINS = SHAPE[0] * SHAPE[1]


def to_class(value: Column, edges: list[float]) -> Column:
    """Number of edges that are at most the value: 0 below the first."""
    out = F.lit(0)
    for e in edges:
        out = out + (value >= F.lit(e)).cast("int")
    return out


def uniform_class(value: Column, low: float, high: float, classes: int) -> Column:
    return F.least(F.lit(classes - 1), F.greatest(F.lit(0), F.floor((value - low) * classes / (high - low)))).cast("int")


def joint_histogram(df: DataFrame, keys: list[str], a: Column, b: Column, *, shape: tuple[int, int] = SHAPE, counted: Column | None = None) -> DataFrame:
    """(keys, n, features, cloud_fraction): per group the fraction of its rows in each class pair, row by row.

    Counts per class pair are one aggregate with partial sums: one shuffle on the keys, whatever a key's share of the rows.
    ``counted`` tells which rows count in a bin; all rows count in n, so the sum of bins may be below 1.
    """
    bins = shape[0] * shape[1]
    binned = df.withColumn("__bin", F.when(F.lit(True) if counted is None else counted, (a * shape[1] + b).cast("int")))
    sums = binned.groupBy(*keys).agg(F.count("*").alias("n"), *[F.count_if(F.col("__bin") == k).alias(f"__{k}") for k in range(bins)])
    features = F.array(*[F.col(f"__{k}") / F.col("n") for k in range(bins)])
    total = sum((F.col(f"__{k}") for k in range(1, bins)), F.col("__0"))
    return sums.select(*keys, "n", features.alias("features"), (total / F.col("n")).alias("cloud_fraction"))


def drop_invalid(df: DataFrame, features: str = "features") -> DataFrame:
    """Without records that are missing, have a missing component, or are zero throughout."""
    x = F.col(features)
    return df.where(x.isNotNull() & ~F.exists(x, lambda v: v.isNull() | F.isnan(v)) & F.exists(x, lambda v: v != 0))


def retention(df: DataFrame, features: str = "features") -> DataFrame:
    """One row: records, missing ones, all-zero ones, valid ones and their share."""
    x = F.col(features)
    missing = x.isNull() | F.exists(x, lambda v: v.isNull() | F.isnan(v))
    zero = ~missing & ~F.exists(x, lambda v: v != 0)
    counts = df.agg(F.count("*").alias("records"), F.count_if(missing).alias("missing"), F.count_if(zero).alias("all_zero"))
    valid = F.col("records") - F.col("missing") - F.col("all_zero")
    return counts.select("records", "missing", "all_zero", valid.alias("valid"), (valid / F.col("records")).alias("retained"))


def cloud_fraction(features: Column) -> Column:
    return F.aggregate(features, F.lit(0.0), lambda s, v: s + v)


def histogram_long(df: DataFrame, keys: list[str], features: str = "features", width: int = SHAPE[1]) -> DataFrame:
    """(keys, a, b, value): one row per bin."""
    return df.select(*keys, F.posexplode(features).alias("bin", "value")).select(*keys, F.floor(F.col("bin") / width).cast("int").alias("a"), (F.col("bin") % width).alias("b"), "value")


def minmax_scale(df: DataFrame, dim: int, features: str = "features") -> DataFrame:
    """Each component onto [0, 1] by its smallest and largest value; a constant component becomes 0. Two numbers per component reach the driver."""
    ends = df.agg(*[f(F.get(features, i)).alias(f"{name}{i}") for i in range(dim) for name, f in (("lo", F.min), ("hi", F.max))]).first()
    if ends["lo0"] is None:
        return df
    low = F.array(*[F.lit(float(ends[f"lo{i}"])) for i in range(dim)])
    high = F.array(*[F.lit(float(ends[f"hi{i}"])) for i in range(dim)])
    span = F.zip_with(high, low, lambda h, lo: h - lo)
    scaled = F.zip_with(F.zip_with(F.col(features), low, lambda x, lo: x - lo), span, lambda x, s: F.when(s > 0, x / s).otherwise(0.0))
    return df.withColumn(features, scaled)


def sparse_histogram(features: Column) -> Column:
    """map<int,double> of the bins that aren't zero."""
    return F.map_from_entries(F.filter(F.transform(features, lambda v, i: F.struct(i.alias("bin"), v.alias("value"))), lambda e: e["value"] != 0))


def dense_histogram(sparse: Column, bins: int = BINS) -> Column:
    return F.transform(F.sequence(F.lit(0), F.lit(bins - 1)), lambda i: F.coalesce(F.try_element_at(sparse, i), F.lit(0.0)))
