"""The training list and the orders in which a pass shows it.

Staggered order in closed form: pass t starts at t/2 and runs forward when t is even, and starts at N-1-(t-1)/2 and runs backward
when it is odd, wrapping around. So an order is one ``pmod`` of the sample index: no sort and no state per pass, and over N passes every sample starts once.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.scratch import written


def dense_index(df: DataFrame, keys: list[str], name: str = "sample_index") -> DataFrame:
    """``df`` with 0..N-1 by the order of ``keys``, which must be unique for the order to be total.

    A range sort deals the rows out; counts per range give offsets. No single-partition window: the only table on one task is the list of ranges.
    """
    ranged = df.repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn("__at", F.monotonically_increasing_id())
    stored = written(ranged, "training-list")
    part = F.shiftright("__at", 33)
    counts = stored.groupBy(part.alias("__part")).agg(F.count("*").alias("__n"))
    before = Window.orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select("__part", F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__offset"))
    placed = stored.withColumn("__part", part).join(F.broadcast(offsets), "__part")
    return placed.withColumn(name, F.col("__offset") + F.col("__at").bitwiseAND(F.lit((1 << 33) - 1))).drop("__part", "__at", "__offset")


def start_index(t: int, n: int) -> int:
    """Sample with which pass ``t`` starts."""
    return (t // 2) % n if t % 2 == 0 else (n - 1 - (t - 1) // 2) % n


def staggered_position(index: Column, n: Column | int, t: Column | int) -> Column:
    """Place of a sample in pass ``t``."""
    n, t = (x if isinstance(x, Column) else F.lit(x) for x in (n, t))
    forward = F.pmod(index - F.floor(t / 2), n)
    backward = F.pmod(n - 1 - F.floor((t - 1) / 2) - index, n)
    return F.when(t % 2 == 0, forward).otherwise(backward).cast("long")


def order_staggered(n: int, t: int) -> np.ndarray:
    j = np.arange(n)
    return (start_index(t, n) + j) % n if t % 2 == 0 else (start_index(t, n) - j) % n


def order_sequential(n: int, t: int = 0) -> np.ndarray:
    return np.arange(n)


def order_random(n: int, t: int, seed: int, replacement: bool = False) -> np.ndarray:
    """A permutation per pass (or draws with replacement), fixed by seed, pass and nothing else: samples in the order of a hash of seed, pass and index."""
    hashed = [hashlib.md5(b"%d:%d:%d" % (seed, t, i)).digest() for i in range(n)]
    if replacement:
        return np.array([int.from_bytes(h[:6], "big") % n for h in hashed], np.int64)
    words = np.frombuffer(b"".join(hashed), ">u8").reshape(n, 2)
    return np.lexsort((words[:, 1], words[:, 0]))


def order_of(selection: str, n: int, t: int, seed: int | None) -> np.ndarray:
    if selection == "staggered":
        return order_staggered(n, t)
    if selection == "sequential":
        return order_sequential(n, t)
    return order_random(n, t, seed, selection == "random_replace")


def staggered_horizon(n: int) -> int:
    """Both end pointers close in by one sample per pass and meet after as many passes as there are samples."""
    return n


def staggered_orders(indexed: DataFrame, n: int, passes: int) -> DataFrame:
    """(t, position, sample_index) of the first ``passes`` passes: the list of passes is what is broadcast."""
    ts = indexed.sparkSession.range(passes).withColumnRenamed("id", "t")
    placed = indexed.select("sample_index").crossJoin(F.broadcast(ts))
    return placed.select("t", staggered_position(F.col("sample_index"), n, F.col("t")).alias("position"), "sample_index")


def random_orders(indexed: DataFrame, passes: int, seed: int) -> DataFrame:
    """(t, position, sample_index) by a seeded hash: the sort per pass that the staggered order saves."""
    ts = indexed.sparkSession.range(passes).withColumnRenamed("id", "t")
    drawn = indexed.select("sample_index").crossJoin(F.broadcast(ts)).withColumn("draw", F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("t").cast("string"), F.col("sample_index").cast("string")).cast("binary")))
    place = F.row_number().over(Window.partitionBy("t").orderBy("draw", "sample_index")) - 1
    return drawn.select("t", place.cast("long").alias("position"), "sample_index")


def start_fairness(orders: DataFrame) -> DataFrame:
    """(sample_index, starts, mean_position)."""
    return orders.groupBy("sample_index").agg(F.count_if(F.col("position") == 0).alias("starts"), F.avg("position").alias("mean_position"))
