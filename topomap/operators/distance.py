"""Winner search: the nearest prototype of each sample, the smallest node among equals.

Squared distances are summed component after component in double precision, in every strategy and in the SQL twins, so all agree to the bit.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, IntegerType, StructField, StructType

#: Largest nodes x components for which prototypes are written into the expression.
EXPR_LIMIT = 1_000
#: Winners whose runner-up is nearer than this are computed again in strict order.
NEAR_TIE = 1e-9


def prototype_frame(spark, prototypes: np.ndarray, rows: int, cols: int) -> DataFrame:
    """(node, row, col, prototype)."""
    data = [(k, k // cols, k % cols, [float(x) for x in p]) for k, p in enumerate(prototypes)]
    return spark.createDataFrame(data, "node int, row int, col int, prototype array<double>")


def squared_distance(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


def strict_distances(x: np.ndarray, prototypes: np.ndarray) -> np.ndarray:
    """n x K squared distances, summed from left to right."""
    out = np.zeros((len(x), len(prototypes)))
    for i in range(x.shape[1]):
        out += (x[:, i : i + 1] - prototypes[None, :, i]) ** 2
    return out


def nearest_two(x: np.ndarray, prototypes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(winner, runner-up, winner's squared distance). A matrix product finds candidates; near ties are decided in strict order."""
    rough = (x**2).sum(axis=1)[:, None] - 2 * x @ prototypes.T + (prototypes**2).sum(axis=1)[None, :]
    take = min(3, rough.shape[1])
    low = np.partition(rough, take - 1, axis=1)[:, :take]
    open_ = (np.diff(np.sort(low, axis=1), axis=1) < NEAR_TIE).any(axis=1) if take > 1 else np.zeros(len(x), bool)
    if open_.any():
        rough[open_] = strict_distances(x[open_], prototypes)
    order = np.argsort(rough, axis=1, kind="stable")
    first = order[:, 0]
    second = order[:, 1] if rough.shape[1] > 1 else np.full(len(x), -1)
    return first, second, strict_to(x, prototypes[first])


def strict_to(x: np.ndarray, chosen: np.ndarray) -> np.ndarray:
    """Squared distance of each row to its chosen prototype, summed from left to right."""
    out = np.zeros(len(x))
    for i in range(x.shape[1]):
        out += (x[:, i] - chosen[:, i]) ** 2
    return out


def feature_matrix(column: pa.Array) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1).astype(np.float64, copy=False)


def find_winners(df: DataFrame, prototypes: np.ndarray, *, features: str = "features", strategy: str = "auto", runner_up: bool = False, groups: int | None = None) -> DataFrame:
    """``df`` with node and distance (and second, with ``runner_up``); no shuffle in any strategy.

    ``join`` crosses with a broadcast of the K prototypes, ``expr`` writes them into the expression, ``arrow`` multiplies matrices per batch. ``tree`` looks
    for the nearest of ``groups`` heads (the root of K by default) and then among its nodes only: cheaper for very large maps, and not exact.
    K x D is fixed by the grid and never grows with the data.
    """
    k, dim = prototypes.shape
    if strategy == "auto":
        strategy = "expr" if k * dim <= EXPR_LIMIT and not runner_up else "arrow"
    if runner_up and strategy != "arrow":
        raise ValueError("runners-up come with the arrow strategy")
    if strategy == "expr":
        tried = [F.struct(squared_distance(F.col(features), F.array(*[F.lit(float(x)) for x in p])).alias("d2"), F.lit(n).alias("node")) for n, p in enumerate(prototypes)]
        return df.withColumn("__best", F.array_min(F.array(*tried))).withColumn("node", F.col("__best.node")).withColumn("distance", F.sqrt("__best.d2")).drop("__best")
    if strategy == "join":
        spark = df.sparkSession
        protos = prototype_frame(spark, prototypes, 1, k).select(F.struct("node", "prototype").alias("p")).agg(F.sort_array(F.collect_list("p")).alias("__protos"))
        crossed = df.crossJoin(F.broadcast(protos))
        best = F.array_min(F.transform("__protos", lambda p: F.struct(squared_distance(F.col(features), p["prototype"]).alias("d2"), p["node"].alias("node"))))
        return crossed.withColumn("__best", best).withColumn("node", F.col("__best.node")).withColumn("distance", F.sqrt("__best.d2")).drop("__best", "__protos")
    if strategy not in ("arrow", "tree"):
        raise ValueError(f"no strategy {strategy!r}")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not len(batch):
                continue
            x = feature_matrix(batch.column(features))
            if strategy == "tree":
                first = two_level_winners(x, prototypes, groups or max(1, round(k**0.5)))
                d2, second = strict_to(x, prototypes[first]), None
            else:
                first, second, d2 = nearest_two(x, prototypes)
            columns = [*batch.columns, pa.array(first.astype(np.int32)), pa.array(np.sqrt(d2))]
            names = [*batch.schema.names, "node", "distance"]
            if runner_up:
                columns.append(pa.array(second.astype(np.int32)))
                names.append("second")
            yield pa.RecordBatch.from_arrays(columns, names)

    added = [StructField("node", IntegerType()), StructField("distance", DoubleType()), *([StructField("second", IntegerType())] if runner_up else [])]
    return df.mapInArrow(run, StructType([*df.schema.fields, *added]))


def top_nodes(df: DataFrame, prototypes: np.ndarray, k: int, *, features: str = "features") -> DataFrame:
    """``df`` with one row per sample and each of its ``k`` nearest nodes: (place, node, distance)."""
    tried = [F.struct(squared_distance(F.col(features), F.array(*[F.lit(float(x)) for x in p])).alias("d2"), F.lit(n).alias("node")) for n, p in enumerate(prototypes)]
    nearest = F.slice(F.sort_array(F.array(*tried)), 1, k)
    return df.withColumn("__near", nearest).select(*df.columns, F.posexplode("__near").alias("place", "__n")).select(*df.columns, "place", F.col("__n.node").alias("node"), F.sqrt("__n.d2").alias("distance"))


def two_level_winners(x: np.ndarray, prototypes: np.ndarray, groups: int) -> np.ndarray:
    """Search over a tree of two levels: the nearest of ``groups`` mean prototypes, then its members. Not exact; for very large maps."""
    order = np.arange(len(prototypes)) * groups // len(prototypes)
    heads = np.stack([prototypes[order == g].mean(axis=0) for g in range(groups)])
    chosen, _, _ = nearest_two(x, heads)
    out = np.zeros(len(x), np.int64)
    for g in range(groups):
        members, rows = np.flatnonzero(order == g), np.flatnonzero(chosen == g)
        if len(rows):
            out[rows] = members[nearest_two(x[rows], prototypes[members])[0]]
    return out
