"""SQL and ML surfaces: table functions, a winner function, one pass as recursive SQL, an Estimator."""

from __future__ import annotations

import json

import numpy as np
import pandas as pd
from pyspark.ml import Estimator, Model
from pyspark.ml.param import Param, Params
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf

from ..config import MapConfig
from ..operators.distance import find_winners, nearest_two
from ..operators.grid import gradient_values
from ..operators.ordering import order_staggered
from ..operators.schedule import weights_at
from ..operators.train import fit_map


class StaggeredOrder:
    def eval(self, n: int, passes: int):
        for t in range(passes):
            for position, i in enumerate(order_staggered(n, t)):
                yield t, position, int(i)


class Grid:
    def eval(self, rows: int, cols: int):
        for k in range(rows * cols):
            yield k, k // cols, k % cols


def register(spark: SparkSession) -> None:
    """Table functions ``staggered_order(n, passes)`` and ``grid(rows, cols)`` for SQL."""
    spark.udtf.register("staggered_order", udtf(StaggeredOrder, returnType="t int, position bigint, sample_index bigint"))
    spark.udtf.register("grid", udtf(Grid, returnType="node int, row int, col int"))


def register_winner(spark: SparkSession, name: str, prototypes: np.ndarray) -> None:
    """SQL function ``name(features)``: the winner, in Arrow batches."""

    @pandas_udf("int")
    def winner(features: pd.Series) -> pd.Series:
        return pd.Series(nearest_two(np.stack(features.to_numpy()).astype(np.float64), prototypes)[0].astype(np.int32)) if len(features) else pd.Series([], dtype="int32")

    spark.udf.register(name, winner)


def recursive_pass(spark: SparkSession, points: list[tuple[float, ...]], rows: int, cols: int) -> DataFrame:
    """(node, prototype) after one staggered pass from gradient start, as a recursive query over a literal list: a form to read, for short lists."""
    n, dim = len(points), len(points[0])
    weights = weights_at(0, n, rows, cols, 0.1)
    array = lambda xs: "array(" + ", ".join(xs) + ")"
    number = lambda x: f"{float(x)!r}D"
    table = lambda m: array(array(number(x) for x in row) for row in m)
    start = np.repeat(np.array(gradient_values(rows, cols))[:, None], dim, axis=1)
    text = f"""
    WITH RECURSIVE told(step, v) AS (
      SELECT 0, {table(start)}
      UNION ALL
      SELECT step + 1, zip_with(v, {table(weights)}[array_position(d, array_min(d)) - 1], (p, w) -> zip_with(p, x, (a, b) -> a + w * (b - a)))
      FROM (SELECT step, v, x, transform(v, p -> aggregate(zip_with(p, x, (a, b) -> (b - a) * (b - a)), 0D, (s, e) -> s + e)) AS d
            FROM (SELECT step, v, {table(points)}[step] AS x FROM told WHERE step < {n})))
    SELECT v FROM told WHERE step = {n}"""
    limit = "spark.sql.cteRecursionLevelLimit"
    before = spark.conf.get(limit)
    spark.conf.set(limit, max(100, n + 1))
    try:
        found = spark.sql(text).first()["v"]
    finally:
        spark.conf.set(limit, before)
    return spark.createDataFrame([(k, [round(x, 6) for x in p]) for k, p in enumerate(found)], "node int, prototype array<double>")


class _MapParams(Params):
    settings = Param(Params._dummy(), "settings", "MapConfig fields as JSON")
    key = Param(Params._dummy(), "key", "columns of the training order, comma-separated")
    features = Param(Params._dummy(), "features", "feature column")


class TopologyMap(Estimator, _MapParams):
    """Estimator around ``fit_map``."""

    def __init__(self, key: str, features: str = "features", **settings):
        super().__init__()
        self._set(key=key, features=features, settings=json.dumps(settings))

    def _fit(self, dataset: DataFrame) -> TopologyMapModel:
        cfg = MapConfig(**json.loads(self.getOrDefault(self.settings)))
        model = fit_map(dataset, cfg, key=self.getOrDefault(self.key).split(","), features=self.getOrDefault(self.features))
        out = TopologyMapModel(model)
        out._set(key=self.getOrDefault(self.key), features=self.getOrDefault(self.features), settings=self.getOrDefault(self.settings))
        return out


class TopologyMapModel(Model, _MapParams):
    def __init__(self, model):
        super().__init__()
        self.model = model

    def _transform(self, dataset: DataFrame) -> DataFrame:
        return find_winners(dataset, self.model.prototypes, features=self.getOrDefault(self.features))


__all__ = ["register", "register_winner", "recursive_pass", "TopologyMap", "TopologyMapModel", "F"]
