"""A trained map: prototypes, settings, history."""

from __future__ import annotations

import hashlib
import json
from dataclasses import asdict, dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import MapConfig
from .distance import find_winners, prototype_frame

HISTORY = "pass bigint, start_index bigint, direction string, radius double, rate double, moves bigint, seconds double"


def fingerprint(prototypes: np.ndarray) -> str:
    """SHA-256 of the IEEE bytes in node order: equal maps are equal to the bit."""
    return hashlib.sha256(np.ascontiguousarray(prototypes, dtype="<f8").tobytes()).hexdigest()


@dataclass
class MapModel:
    prototypes: np.ndarray
    cfg: MapConfig
    history: list[dict]
    stop_reason: str

    @property
    def fingerprint(self) -> str:
        return fingerprint(self.prototypes)

    def frame(self, spark: SparkSession) -> DataFrame:
        return prototype_frame(spark, self.prototypes, self.cfg.rows, self.cfg.cols)

    def history_frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([tuple(h[c.split()[0]] for c in HISTORY.split(", ")) for h in self.history], HISTORY)

    def classify(self, df: DataFrame, **options) -> DataFrame:
        """Every record with its node and distance: a scan with K x D constants."""
        return find_winners(df, self.prototypes, **options)

    def save(self, spark: SparkSession, path: str) -> None:
        settings = json.dumps({"cfg": asdict(self.cfg), "history": self.history, "stop_reason": self.stop_reason})
        self.frame(spark).withColumn("settings", F.lit(settings)).coalesce(1).write.mode("overwrite").parquet(path)

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> MapModel:
        rows = sorted(spark.read.parquet(path).collect(), key=lambda r: r["node"])
        settings = json.loads(rows[0]["settings"])
        return cls(np.array([r["prototype"] for r in rows]), MapConfig(**settings["cfg"]), settings["history"], settings["stop_reason"])
