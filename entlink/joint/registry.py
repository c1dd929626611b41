"""Versioned model store: weights as Parquet, a pointer row that is swapped last."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Text encoders by name: objects with ``encode(texts, width)`` that give a matrix, as known to ``Config.encoder``.
ENCODERS: dict[str, object] = {}
#: Towers by name: functions of (widths, seed, keep) that give a tower, as known to ``Config.tower``.
TOWERS: dict[str, Callable] = {}


def register_encoder(name: str, encoder: object) -> None:
    """Make a user's text encoder known by name."""
    ENCODERS[name] = encoder


def register_tower(name: str, factory: Callable) -> None:
    """Make a user's network known by name."""
    TOWERS[name] = factory


class ModelRegistry:
    """Models below a path; readers that hold a version keep it while a new one is published."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path

    def publish(self, model: str, weights: DataFrame) -> int:
        version = (self.current(model) or 0) + 1
        weights.write.parquet(f"{self.path}/{model}/weights-{version}")
        row = [(version,)]
        # Appending the pointer is the last step: a failed write leaves the former version current.
        self.spark.createDataFrame(row, "version int").coalesce(1).write.mode("append").parquet(f"{self.path}/{model}/pointer")
        return version

    def current(self, model: str) -> int | None:
        from pyspark.errors import AnalysisException

        try:
            return self.spark.read.parquet(f"{self.path}/{model}/pointer").agg(F.max("version")).first()[0]
        except AnalysisException:
            return None

    def load(self, model: str, version: int | None = None) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/{model}/weights-{version or self.current(model)}")
