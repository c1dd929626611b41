"""Joins that Spark has no operator for, as compositions of ones it has."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, by: str, left_on: str, right_on: str, take: list[str]) -> DataFrame:
    """Each left row with the ``take`` columns of the latest right row of its key that is not later.

    Both sides go through one shuffle by key and one sort; no pairs are made.
    """
    cols = left.columns
    a = left.select(F.struct(*cols).alias("_row"), F.col(by).alias("_by"), F.col(left_on).alias("_at"), F.lit(1).alias("_side"), F.lit(None).cast(right.select(F.struct(*take)).schema[0].dataType).alias("_seen"))
    b = right.select(F.lit(None).cast(a.schema["_row"].dataType).alias("_row"), F.col(by).alias("_by"), F.col(right_on).alias("_at"), F.lit(0).alias("_side"), F.struct(*take).alias("_seen"))
    w = Window.partitionBy("_by").orderBy("_at", "_side", *[F.col(f"_seen.{c}") for c in take]).rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b).withColumn("_last", F.last("_seen", ignorenulls=True).over(w))
    return both.where("_side = 1").select("_row.*", *[F.col(f"_last.{c}").alias(c) for c in take])


def range_join(points: DataFrame, ranges: DataFrame, at: str, low: str, high: str, width: float) -> DataFrame:
    """Points with the ranges [low, high) that hold them: ranges are spread over bins of ``width``, then one equi join."""
    binned = ranges.withColumn("_bin", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    return points.withColumn("_bin", F.floor(F.col(at) / width)).join(binned, "_bin").where((F.col(at) >= F.col(low)) & (F.col(at) < F.col(high))).drop("_bin")


def interval_join(left: DataFrame, right: DataFrame, by: str, left_at: str, right_at: str, seconds: int) -> DataFrame:
    """Pairs of one key whose right time is at or after the left one and less than ``seconds`` later."""
    gap: Column = F.unix_micros(F.col(right_at).cast("timestamp")) - F.unix_micros(F.col(left_at).cast("timestamp"))
    return left.join(right, by).where((gap >= 0) & (gap < seconds * 1_000_000))


def salted_join(left: DataFrame, right: DataFrame, by: str, salts: int = 8) -> DataFrame:
    """Equi join whose left rows of a key are spread over ``salts`` tasks; the right side is copied as often."""
    a = left.withColumn("_salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)).cast("int"))
    b = right.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [by, "_salt"]).drop("_salt")
