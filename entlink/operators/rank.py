"""Linking: ranks of candidates in both directions."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def top_n(pairs: DataFrame, query: str, result: str, n: int) -> DataFrame:
    """The ``n`` nearest results of each query by distance, then result id; Spark limits each task before the shuffle."""
    w = Window.partitionBy(query).orderBy("distance", result)
    return pairs.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= n)


def link_rank(pairs: DataFrame, query: str, result: str, n: int) -> DataFrame:
    """As ``top_n``, but queries whose candidates have no distance keep all of them at rank one."""
    scored = F.max(F.col("distance").isNotNull().cast("int")).over(Window.partitionBy(query))
    w = Window.partitionBy(query).orderBy(F.col("distance").asc_nulls_last(), result)
    ranked = pairs.withColumn("_scored", scored).withColumn("_row", F.row_number().over(w))
    ranked = ranked.withColumn("rank", F.when(F.col("_scored") == 0, 1).otherwise(F.col("_row")))
    return ranked.where((F.col("_scored") == 0) | (F.col("_row") <= n)).drop("_scored", "_row")


def within(links: DataFrame, max_distance: float) -> DataFrame:
    """Links no farther than a threshold; queries left without any have no entity."""
    return links.where(F.col("distance") <= max_distance)


def rollup_instances(links: DataFrame, tuples: DataFrame, query: str, result: str = "tuple_id") -> DataFrame:
    """Best tuple of each instance for every query."""
    w = Window.partitionBy(query, "instance_id").orderBy("distance", result)
    return links.join(tuples.select(F.col("tuple_id").alias(result), "instance_id"), result).withColumn("_n", F.row_number().over(w)).where("_n = 1").drop("_n")


def mutual(forth: DataFrame, back: DataFrame) -> DataFrame:
    """Pairs that are first choice in both directions; both have tuple_id, mention_id, rank."""
    return forth.where("rank = 1").select("tuple_id", "mention_id").intersect(back.where("rank = 1").select("tuple_id", "mention_id"))
