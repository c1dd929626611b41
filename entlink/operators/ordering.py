"""Global ranks and running sums without a single task that sees all rows.

Rows are dealt out by range and sorted, and written once with partition and row
numbers, so that all passes see the same order.  One number for each range is
summed over the ranges before it; that table has as many rows as there are
ranges, so its window in one task and its broadcast have a bound that does not
follow the data.  Nothing goes through Python, and nothing but counts to the driver.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from entlink.storage import materialize

_BEFORE = Window.unboundedPreceding, -1


def _placed(df: DataFrame, order: list[Column], tag: str) -> DataFrame:
    """Rows in global order, with the number of their range and their place in it."""
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    placed = df.repartitionByRange(parts, *order).sortWithinPartitions(*order)
    # monotonically_increasing_id has the partition number above bit 33 and the row number below
    placed = materialize(placed.withColumn("_place", F.monotonically_increasing_id()), tag)
    return placed.withColumn("_part", F.shiftright("_place", 33)).withColumn("_place", F.col("_place").bitwiseAND((1 << 33) - 1))


def _with_offsets(placed: DataFrame, size: Column) -> DataFrame:
    ranges = placed.groupBy("_part").agg(size.alias("_size"))
    offsets = ranges.select("_part", F.coalesce(F.sum("_size").over(Window.orderBy("_part").rowsBetween(*_BEFORE)), F.lit(0)).alias("_before"))
    return placed.join(F.broadcast(offsets), "_part")


def _order(keys: list[str | Column]) -> list[Column]:
    return [F.col(k).asc_nulls_first() if isinstance(k, str) else k for k in keys]


def ranked(df: DataFrame, keys: list[str | Column], rank_col: str = "rank", tag: str = "ranked") -> tuple[DataFrame, int]:
    """Rows of ``df`` with their place, from zero, in the order of ``keys``, and the number of rows.

    Keys are names (ascending, nulls first) or orderings; they should leave no ties but equal rows.
    """
    placed = _placed(df, _order(keys), tag)
    found = _with_offsets(placed, F.count("*")).withColumn(rank_col, F.col("_before") + F.col("_place"))
    return found.drop("_place", "_part", "_before"), placed.count()


def sums_before(df: DataFrame, keys: list[str | Column], weight: str, out: str = "below", tag: str = "sums") -> DataFrame:
    """Rows of ``df`` with the sum of ``weight`` over all rows before them in the order of ``keys``."""
    placed = _placed(df, _order(keys), tag)
    within = F.coalesce(F.sum(weight).over(Window.partitionBy("_part").orderBy("_place").rowsBetween(*_BEFORE)), F.lit(0))
    found = _with_offsets(placed.withColumn("_within", within), F.sum(weight))
    return found.withColumn(out, F.col("_before") + F.col("_within")).drop("_place", "_part", "_before", "_within")


def ntile(df: DataFrame, keys: list[str | Column], tiles: int, out: str, tag: str = "tiles") -> DataFrame:
    """Rows with the number, from one, of their tile in the order of ``keys``: sizes differ by one at most, larger first."""
    found, n = ranked(df, keys, "_rank", tag)
    size, larger = n // tiles, n % tiles
    edge = larger * (size + 1)
    tile = F.when(F.col("_rank") < edge, F.floor(F.col("_rank") / (size + 1))).otherwise(larger + F.floor((F.col("_rank") - edge) / max(1, size)))
    return found.withColumn(out, (tile + 1).cast("int")).drop("_rank")
