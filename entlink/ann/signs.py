"""Sign-random-projection hashing: bits of dot products with hashed planes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def plane_value(table_no: Column, bit: Column, i: Column) -> Column:
    """Coordinate i of a plane: a number in [-1, 1) by md5."""
    key = F.concat_ws("|", table_no.cast("string"), bit.cast("string"), i.cast("string"))
    return F.conv(F.substring(F.md5(key), 1, 8), 16, 10).cast("bigint") / 2147483648.0 - 1.0


def planes(spark, tables: int, bits: int, width: int) -> DataFrame:
    rows = spark.range(tables * bits * width).select(
        F.floor(F.col("id") / (bits * width)).cast("int").alias("table_no"), (F.floor(F.col("id") / width) % bits).cast("int").alias("bit"), (F.col("id") % width).cast("int").alias("i")
    )
    return rows.withColumn("w", plane_value(F.col("table_no"), F.col("bit"), F.col("i")))


def buckets(vectors: DataFrame, tables: int, bits: int, width: int) -> DataFrame:
    """``(id, table_no, bucket)`` for vectors (id, vec)."""
    cells = vectors.select("id", F.posexplode("vec").alias("i", "x"))
    dots = cells.join(F.broadcast(planes(vectors.sparkSession, tables, bits, width)), "i").groupBy("id", "table_no", "bit").agg(F.sum(F.col("x").cast("double") * F.col("w")).alias("d"))
    return dots.groupBy("id", "table_no").agg(F.sum(F.when(F.col("d") > 0, F.pow(F.lit(2.0), F.col("bit"))).otherwise(0.0)).cast("int").alias("bucket"))


def candidates(found: DataFrame) -> DataFrame:
    """Pairs of ids that share a bucket in some table."""
    a, b = found.withColumnRenamed("id", "a_id"), found.withColumnRenamed("id", "b_id")
    return a.join(b, ["table_no", "bucket"]).where("a_id < b_id").select("a_id", "b_id").distinct()
