"""Exact deduplication by content sort, in DataFrame functions only.

The normalised text is the sort key.  Spark samples splitters, deals the rows
out by range and sorts each range externally, so equal texts become neighbours;
a window over runs of equal text compares them in full and ranks each run by
identifier.  A splitter is the first ``PREFIX`` characters with a 64-bit hash
to part texts that begin alike, so the sample on the driver stays small however
long the texts are; inside a range the whole text decides, and nothing depends
on the hash being free of collisions.

A text that makes up more than one in ``HOT_SHARE`` rows would overload its
range.  Such texts (fewer than ``HOT_SHARE`` of them, whatever the input) are
found by a count of 64-bit hashes and get a salt that spreads their rows over
``SALTS`` runs; the few run winners are merged afterwards.

Defined results: a null text counts as empty; null identifiers rank after all
others; of rows with equal text and equal identifier one stays; an empty table
gives an empty table.  Other columns of the input are carried in one struct,
so their names cannot clash with ours.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from entlink.llm.textnorm import fold_ascii_case
from entlink.storage import materialize

HOT_SHARE = 1000
SALTS = 64
PREFIX = 32


def hot_hashes(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """Hashes of texts held by more than one in ``HOT_SHARE`` rows (fewer than ``HOT_SHARE`` rows)."""
    hashed = docs.select(F.xxhash64(fold_ascii_case(F.col(text_col))).alias("hot_hash"))
    counts = materialize(hashed.groupBy("hot_hash").agg(F.count("*").alias("n")), "dedup-counts")
    total = counts.agg(F.sum("n").alias("total"))
    return counts.join(F.broadcast(total), F.col("n") * HOT_SHARE > F.col("total")).select("hot_hash")


def sorted_runs(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "smallest") -> DataFrame:
    """Rows in content order, each with its place in its run of equal texts.

    Returns ``row`` (struct of all input columns), ``hot`` and ``salt`` (of its run),
    ``place`` (1 for the row that stays), ``first_id`` and ``run_size``.
    """
    spark = docs.sparkSession
    hot = hot_hashes(docs, text_col).collect()  # fewer than HOT_SHARE longs
    hot_list = F.array(*[F.lit(r.hot_hash) for r in hot]) if hot else F.array().cast("array<bigint>")
    rows = docs.select(
        F.struct("*").alias("row"),
        F.col(id_col).alias("id"),
        fold_ascii_case(F.col(text_col)).alias("norm"),
    )
    rows = rows.withColumn("head", F.substring("norm", 1, PREFIX)).withColumn("hash", F.xxhash64("norm"))
    rows = rows.withColumn("hot", F.array_contains(hot_list, F.col("hash")) if hot else F.lit(False))
    rows = rows.withColumn("salt", F.when(F.col("hot"), F.pmod(F.xxhash64("id"), F.lit(SALTS)).cast("int")).otherwise(F.lit(0)))
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    ranged = rows.repartitionByRange(parts, "head", "hash", "salt")
    order = F.col("id").asc_nulls_last() if keep == "smallest" else F.col("id").desc_nulls_last()
    run = Window.partitionBy("head", "hash", "salt", "norm")
    placed = run.orderBy(order)
    return ranged.select(
        "row",
        "norm",
        "hot",
        "salt",
        F.row_number().over(placed).alias("place"),
        F.first("id").over(placed).alias("first_id"),
        F.count("*").over(run).alias("run_size"),
    )


def _winners(runs: DataFrame, keep: str) -> DataFrame:
    """For each hot text: the row that stays and the size over all its salted runs."""
    heads = runs.where(F.col("hot") & (F.col("place") == 1))
    order = F.col("first_id").asc_nulls_last() if keep == "smallest" else F.col("first_id").desc_nulls_last()
    w = Window.partitionBy("digest")
    return (
        heads.select(
            "digest",
            F.row_number().over(w.orderBy(order, "salt")).alias("n"),
            F.col("salt").alias("win_salt"),
            F.col("first_id").alias("win_id"),
            F.sum("run_size").over(w).alias("win_size"),
        )
        .where("n = 1")
        .drop("n")
    )


def decisions(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "smallest") -> DataFrame:
    """One row per input row: id, ``keep_id``, ``group_size``, ``kept``, ``text_sha256``."""
    slim = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    runs = sorted_runs(slim, "id", "text", keep).select(
        F.col("row.id").alias("id"), "hot", "salt", "place", "first_id", "run_size", F.unhex(F.sha2("norm", 256)).alias("digest")
    )
    runs = materialize(runs, "dedup-runs")
    joined = runs.join(F.broadcast(_winners(runs, keep)), "digest", "left")
    hot = F.col("win_size").isNotNull()
    return joined.select(
        F.col("id").alias(id_col),
        F.when(hot, F.col("win_id")).otherwise(F.col("first_id")).alias("keep_id"),
        F.coalesce("win_size", "run_size").alias("group_size"),
        ((F.col("place") == 1) & (~hot | (F.col("salt") == F.col("win_salt")))).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
    )


def survivors(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "smallest") -> DataFrame:
    """The rows that stay, whole, with the columns of the input."""
    runs = sorted_runs(docs, id_col, text_col, keep).where("place = 1")
    heads = materialize(
        runs.select(
            "row", "hot", "salt", "place", "first_id", "run_size",
            F.when(F.col("hot"), F.unhex(F.sha2("norm", 256))).alias("digest"),
        ),
        "dedup-heads",
    )
    joined = heads.join(F.broadcast(_winners(heads, keep)), "digest", "left")
    return joined.where(F.col("win_salt").isNull() | (F.col("salt") == F.col("win_salt"))).select("row.*")
