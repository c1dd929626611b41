"""Triples and nested XML entries, to and from relations."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def to_triples(df: DataFrame, key: str, columns: list[str]) -> DataFrame:
    """``(subject, predicate, object)`` strings of all non-null attributes."""
    texts = df.select(F.col(key).cast("string").alias("subject"), *[F.col(c).cast("string").alias(c) for c in columns])
    return texts.unpivot("subject", columns, "predicate", "object").where("object is not null")


def pivot_triples(triples: DataFrame, predicates: list[str]) -> DataFrame:
    """One row per subject; the list of predicates keeps the plan static."""
    return triples.groupBy("subject").pivot("predicate", predicates).agg(F.first("object"))


ENTRY = T.StructType(
    [
        T.StructField("_eid", T.StringType()),
        T.StructField("_category", T.StringType()),
        T.StructField("_size", T.IntegerType()),
        T.StructField("triples", T.StructType([T.StructField("triple", T.ArrayType(T.StringType()))])),
        T.StructField("lex", T.ArrayType(T.StringType())),
    ]
)


def write_entries(entries: DataFrame, path: str) -> None:
    """Write (eid, category, triples array, lex array) as XML entries."""
    shaped = entries.select(
        F.col("eid").alias("_eid"), F.col("category").alias("_category"), F.size("triples").alias("_size"), F.struct(F.col("triples").alias("triple")).alias("triples"), "lex"
    )
    shaped.write.mode("overwrite").format("xml").option("rowTag", "entry").option("rootTag", "entries").save(path)


def read_entries(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame]:
    """Triples (eid, subject, predicate, object) and texts (eid, no, text) of XML entries.

    Underscores stand for blanks in names, quotes around values are dropped.
    """
    rows = spark.read.format("xml").option("rowTag", "entry").schema(ENTRY).load(path)
    parts = rows.select(F.col("_eid").alias("eid"), F.explode("triples.triple").alias("t")).withColumn("p", F.split(F.trim("t"), r"\s*\|\s*"))
    clean = lambda i: F.regexp_replace(F.translate(F.element_at("p", i), "_", " "), '^"|"$', "")
    triples = parts.select("eid", clean(1).alias("subject"), F.element_at("p", 2).alias("predicate"), clean(3).alias("object"))
    texts = rows.select(F.col("_eid").alias("eid"), F.posexplode("lex").alias("no", "text")).withColumn("text", F.trim(F.regexp_replace("text", r"\s+", " ")))
    return triples, texts
