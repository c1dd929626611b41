"""Vector expressions that stay in the JVM, for single pairs and small tables."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(x: Column, y: Column) -> Column:
    return F.aggregate(F.zip_with(x, y, lambda a, b: a.cast("double") * b.cast("double")), F.lit(0.0), lambda s, v: s + v)


def norm(x: Column) -> Column:
    return F.sqrt(dot(x, x))


def cosine_distance(x: Column, y: Column) -> Column:
    """One minus the cosine, from 0 to 2; 1 if either vector is zero."""
    size = norm(x) * norm(y)
    return F.when(size > 0, 1 - dot(x, y) / size).otherwise(F.lit(1.0))


def euclidean_distance(x: Column, y: Column) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(x, y, lambda a, b: (a.cast("double") - b.cast("double")) ** 2), F.lit(0.0), lambda s, v: s + v))


def elu(x: Column) -> Column:
    return F.when(x > 0, x).otherwise(F.exp(x) - 1)


def unit(x: Column) -> Column:
    n = norm(x)
    return F.transform(x, lambda v: F.when(n > 0, v / n).otherwise(F.lit(0.0)))


def overlaps(a: Column, b: Column) -> Column:
    """Spans of the same document that share a character; spans are structs doc_id, start, end (end excluded)."""
    return (a["doc_id"] == b["doc_id"]) & (a["start"] < b["end"]) & (b["start"] < a["end"])


def covers(a: Column, b: Column) -> Column:
    return (a["doc_id"] == b["doc_id"]) & (a["start"] <= b["start"]) & (b["end"] <= a["end"])


def precedes(a: Column, b: Column) -> Column:
    return (a["doc_id"] == b["doc_id"]) & (a["end"] <= b["start"])


def covered_text(text: Column, span: Column) -> Column:
    return F.substring(text, span["start"] + 1, span["end"] - span["start"])
