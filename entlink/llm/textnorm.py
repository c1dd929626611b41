"""Text expressions that several operators share."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"


def fold_ascii_case(text: Column) -> Column:
    """Lower-case A-Z and nothing else; null becomes the empty string.

    Spark's ``lower`` also folds letters beyond ASCII, so it serves only texts
    of one byte per character, where it is the fast path.
    """
    text = F.coalesce(text, F.lit(""))
    ascii_only = F.octet_length(text) == F.char_length(text)
    return F.when(ascii_only, F.lower(text)).otherwise(F.translate(text, UPPER, UPPER.lower()))
