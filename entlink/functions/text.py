"""Hashing and tokens, equal in Spark and DuckDB."""

from __future__ import annotations

import hashlib
import re
from functools import lru_cache

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SEPARATORS = r"[^\p{L}\p{N}]+"


def h(value: Column) -> Column:
    """The first eight hex digits of the md5 of a string, as a number."""
    return F.conv(F.substring(F.md5(value), 1, 8), 16, 10).cast("bigint")


def sign(value: Column) -> Column:
    """Plus or minus one by the next eight hex digits."""
    odd = F.conv(F.substring(F.md5(value), 9, 8), 16, 10).cast("bigint") % 2
    return F.when(odd == 0, F.lit(1)).otherwise(F.lit(-1))


def tokens(text: Column) -> Column:
    """Lower-cased runs of letters and digits; null gives an empty array."""
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), SEPARATORS), lambda x: x != "")


_WORD = re.compile(r"[^\W_]+")


def python_tokens(text: str | None) -> list[str]:
    return _WORD.findall((text or "").lower())


@lru_cache(maxsize=200_000)
def bucket_and_sign(token: str, dim: int) -> tuple[int, int]:
    d = hashlib.md5(token.encode()).hexdigest()
    return int(d[:8], 16) % dim, 1 - 2 * (int(d[8:16], 16) & 1)


def hashed_bag(text: str | None, dim: int, grams: tuple[int, int] | None = None) -> np.ndarray:
    """Signed counts of tokens, or of character n-grams of padded tokens if ``grams`` is given."""
    out = np.zeros(dim)
    units = python_tokens(text)
    if grams:
        units = [f"^{t}$"[i : i + n] for t in units for n in range(grams[0], grams[1] + 1) for i in range(len(t) + 3 - n)]
    for u in units:
        b, s = bucket_and_sign(u, dim)
        out[b] += s
    return out
