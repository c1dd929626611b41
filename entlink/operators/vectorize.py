"""Vectorisation: typed attribute blocks, foreign-key sums, concatenated signatures, text encoders."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from entlink.functions.text import h, hashed_bag, python_tokens, tokens
from entlink.spec import NUMBER, ONE_HOT, TEXT, EntitySpec


def normalized(df: DataFrame, columns: list[str], null_policy: str = "zero") -> DataFrame:
    """Add ``<column>_z``: (value - mean) / population deviation over the relation, in one aggregate.

    A constant column gives zero.  Nulls give zero, the same as the mean; ``indicator`` adds ``<column>_set``.
    """
    stats = df.agg(*[f(F.col(c).cast("double")).alias(f"{n}_{c}") for c in columns for n, f in (("mean", F.avg), ("dev", F.stddev_pop))])
    out = df.crossJoin(F.broadcast(stats))  # one row
    for c in columns:
        z = (F.col(c).cast("double") - F.col(f"mean_{c}")) / F.nullif(F.col(f"dev_{c}"), F.lit(0.0))
        out = out.withColumn(f"{c}_z", F.coalesce(z, F.lit(0.0)))
        if null_policy == "indicator":
            out = out.withColumn(f"{c}_set", F.col(c).isNotNull().cast("double"))
    return out.drop(*[f"{n}_{c}" for c in columns for n in ("mean", "dev")])


CATEGORIES, SHARED = 256, 64


def domain(df: DataFrame, column: str, max_categories: int = CATEGORIES) -> list[str]:
    """Sorted distinct values of a column, the most frequent ``max_categories`` of them; others share hashed places."""
    return _domain(df, column, max_categories)[0]


def _domain(df: DataFrame, column: str, max_categories: int) -> tuple[list[str], bool]:
    rows = df.where(F.col(column).isNotNull()).groupBy(F.col(column).cast("string").alias("v")).count()
    top = [r.v for r in rows.orderBy(F.desc("count"), "v").limit(max_categories + 1).collect()]
    return sorted(top[:max_categories]), len(top) > max_categories


def one_hot(value: Column, values: list[str], shared: int = 0) -> Column:
    """Array of zeros with a one at the value's place; null gives zeros only.

    Unknown values give zeros too, or, with ``shared`` places behind the known ones, a one at the place of their hash.
    """
    place = F.array_position(F.array(*[F.lit(v) for v in values]), value.cast("string")) if values else F.lit(0)
    place = F.coalesce(place, F.lit(0)).cast("int")
    if shared:
        place = F.when((place == 0) & value.isNotNull(), (len(values) + 1 + h(value.cast("string")) % shared).cast("int")).otherwise(place)
    return F.transform(F.sequence(F.lit(1), F.lit(max(1, len(values) + shared))), lambda i: (i == place).cast("double"))


def constraint_flags(df: DataFrame, ranges: dict[str, tuple[float | None, float | None]]) -> list[Column]:
    """One number for each constrained column: one within its range, minus one outside, zero for null or no number."""
    flags = []
    for c, (lo, hi) in ranges.items():
        v = F.col(c).cast("double")
        good = (v >= lo if lo is not None else F.lit(True)) & (v <= hi if hi is not None else F.lit(True))
        flags.append(F.when(v.isNull(), 0.0).when(good, 1.0).otherwise(-1.0))
    return flags


def hashed_long(df: DataFrame, id_col: str, text_col: str, dim: int) -> DataFrame:
    """``(id, bucket, value)``: signed token counts by hash bucket, scaled to unit length.

    Tokens are counted before they are hashed, so a hash is taken once for a token of a text and not for each time it occurs.
    """
    rows = df.select(F.col(id_col).alias("id"), F.explode(tokens(F.col(text_col))).alias("token"))
    counts = rows.groupBy("id", "token").agg(F.count("*").alias("n")).withColumn("md5", F.md5("token"))
    digits = lambda at: F.conv(F.substring("md5", at, 8), 16, 10).cast("bigint")
    signed = F.when(digits(9) % 2 == 0, F.col("n")).otherwise(-F.col("n"))
    cells = counts.groupBy("id", (digits(1) % dim).cast("int").alias("bucket")).agg(F.sum(signed).alias("raw")).where("raw != 0")
    length = F.sqrt(F.sum(F.col("raw") * F.col("raw")).over(Window.partitionBy("id")))
    return cells.select("id", "bucket", (F.col("raw") / length).alias("value"))


def tfidf_long(df: DataFrame, id_col: str, text_col: str, min_df: int = 2) -> DataFrame:
    """``(id, token, weight)``: count times ln(N / df), for tokens in at least ``min_df`` rows."""
    counts = df.select(F.col(id_col).alias("id"), F.explode(tokens(F.col(text_col))).alias("token")).groupBy("id", "token").agg(F.count("*").alias("tf"))
    dfs = counts.groupBy("token").agg(F.count("*").alias("df")).where(F.col("df") >= min_df)
    n = df.agg(F.count("*").alias("n"))
    return counts.join(dfs, "token").crossJoin(F.broadcast(n)).select("id", "token", (F.col("tf") * F.log(F.col("n") / F.col("df"))).alias("weight"))


def hashed_dense(text: Column, dim: int, grams: tuple[int, int] | None = None) -> Column:
    """Unit vector of the hashed bag of a text, of words or of character n-grams."""

    @F.pandas_udf("array<double>")
    def run(texts: pd.Series) -> pd.Series:
        def one(t):
            v = hashed_bag(t, dim, grams)
            n = np.sqrt(v @ v)
            return v / n if n else v

        return texts.map(one)

    return run(F.coalesce(text, F.lit("")))


def vector_sum(df: DataFrame, by: str, vec: str, width: int) -> DataFrame:
    """Element-wise sum of vectors by key, with partial sums before the shuffle."""
    sums = df.groupBy(by).agg(*[F.sum(F.element_at(vec, i + 1)).alias(f"e{i}") for i in range(width)])
    return sums.select(by, F.array(*[F.col(f"e{i}") for i in range(width)]).alias(vec))


def fk_vector(df: DataFrame, fk: str, target: DataFrame, target_key: str, vec: str, width: int, out: str) -> DataFrame:
    """Sum of the vectors of all target rows that the key names; no target gives zeros.

    Targets are summed by key before the join, so a key with many rows joins one.
    """
    sums = vector_sum(target.select(F.col(target_key).alias("_key"), F.col(vec)), "_key", vec, width)
    zeros = F.array_repeat(F.lit(0.0), width)
    return df.join(sums.withColumnRenamed(vec, out), F.col(fk) == F.col("_key"), "left").drop("_key").withColumn(out, F.coalesce(out, zeros))


@dataclass(frozen=True)
class Codec:
    """How one attribute becomes a block: fitted statistics, small enough for the driver."""

    column: str
    kind: str
    width: int
    mean: float = 0.0
    dev: float = 0.0
    values: tuple[str, ...] = ()
    shared: int = 0


def codecs(df: DataFrame, spec: EntitySpec, text_dim: int) -> list[Codec]:
    """Codecs of a relation's attributes in declared order; numbers take one aggregate for all columns together."""
    numbers = [c for c, k in spec.attributes.items() if k == NUMBER]
    stats = df.agg(*[f(F.col(c).cast("double")).alias(f"{n}_{c}") for c in numbers for n, f in (("mean", F.avg), ("dev", F.stddev_pop))]).first() if numbers else {}
    found = []
    for c, kind in spec.attributes.items():
        if kind == TEXT:
            found.append(Codec(c, kind, text_dim))
        elif kind == NUMBER:
            found.append(Codec(c, kind, 1, stats[f"mean_{c}"] or 0.0, stats[f"dev_{c}"] or 0.0))
        else:
            values, more = _domain(df, c, CATEGORIES)
            shared = SHARED if more else 0
            found.append(Codec(c, kind, max(1, len(values) + shared), values=tuple(values), shared=shared))
    return found


def block(codec: Codec, encode=None) -> Column:
    """The vector block of one attribute."""
    value = F.col(codec.column)
    if codec.kind == TEXT:
        return (encode or hashed_dense)(value.cast("string"), codec.width)
    if codec.kind == NUMBER:
        z = (value.cast("double") - F.lit(codec.mean)) / F.nullif(F.lit(codec.dev), F.lit(0.0))
        return F.array(F.coalesce(z, F.lit(0.0)))
    return one_hot(value, list(codec.values), codec.shared)


def signature(tables: dict[str, DataFrame], spec: EntitySpec, text_dim: int = 32, depth: int = 3, null_policy: str = "zero", encode=None,
              ranges: dict[str, tuple[float | None, float | None]] | None = None, keys: DataFrame | None = None) -> tuple[DataFrame, list[tuple[str, str, int, int]]]:
    """``(key, v_r)`` of a relation and the layout (block, codec, offset, width) of its vectors.

    Blocks stand in declared order, attributes first, then flags of the constraints ``ranges``, then foreign keys; the
    relation that a key refers to is vectorised the same way, down to ``depth`` references.  Texts go through
    ``encode(column, width)``, hashed words by default.  Null numbers give zero, the mean; ``indicator`` adds whether
    the number is set.  With ``keys``, a frame of the relation's key, only those rows get a vector; statistics are of all rows.
    """
    df = tables[spec.table]
    blocks, layout, at = [], [], 0

    def add(name, kind, column, width):
        nonlocal at
        blocks.append(column)
        layout.append((name, kind, at, width))
        at += width

    for c in codecs(df, spec, text_dim):
        if c.kind == NUMBER and null_policy == "indicator":
            add(c.column, c.kind, F.concat(block(c), F.array(F.col(c.column).isNotNull().cast("double"))), 2)
        else:
            add(c.column, c.kind, block(c, encode), c.width)
    if ranges:
        add("constraints", "flags", F.array(*constraint_flags(df, ranges)), len(ranges))
    if keys is not None:
        df = df.join(keys, spec.key, "left_semi")
    rows = df.select(F.col(spec.key).alias("key"), *[F.col(f.column) for f in spec.foreign_keys if f.column != spec.key], F.concat(*blocks).alias("v_r"))
    for fk in spec.foreign_keys if depth > 0 else ():
        target, inner = signature(tables, fk.target, text_dim, depth - 1, null_policy, encode)
        width = inner[-1][2] + inner[-1][3]
        rows = fk_vector(rows, fk.column, target.withColumnRenamed("v_r", "v_fk"), "key", "v_fk", width, "v_fk_sum")
        rows = rows.withColumn("v_r", F.concat("v_r", "v_fk_sum")).drop("v_fk_sum")
        layout.append((fk.column, "foreign_key", at, width))
        at += width
    return rows.select("key", "v_r"), layout


def reverse_fk(df: DataFrame, key: str, facts: DataFrame, fk: str, measures: list[str]) -> DataFrame:
    """Sums of fact measures over the rows that refer to each tuple, zero where none does."""
    sums = facts.groupBy(F.col(fk).alias("_key")).agg(*[F.sum(m).alias(m) for m in measures])
    return df.join(sums, F.col(key) == F.col("_key"), "left").drop("_key").fillna(0.0, measures)


class NeighborSentenceEncoder:
    """A linear sentence encoder trained to tell a sentence's neighbours from other sentences.

    A hashed bag is mapped to ``width`` numbers; the map is learned by stochastic gradient steps on the
    logistic score of (sentence, neighbour) against in-batch others.  A stand-in for a pre-trained encoder.
    """

    def __init__(self, weights: np.ndarray):
        self.weights = weights

    @classmethod
    def fit(cls, pairs: DataFrame, dim: int = 256, width: int = 64, epochs: int = 2, rate: float = 0.3, batch: int = 64, max_pairs: int = 20_000, seed: int = 1) -> NeighborSentenceEncoder:
        """``pairs`` has text and next_text; at most ``max_pairs`` of them, drawn by hash, are used in one task."""
        sample = pairs.select("text", "next_text").orderBy(h(F.col("text")), "text", "next_text").limit(max_pairs)

        def learn(batches):
            rows = pd.concat([b for b in batches] or [pd.DataFrame({"text": [], "next_text": []})])
            a = np.array([hashed_bag(t, dim) for t in rows.text]).reshape(-1, dim)
            b = np.array([hashed_bag(t, dim) for t in rows.next_text]).reshape(-1, dim)
            a, b = (x / np.maximum(1e-9, np.linalg.norm(x, axis=1, keepdims=True)) for x in (a, b))
            w = np.random.default_rng(seed).normal(0, width**-0.5, (dim, width))
            for _ in range(epochs):
                for i in range(0, len(a) - batch + 1, batch):
                    x, y = a[i : i + batch], b[i : i + batch]
                    p, q = x @ w, y @ w
                    s = p @ q.T
                    e = np.exp(s - s.max(axis=1, keepdims=True))
                    g = e / e.sum(axis=1, keepdims=True) - np.eye(len(x))
                    w -= rate / len(x) * (x.T @ (g @ q) + y.T @ (g.T @ p))
            yield pd.DataFrame({"weights": [w.ravel().tolist()]})

        found = sample.coalesce(1).mapInPandas(learn, "weights array<double>").first()
        return cls(np.array(found.weights).reshape(dim, width))

    def transform(self, text: Column) -> Column:
        w = self.weights

        @F.pandas_udf("array<double>")
        def run(texts: pd.Series) -> pd.Series:
            def one(t):
                v = hashed_bag(t, w.shape[0])
                v = (v / max(1e-9, np.sqrt(v @ v))) @ w
                return v / max(1e-9, np.sqrt(v @ v))

            return texts.map(one)

        return run(F.coalesce(text, F.lit("")))


    def encode(self, texts: list[str], width: int | None = None) -> np.ndarray:
        """Unit vectors of texts; ``width`` is that of the model."""
        bags = np.array([hashed_bag(t, self.weights.shape[0]) for t in texts]).reshape(-1, self.weights.shape[0])
        out = bags / np.maximum(1e-9, np.linalg.norm(bags, axis=1, keepdims=True)) @ self.weights
        return out / np.maximum(1e-9, np.linalg.norm(out, axis=1, keepdims=True))

    def save(self, spark, path: str) -> None:
        rows = [(i, w.tolist()) for i, w in enumerate(self.weights)]
        spark.createDataFrame(rows, "row int, weights array<double>").coalesce(1).write.mode("overwrite").parquet(path)

    @classmethod
    def load(cls, spark, path: str) -> NeighborSentenceEncoder:
        return cls(np.array([r.weights for r in spark.read.parquet(path).orderBy("row").collect()]))


class WordVectorEncoder:
    """Mean of given word vectors; words without one are left out, a text without any gives zeros."""

    def __init__(self, vectors: dict[str, np.ndarray]):
        self.vectors = {w: np.asarray(v, float) for w, v in vectors.items()}
        self.width = len(next(iter(self.vectors.values()), ()))

    @classmethod
    def load(cls, table: DataFrame) -> WordVectorEncoder:
        """From a table (word, vec) that fits the driver, as a vocabulary does."""
        return cls({r.word: np.array(r.vec) for r in table.select("word", "vec").collect()})

    def save(self, spark, path: str) -> None:
        rows = [(w, v.tolist()) for w, v in sorted(self.vectors.items())]
        spark.createDataFrame(rows, "word string, vec array<double>").write.mode("overwrite").parquet(path)

    def encode(self, texts: list[str], width: int | None = None) -> np.ndarray:
        out = np.zeros((len(texts), self.width))
        for i, t in enumerate(texts):
            known = [self.vectors[w] for w in python_tokens(t) if w in self.vectors]
            if known:
                out[i] = np.mean(known, axis=0)
        return out


def hybrid(*encoded: Column) -> Column:
    """Encodings of one text by several encoders, side by side."""
    return F.concat(*encoded)
