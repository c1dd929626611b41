"""Train, embed, link and score entity types: the accuracy experiments in one plan each."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from entlink.ann.exact import grouped_knn
from entlink.joint.network import Tower
from entlink.joint.train import Config, encoded, load_tower, mention_vector, train
from entlink.operators.evaluate import hit_at_k
from entlink.operators.vectorize import signature
from entlink.sources.mentions import PARTIAL, TYPE_NAMES, entity_type, relations, with_split
from entlink.spec import BY_NAME
from entlink.storage import held, materialize, measured_broadcasts


def relation_vectors(spark: SparkSession, sf_dir: str, name: str, config: Config, depth: int = 3, tables: dict[str, DataFrame] | None = None,
                     keys: DataFrame | None = None) -> DataFrame:
    """``(tuple_id, vec)``: the typed blocks and foreign-key sums of a type's relation, side by side; of ``keys`` only, if given."""
    encode = lambda column, width: encoded(column, width, config.encoder)
    found, _ = signature(tables or relations(spark, sf_dir), BY_NAME[name], config.text_dim, depth, encode=encode, keys=keys)
    return found.select(F.col("key").cast("string").alias("tuple_id"), F.col("v_r").cast("array<float>").alias("vec"))


def with_inputs(tuples: DataFrame, mentions: DataFrame, vectors: DataFrame | None, config: Config) -> tuple[DataFrame, DataFrame]:
    """Add ``vec``, what the towers read: relation vectors against span, sentence and context, or without
    ``vectors`` bags of both texts in one space."""
    if vectors is None:
        text = encoded(F.col("text"), config.dim, config.encoder)
        return tuples.withColumn("vec", text), mentions.withColumn("vec", text)
    return tuples.join(vectors, "tuple_id"), mentions.withColumn("vec", mention_vector(config))


def entity_frames(spark: SparkSession, sf_dir: str, types: tuple[str, ...] = TYPE_NAMES, config: Config = Config(), inputs: str = "signature") -> tuple[DataFrame, DataFrame]:  # noqa: B008
    """Tuples and split mentions of several types, each marked with its type, with what the towers read.

    ``inputs`` is ``signature`` (relation vectors), ``attributes`` (without foreign keys) or ``string`` (bags of texts).
    """
    measured_broadcasts(spark)
    cols, tables = ["mention_id", "tuple_id", "instance_id", "channel", "text"], relations(spark, sf_dir)
    left, right = [], []
    for n in types:
        t, m = entity_type(spark, sf_dir, n)
        keys = held(t.select(F.col("tuple_id").cast("bigint").alias(BY_NAME[n].key)), "keys") if n in PARTIAL and inputs != "string" else None
        vectors = None if inputs == "string" else relation_vectors(spark, sf_dir, n, config, 0 if inputs == "attributes" else 3, tables, keys)
        t, m = with_inputs(t, m, vectors, config)
        left.append(t.select(F.lit(n).alias("entity_type"), "tuple_id", "instance_id", "text", "vec"))
        right.append(m.select(F.lit(n).alias("entity_type"), *cols, "vec"))
    return materialize(reduce(DataFrame.unionByName, left), "tuples"), materialize(with_split(reduce(DataFrame.unionByName, right)), "mentions")


def embedded(df: DataFrame, towers: dict[str, Tower]) -> DataFrame:
    """``vec`` passed through the type's tower; as it is where there is none."""
    shared = df.sparkSession.sparkContext.broadcast(towers)

    @F.pandas_udf("array<float>")
    def run(batches: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for kinds, vecs in batches:
            out = vecs.to_numpy(copy=True)
            for kind in kinds.unique():
                tower = shared.value.get(kind)
                own = np.flatnonzero((kinds == kind).to_numpy())
                if tower is not None:
                    for i, v in zip(own, tower.forward(np.stack(out[own]).astype(float)).astype(np.float32)):
                        out[i] = v
            yield pd.Series(out)

    return df.withColumn("vec", run("entity_type", "vec"))


def trained(tuples: DataFrame, mentions: DataFrame, config: Config, start: DataFrame | None = None) -> DataFrame:
    """Weights from training mentions; tuples of unseen instances take no part.  ``start`` are weights to begin with."""
    seen = mentions.where("split = 'train'")
    known = tuples.join(seen.select("entity_type", "instance_id").distinct(), ["entity_type", "instance_id"], "left_semi")
    begin = None
    if start is not None:
        last = {r.entity_type: r.step for r in start.groupBy("entity_type").agg(F.max("step").alias("step")).collect()}  # one row per type
        begin = {k: tuple(load_tower(start, k, side, step) for side in ("relation", "text")) for k, step in last.items()}
    return materialize(train(known, seen, config, start=begin), "weights")


def embedded_sides(tuples: DataFrame, mentions: DataFrame, weights: DataFrame | None, config: Config, step: int | None = None) -> tuple[DataFrame, DataFrame]:
    """Tuples and mentions of all types in the learned space, written once; without weights what the towers read."""
    types = [r.entity_type for r in tuples.select("entity_type").distinct().collect()]  # one row per type
    step = config.steps if step is None else step
    gr, gt = ({}, {}) if weights is None else ({k: load_tower(weights, k, s, step) for k in types} for s in ("relation", "text"))
    return materialize(embedded(tuples, gr), "e-tuples"), materialize(embedded(mentions, gt), "e-mentions")


def links_of(tuples: DataFrame, mentions: DataFrame, weights: DataFrame | None, config: Config, n: int = 10, by: str = "tuple", metric: str = "cosine",
             step: int | None = None, pool: str = "split", split: str | None = None,
             sides: tuple[DataFrame, DataFrame] | None = None) -> DataFrame:
    """Ranked links of every type and split, with ``correct``; without weights by what the towers read.

    ``pool`` tells which mentions a tuple is compared with: those of its ``split``, or ``all`` mentions of the type.
    With ``split`` only tuples of that split are asked for; ``sides`` are ``embedded_sides`` made before.
    """
    measured_broadcasts(tuples.sparkSession)
    e_t, e_m = sides or embedded_sides(tuples, mentions, weights, config, step)
    pools = mentions.select("entity_type", "instance_id", "split").distinct()
    if split is not None:
        pools = pools.where(F.col("split") == split)
    grp = F.concat_ws("|", "entity_type", "split").alias("grp")
    t_rows = e_t.join(pools, ["entity_type", "instance_id"]).select(grp, F.col("tuple_id").alias("id"), "vec")
    if pool == "all" and by == "tuple":
        splits = pools.select("entity_type", "split").distinct()
        m_rows = e_m.drop("split").join(splits, "entity_type").select(grp, F.col("mention_id").alias("id"), "vec")
    else:
        m_rows = (e_m if split is None else e_m.where(F.col("split") == split)).select(grp, F.col("mention_id").alias("id"), "vec")
    queries, base = (t_rows, m_rows) if by == "tuple" else (m_rows, t_rows)
    found = grouped_knn(queries, base, n, metric, cells=True).withColumn("entity_type", F.split("grp", r"\|")[0]).withColumn("split", F.split("grp", r"\|")[1])
    t_key, m_key = ("query_id", "result_id") if by == "tuple" else ("result_id", "query_id")
    a = tuples.select("entity_type", F.col("tuple_id").alias(t_key), F.col("instance_id").alias("t_inst"))
    b = mentions.select("entity_type", F.col("mention_id").alias(m_key), F.col("instance_id").alias("m_inst"), "channel").distinct()
    out = found.join(a, ["entity_type", t_key]).join(b, ["entity_type", m_key])
    return out.withColumn("correct", F.col("t_inst") == F.col("m_inst")).select("entity_type", "split", "query_id", "result_id", "distance", "rank", "channel", "correct")


def accuracy_table(spark: SparkSession, sf_dir: str, types: tuple[str, ...] = TYPE_NAMES, config: Config = Config(), pools: tuple[str, ...] = ("split",),  # noqa: B008
                   inputs: str = "signature", split: str | None = None) -> DataFrame:
    """Hit rates at 1, 5 and 10 of every type over training, test and unseen entities, or one ``split`` of them, against each pool of mentions."""
    tuples, mentions = entity_frames(spark, sf_dir, types, config, inputs)
    weights = trained(tuples, mentions, config)
    sides = embedded_sides(tuples, mentions, weights, config)
    rows = [hit_at_k(links_of(tuples, mentions, weights, config, pool=p, split=split, sides=sides), ["entity_type", "split"]).withColumn("pool", F.lit(p)) for p in pools]
    return reduce(DataFrame.unionByName, rows)
