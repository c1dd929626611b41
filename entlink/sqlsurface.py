"""Linking from SQL: embedding functions, a link predicate, table functions, stored embeddings."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from entlink.ann.exact import exact_knn
from entlink.functions.text import bucket_and_sign, python_tokens
from entlink.joint.network import Tower
from entlink.joint.registry import ENCODERS
from entlink.joint.train import Config, encoded
from entlink.operators.vectorize import Codec, codecs, fk_vector, signature
from entlink.plans.link import link
from entlink.spec import NUMBER, TEXT, EntitySpec
from entlink.storage import materialize


def register_embeddings(spark: SparkSession, spec: EntitySpec, tables: dict[str, DataFrame], relation: Tower, text: Tower, config: Config) -> tuple[str, str]:
    """Make ``embed_<type>(attribute, ..., context, ...)`` and ``embed_mention_<type>(span, sentence, context)`` known to SQL.

    The first takes the attributes of the relation in declared order, each in its own type, and then for every foreign
    key the summed vector of what it refers to (column ``context_<column>`` of the view ``<type>_context``; null
    counts as zeros).  Statistics of the relation's columns and the weights are taken once and broadcast.
    """
    kind, model = spec.name.replace("-", "_"), ENCODERS[config.encoder]
    fitted = codecs(tables[spec.table], spec, config.text_dim)
    encode = lambda column, width: encoded(column, width, config.encoder)
    around, widths = tables[spec.table].select(F.col(spec.key).alias("key"), *[F.col(f.column).alias(f"_{f.column}") for f in spec.foreign_keys]), []
    for fk in spec.foreign_keys:
        target, layout = signature(tables, fk.target, config.text_dim, encode=encode)
        widths.append(layout[-1][2] + layout[-1][3])
        around = fk_vector(around, f"_{fk.column}", target.withColumnRenamed("v_r", "v_fk"), "key", "v_fk", widths[-1], f"context_{fk.column}")
    around.drop(*[f"_{f.column}" for f in spec.foreign_keys]).createOrReplaceTempView(f"{kind}_context")
    shared = spark.sparkContext.broadcast((relation, text))

    def block(codec: Codec, values: pd.Series) -> np.ndarray:
        if codec.kind == TEXT:
            return model.encode(values.astype(object).where(values.notna(), "").astype(str).tolist(), codec.width)
        if codec.kind == NUMBER:
            v = pd.to_numeric(values, errors="coerce").to_numpy(float)
            return np.nan_to_num((v - codec.mean) / codec.dev if codec.dev else np.zeros(len(v)))[:, None]
        known = {v: i for i, v in enumerate(codec.values)}
        out = np.zeros((len(values), codec.width))
        for i, v in enumerate(values):
            place = None if v is None or v != v else known.get(str(v), len(known) + bucket_and_sign(str(v), codec.shared)[0] if codec.shared else None)
            if place is not None:
                out[i, place] = 1.0
        return out

    @F.pandas_udf("array<double>")
    def tuples(*columns: pd.Series) -> pd.Series:
        blocks = [block(c, v) for c, v in zip(fitted, columns)]
        for width, vecs in zip(widths, columns[len(fitted) :]):
            blocks.append(np.array([np.zeros(width) if v is None else np.asarray(v, float) for v in vecs]).reshape(-1, width))
        return pd.Series(list(shared.value[0].forward(np.concatenate(blocks, axis=1))))

    @F.pandas_udf("array<double>")
    def mentions(span: pd.Series, sentence: pd.Series, context: pd.Series) -> pd.Series:
        quarter = config.dim // 4
        parts = ((span, quarter), (sentence, config.dim - 2 * quarter), (context, quarter))
        return pd.Series(list(shared.value[1].forward(np.concatenate([model.encode(v.fillna("").tolist(), w) for v, w in parts], axis=1))))

    names = f"embed_{kind}", f"embed_mention_{kind}"
    spark.udf.register(names[0], tuples)
    spark.udf.register(names[1], mentions)
    return names


def register_predicates(spark: SparkSession) -> None:
    """``link_matches(mention, name, strategy)`` for small data: equal, contains, shared_word."""
    spark.sql("""CREATE OR REPLACE TEMPORARY FUNCTION link_matches(mention STRING, name STRING, strategy STRING) RETURNS BOOLEAN RETURN
        CASE strategy WHEN 'equal' THEN lower(trim(mention)) = lower(trim(name))
                      WHEN 'contains' THEN contains(mention, name)
                      WHEN 'shared_word' THEN arrays_overlap(filter(split(lower(mention), '[^\\\\p{L}\\\\p{N}]+'), t -> t <> ''), filter(split(lower(name), '[^\\\\p{L}\\\\p{N}]+'), t -> t <> '')) END""")


def knn_links(spark: SparkSession, queries: str, base: str, n: int = 10, view: str = "knn") -> DataFrame:
    """Nearest rows of table ``base`` for each row of table ``queries`` (both id, vec), also as a temporary view."""
    found = link(spark.table(queries), spark.table(base), "semantic", n=n)
    found = found.select(F.col("name_id").alias("query_key"), F.col("text_id").alias("result_key"), "distance", "rank")
    found.createOrReplaceTempView(view)
    return found


def store_embeddings(df: DataFrame, table: str) -> None:
    """Keep embeddings as a table of the catalog, bucketed by id so that later joins on it need no shuffle."""
    df.write.mode("overwrite").bucketBy(8, "id").sortBy("id").saveAsTable(table)


def pack(vec: pd.Series) -> pd.Series:
    """Vectors as little-endian 32-bit bytes."""
    return vec.map(lambda v: np.asarray(v, "<f4").tobytes())


def unpack(raw: pd.Series) -> pd.Series:
    return raw.map(lambda b: np.frombuffer(b, "<f4").tolist())


def pack_vectors(column: str) -> Column:
    return F.pandas_udf(pack, "binary")(column)


def unpack_vectors(column: str | Column) -> Column:
    return F.pandas_udf(unpack, "array<float>")(column)


def blocking(df: DataFrame, apply) -> DataFrame:
    """``apply`` as a blocking operator in one task: the baseline for functions that cannot run in parallel."""
    return apply(df.coalesce(1))


def shipped(df: DataFrame, apply) -> DataFrame:
    """``apply`` after a detour over text files: the baseline of shipping data to another tool."""
    from entlink.storage import scratch_path

    path = scratch_path(df.sparkSession, "shipped")
    df.write.option("escape", '"').csv(path)
    return apply(df.sparkSession.read.schema(df.schema).option("escape", '"').csv(path))


def relaxed_word_movers(pairs: DataFrame, words: dict[str, list[float]]) -> DataFrame:
    """Lower bound of the word mover's distance for (a, b) texts: each word moves to its nearest word of the other side."""
    shared = pairs.sparkSession.sparkContext.broadcast({k: np.asarray(v, float) for k, v in words.items()})

    @F.pandas_udf("double")
    def bound(a: pd.Series, b: pd.Series) -> pd.Series:
        def one(x, y):
            p, q = ([shared.value[t] for t in python_tokens(s) if t in shared.value] for s in (x, y))
            if not p or not q:
                return None
            d = np.linalg.norm(np.array(p)[:, None] - np.array(q)[None], axis=2)
            return float(max(d.min(1).mean(), d.min(0).mean()))

        return pd.Series([one(x, y) for x, y in zip(a, b)], dtype=object).astype(float)

    return pairs.withColumn("distance", bound("a", "b"))


def movement(df: DataFrame) -> DataFrame:
    """What a query moved: one row per node metric that counts shuffled bytes or rows through Python, after it ran."""
    df.write.format("noop").mode("overwrite").save()
    spark, rows = df.sparkSession, []

    def walk(node):
        if node.nodeName().startswith("AdaptiveSparkPlan"):
            walk(node.executedPlan())
            return
        metrics = node.metrics()
        for name in ("shuffleBytesWritten", "dataSize", "pythonDataSent", "pythonDataReceived", "numOutputRows"):
            if metrics.contains(name):
                rows.append((node.nodeName(), name, int(metrics.apply(name).value())))
        kids = node.children()
        for i in range(kids.size()):
            walk(kids.apply(i))

    walk(df._jdf.queryExecution().executedPlan())
    return spark.createDataFrame(rows or [("none", "none", 0)], "node string, metric string, value long")


def embed_and_link(left: DataFrame, right: DataFrame, n: int = 10) -> DataFrame:
    """Exact links of stored embeddings (id, vec), joined back late: only ids and distances are shuffled."""
    return exact_knn(materialize(left.select("id", "vec"), "left"), materialize(right.select("id", "vec"), "right"), n)
