import numpy as np
import pytest
from pyspark.sql import functions as F

from entlink import sqlsurface as q
from entlink.joint.network import Tower
from entlink.joint.train import Config, encoded
from entlink.operators.vectorize import signature
from entlink.spec import CUSTOMER, PART

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("spec", [PART, CUSTOMER])
def test_embedding_functions_take_typed_columns(spark, spec):
    """The SQL function of raw columns gives what the tower makes of the relation's signature."""
    c = Config(dim=32, text_dim=16)
    tables = {n: spark.read.parquet(f"{SF}/{n}.parquet") for n in ("part", "customer", "nation", "region")}
    sig, layout = signature(tables, spec, c.text_dim, encode=lambda col, w: encoded(col, w))
    width = layout[-1][2] + layout[-1][3]
    towers = Tower((width, 8), 1), Tower((32, 8), 2)
    name, said = q.register_embeddings(spark, spec, tables, *towers, c)
    tables[spec.table].createOrReplaceTempView("t_rel")
    kind = spec.name.replace("-", "_")
    args = ", ".join([*spec.attributes, *[f"context_{f.column}" for f in spec.foreign_keys]])
    got = {r.key: r.e for r in spark.sql(f"SELECT key, {name}({args}) AS e FROM t_rel JOIN {kind}_context ON {spec.key} = key").collect()}
    want = {r.key: towers[0].forward(np.array([r.v_r], float))[0] for r in sig.collect()}
    assert got.keys() == want.keys() and all(np.allclose(got[k], want[k], atol=1e-6) for k in want)
    nulls = ", ".join(f"CAST(NULL AS {t.simpleString()})" for t in [tables[spec.table].schema[a].dataType for a in spec.attributes])
    nulls += "".join(", CAST(NULL AS array<double>)" for _ in spec.foreign_keys)
    assert len(spark.sql(f"SELECT {name}({nulls}) AS e").first().e) == 8
    assert len(spark.sql(f"SELECT {said}('red rod', 'a red rod.', NULL) AS e").first().e) == 8


def test_link_predicate(spark):
    q.register_predicates(spark)
    row = spark.sql("""SELECT link_matches('a Red Rod', 'red rod', 'shared_word') AS w, link_matches('a red rod', 'red rod', 'contains') AS c,
        link_matches(' Red Rod', 'red rod', 'equal') AS e, link_matches('blue', 'red', 'shared_word') AS n""").first()
    assert (row.w, row.c, row.e, row.n) == (True, True, True, False)


def test_knn_table_and_packing(spark):
    base = spark.read.parquet(f"{SF}/embeddings.parquet").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"))
    base.createOrReplaceTempView("t_vec")
    q.knn_links(spark, "t_vec", "t_vec", 3)
    assert spark.sql("SELECT count(*) AS n FROM knn WHERE query_key = result_key AND rank = 1").first().n == base.count()
    back = base.select("id", "vec", q.unpack_vectors(q.pack_vectors("vec")).alias("again"))
    assert back.where("vec != again").count() == 0
    assert q.embed_and_link(base.limit(20), base, 1).count() == 20


def test_baselines_give_the_same_rows(spark):
    df = spark.createDataFrame([(i, f'text "{i}", x') for i in range(50)], "id long, text string").repartition(4)
    work = lambda d: d.select("id", F.upper("text").alias("t"))
    want = sorted(work(df).collect())
    assert sorted(q.blocking(df, work).collect()) == want
    assert sorted(q.shipped(df, work).collect()) == want


def test_relaxed_word_movers(spark):
    words = {"cat": [0.0, 0.0], "dog": [3.0, 4.0], "cow": [0.0, 1.0]}
    df = spark.createDataFrame([("cat", "dog"), ("cat cow", "cow cat"), ("zzz", "cat")], "a string, b string")
    got = [r.distance for r in q.relaxed_word_movers(df, words).collect()]
    assert got[:2] == pytest.approx([5.0, 0.0]) and (got[2] is None or np.isnan(got[2]))


def test_movement_sees_shuffles(spark):
    got = q.movement(spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count())
    assert got.where("metric != 'none'").count() > 0
