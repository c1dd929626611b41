import zlib

import pytest
from pyspark.sql import functions as F

from entlink.llm import hilbert_shards as h


@pytest.mark.parametrize("dims,bits", [(2, 4), (3, 3)])
def test_curve_visits_every_cell_by_unit_steps(spark, dims, bits):
    side = 1 << bits
    cells = spark.range(side**dims)
    coords = [(F.floor(F.col("id") / side**k) % side).cast("int") for k in range(dims)]
    rows = cells.select(h.hilbert_index(coords, bits).alias("i"), *[c.alias(f"c{k}") for k, c in enumerate(coords)]).orderBy("i").collect()
    assert [r.i for r in rows] == list(range(side**dims))
    for a, b in zip(rows, rows[1:]):
        assert sum(abs(a[f"c{k}"] - b[f"c{k}"]) for k in range(dims)) == 1


def test_shards_follow_the_law(spark):
    rows = [(i, "é" * (i % 50), ["en", "fr", None][i % 3], f"s{i % 7}", "x") for i in range(1003)] + [(None, None, "en", "s1", "x"), (5, "dup", "en", None, "x"), (5, "dup", "en", None, "x")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, shard string")
    got = h.assign_shards(docs, 16).collect()
    assert len(got) == len(rows)
    counts = [sum(r.shard == s for r in got) for s in range(16)]
    assert max(counts) - min(counts) <= 1
    for s in range(16):
        assert sorted(r.slot for r in got if r.shard == s) == list(range(counts[s]))
    for r in got:
        if r.doc_id is not None and r.doc_id != 5:
            t = rows[r.doc_id][1].encode()
            assert (r.size, r.text_crc32) == (len(t) + 1, zlib.crc32(t))
    assert [(r.size, r.text_crc32) for r in got if r.doc_id is None] == [(1, 0)]
    order = sorted(got, key=lambda r: (r.shard, r.slot))
    assert [r.curve for r in order] == sorted(r.curve for r in got)
    assert h.assign_shards(docs.where("false")).count() == 0
    assert h.assign_shards(docs.limit(3)).count() == 3


def test_steps_are_exact_and_repeatable(spark):
    rows = [(None if i % 11 == 0 else i * i % 37 if i % 3 else 5,) for i in range(1000)]
    known = sorted(v for (v,) in rows if v is not None)
    want = {v: known.index(v) * 8 // len(known) for v in set(known)}
    for parts in (1, 7):
        df = spark.createDataFrame(rows, "v int").repartition(parts)
        cut = h.edges(df, "v", 3)
        got = {r.v: r.s for r in df.select("v", h.step_of(F.col("v"), cut).alias("s")).distinct().collect()}
        assert got == want | {None: 0}
    docs = spark.createDataFrame([(i, "x" * (i * 7 % 90), ["en", "fr"][i % 2], f"s{i % 5}") for i in range(500)], "doc_id long, text string, lang string, source string")
    a, b = (sorted(h.assign_shards(docs.repartition(n)).collect()) for n in (1, 9))
    assert a == b


def test_files_hold_all_rows_once_and_prune(spark, tmp_path):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    path = f"{tmp_path}/shards"
    h.write_shards(docs, path, 16)
    back = spark.read.parquet(path)
    assert sorted(back.select(*docs.columns).collect()) == sorted(docs.collect())
    # Files whose minimum and maximum let a filter on one dimension skip them, over all values: the plain order skips next to none.
    def skipped(frame, column, part):
        ends = frame.groupBy(part).agg(F.min(column).alias("lo"), F.max(column).alias("hi")).collect()
        values = [r[0] for r in docs.select(column).distinct().collect()]
        return sum(not e.lo <= v <= e.hi for e in ends for v in values) / (len(ends) * len(values))

    plain = docs.withColumn("_shard", F.pmod(F.xxhash64("doc_id"), F.lit(16)))
    for column in ("lang", "source"):
        assert skipped(back, column, "_shard") > 0.2 + skipped(plain, column, "_shard")
    twice = spark.createDataFrame([(5, "a", "en", "s"), (5, "a", "en", "s"), (5, "b", None, None)], "doc_id long, text string, lang string, source string")
    h.write_shards(twice, f"{tmp_path}/twice", 2)
    assert sorted(map(str, spark.read.parquet(f"{tmp_path}/twice").select(*twice.columns).collect())) == sorted(map(str, twice.collect()))
