"""The scan over shared blocks: same rows as all pairs, without storing pairs; joins broadcast by measured sizes."""

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from entlink import storage
from entlink.ann.exact import exact_knn, grouped_knn
from entlink.operators import candidates, loss
from entlink.registry import oracles, queries
from entlink.workloads import core

SF = "/root/testdata/sf0.001"


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.fixture(scope="module")
def halves(spark):
    rng = np.random.default_rng(3)
    rows = [(i, rng.normal(size=8).tolist(), None if i == 7 else i % 3) for i in range(300)]
    df = spark.createDataFrame(rows, "id long, vec array<double>, label int").cache()
    return df.where("id < 120"), df.where("id >= 120")


def all_pairs(halves):
    a, b = halves
    found = exact_knn(a, b, 1 << 30)
    left, right = a.select(F.col("id").alias("query_id"), F.col("label").alias("l")), b.select(F.col("id").alias("result_id"), F.col("label").alias("m"))
    rows = found.join(left, "query_id").join(right, "result_id")
    return rows.select(F.col("query_id").alias("r_id"), F.col("result_id").alias("t_id"), F.round("distance", 9).alias("dist"), (F.col("l") == F.col("m")).alias("is_match"))


def test_scan_does_not_copy_rows_for_blocks(spark, halves):
    """Neither side is repeated for the blocks of the other: before, every query went once to each block."""
    a, b = halves
    found = exact_knn(a, b, 4, block=16)
    assert "Generate explode" not in plan(found)
    x, y = (np.array([r.vec for r in df.orderBy("id").collect()]) for df in (a, b))
    d = 1 - (x @ y.T) / np.outer(np.linalg.norm(x, axis=1), np.linalg.norm(y, axis=1))
    want = {(i, 120 + int(j)) for i in range(len(x)) for j in np.argsort(d[i])[:4]}
    assert {(r.query_id, r.result_id) for r in found.collect()} == want


def test_scan_orders_ties_by_id_in_groups(spark):
    rows = [(g, str(i), [1.0, float(i % 2)]) for g in ("a|x", "b") for i in range(100)]
    df = spark.createDataFrame(rows, "grp string, id string, vec array<double>")
    got = grouped_knn(df.where("id = '4'"), df, 3, block=7).orderBy("grp", "rank").collect()
    assert [(r.grp, r.result_id, r["rank"]) for r in got] == [(g, i, k + 1) for g in ("a|x", "b") for k, i in enumerate(("0", "10", "12"))]


@pytest.mark.parametrize("side", ["relation", "text"])
def test_summed_losses_equal_those_of_all_pairs(spark, halves, side):
    items, others = halves if side == "relation" else halves[::-1]
    s, key = all_pairs(halves), loss.SIDES[side]
    got = {r.id: r for r in loss.scanned_loss(items, others, 0.1).collect()}
    means = {r[key]: (r.n, r.mean_positive) for r in loss.mean_positive(s, side).collect()}
    assert {k: r.n for k, r in got.items() if r.n} == {k: n for k, (n, _) in means.items()}
    assert all(got[k].mean_positive == pytest.approx(m) for k, (_, m) in means.items())
    want = {r[key]: r.loss for r in loss.partial_loss(s, side, 0.1).collect()}
    assert want and {k: r.loss for k, r in got.items() if r.n and r.negatives} == pytest.approx(want)
    single = {r[key]: r.loss for r in loss.single_positive_loss(s, side, 0.1).collect()}
    assert {r.id: r.loss for r in loss.scanned_single_loss(items, others, 0.1).collect() if r.n and r.negatives} == pytest.approx(single)


@pytest.mark.parametrize("name", ["q22_mean_positive", "q23_loss_relation_side", "q24_loss_text_side", "q25_loss_total", "q26_loss_single_positive", "q31_mutual_best", "q32_instance_rollup"])
def test_no_pairs_are_shuffled(spark, name):
    """Distances to all others were rows before, and were joined with labels."""
    rows = plan(queries()[name](spark, SF))
    assert "FlatMapCoGroupsInPandas" not in rows and "MapInArrow" in rows


def test_links_of_tuples_alike_are_counted_once(spark, tmp_path):
    """With every part ten times, the query by channel joins links with a text's tuples summed up, and gives the rows of its SQL."""
    import duckdb

    name, sizes = "q15_hit_at_k_by_channel", []
    part = spark.read.parquet(f"{SF}/part.parquet").where("p_partkey < 20")
    for copies in (1, 10):
        folder, kept, write = f"{tmp_path}/{copies}", [], storage.materialize
        more = part.withColumn("c", F.explode(F.sequence(F.lit(0), F.lit(copies - 1)))).withColumn("p_partkey", F.col("p_partkey") + 1000 * F.col("c")).drop("c")
        more.write.parquet(f"{folder}/part.parquet")

        def watched(df, tag, write=write, kept=kept):
            out = write(df, tag)
            kept.extend([out] if tag == "raw-asked" else [])
            return out

        core.materialize = watched
        try:
            got = sorted(tuple(r) for r in queries()[name](spark, folder).select("split", "channel", "links", "correct", "rate").collect())
        finally:
            core.materialize = write
        duck = duckdb.connect()
        duck.execute(f"CREATE VIEW part AS SELECT * FROM '{folder}/part.parquet/*.parquet'")
        assert got == sorted(duck.execute(f"SELECT split, channel, links, correct, rate FROM ({oracles()[name]})").fetchall())
        rows = kept[0].collect()
        assert len(rows) == len({(r.split, r.text, r.asked) for r in rows}) < 60
        sizes.append(sum(r.n for r in rows if r.split == "unseen"))
    assert 0 < 10 * sizes[0] == sizes[1]


@pytest.mark.parametrize("name", ["q14_hit_at_k_raw", "q15_hit_at_k_by_channel", "q35_accuracy_vs_density", "q105_knn_report"])
def test_equal_texts_are_compared_once(spark, name, tmp_path):
    """With every part ten times, the scan sees each text once: before, it compared all ten copies with all mentions."""
    seen, scan = [], storage.materialize

    def watched(df, tag):
        out = scan(df, tag)
        seen.extend([out] if tag == "scan-base" else [])
        return out

    from entlink.ann import exact

    part = spark.read.parquet(f"{SF}/part.parquet").where("p_partkey < 20")
    part.withColumn("c", F.explode(F.sequence(F.lit(0), F.lit(9)))).withColumn("p_partkey", F.col("p_partkey") + 1000 * F.col("c")).drop("c").write.parquet(f"{tmp_path}/part.parquet")
    exact.materialize = watched
    try:
        queries()[name](spark, str(tmp_path)).count()
    finally:
        exact.materialize = scan
    mentions = queries()["q03_verbalized_mentions"](spark, str(tmp_path))
    assert len(seen) == 1 and seen[0].count() < mentions.count() / 2


@pytest.fixture
def fresh(spark):
    """Spark's own threshold, as a new session has it."""
    spark.conf.unset("spark.sql.adaptive.autoBroadcastJoinThreshold")
    spark.conf.unset(storage.BROADCAST)
    return spark


@pytest.mark.parametrize("name", ["q18_link_shared_word", "q19_candidate_union", "q56_detect_mentions", "q117_rarest_token_blocks"])
def test_exploded_words_are_not_broadcast_by_guess(fresh, name):
    """Before a run sizes are guesses: exploded words of 60 times the mentions went to the driver by them."""
    assert "BroadcastExchange" not in plan(queries()[name](fresh, SF))


def test_measured_sizes_still_broadcast(fresh):
    names = fresh.createDataFrame([("red rod", "red rod")], "id string, text string").repartition(2)
    texts = fresh.createDataFrame([(i, "a red rod") for i in range(50)], "id long, text string").repartition(2)
    found = candidates.shared_word(names, texts)
    assert [r.shared for r in found.collect()] == [2] * 50
    assert "BroadcastHashJoin" in plan(found)
    assert fresh.conf.get("spark.sql.adaptive.autoBroadcastJoinThreshold").lower() in ("10mb", "10485760b", "10485760")


def test_vectors_are_not_broadcast_by_guess(fresh):
    """Relation vectors are far larger than the columns that they come from."""
    from entlink.plans.accuracy import entity_frames, links_of
    from entlink.workloads.experiments import QUICK

    tuples, mentions = entity_frames(fresh, SF, ("supplier",), QUICK)
    assert fresh.conf.get(storage.BROADCAST) == "-1"
    assert "BroadcastExchange" not in plan(links_of(tuples, mentions, None, QUICK)).split("MapInArrow")[0]


def test_schedule_reads_the_orders(fresh):
    """Its steps were made up on the driver before."""
    found = queries()["q28_lr_schedule"](fresh, SF)
    assert "orders.parquet" in plan(found)
    rates = dict(found.collect())
    assert len(rates) == fresh.read.parquet(f"{SF}/orders.parquet").count()
    assert all(r == pytest.approx(1e-5 * 0.9 ** (s // 1000), abs=1e-15) for s, r in rates.items())


def test_rows_of_a_small_file_reach_all_cores(spark):
    from entlink.sources.mentions import entity_type, relations

    cores = spark.sparkContext.defaultParallelism
    tuples, mentions = entity_type(spark, "/root/testdata/sf0.001", "product-name")
    for found in (relations(spark, "/root/testdata/sf0.001")["part"], tuples, mentions):
        assert found.rdd.getNumPartitions() >= cores


def test_training_rows_are_picked_without_vectors(spark, monkeypatch):
    """The rows that a type is trained on are those of the plain windows over all columns; ids and instances may be null."""
    from pyspark.sql import Window

    from entlink.joint import train as tr

    rows = [("k", str(i % 41) if i % 41 else None, str(i % 7) if i % 7 else None, [float(i), 1.0]) for i in range(60)]
    left = spark.createDataFrame(rows, "entity_type string, tuple_id string, instance_id string, vec array<float>")
    right = left.withColumnRenamed("tuple_id", "mention_id")
    taken = {}
    monkeypatch.setattr(type(left), "groupBy", lambda self, *by: taken.update(rows=self) or type("G", (), {"applyInPandas": lambda *_: None})())
    tr.train(left, right, tr.Config(), max_rows=20)
    monkeypatch.undo()
    both = left.selectExpr("entity_type", "tuple_id id", "instance_id", "vec", "'tuple' side").union(right.selectExpr("entity_type", "mention_id id", "instance_id", "vec", "'mention' side"))
    own = Window.partitionBy("side", "instance_id").orderBy(F.xxhash64("id"), "id")
    some = Window.partitionBy("side").orderBy("turn", F.xxhash64("instance_id"), "instance_id")
    plain = both.withColumn("turn", F.row_number().over(own)).withColumn("n", F.row_number().over(some)).where("n <= 20")
    name = lambda df: sorted(str((r.side, r.id, r.instance_id)) for r in df.collect())
    assert name(taken["rows"]) == name(plain)
    plan = taken["rows"]._jdf.queryExecution().optimizedPlan().toString()
    assert "LeftSemi" in plan and plan.count("Window") > 2


def test_bags_equal_plain_sums():
    from entlink.functions.text import hashed_bag
    from entlink.joint.train import bags

    texts = ["", None, "a a b", "Blue ring", "a a b", "été ÉTÉ x1"]
    plain = np.stack([hashed_bag(t, 64) + 0.5 * hashed_bag(t, 64, (3, 3)) for t in texts])
    assert (bags(texts, 64) == plain / np.maximum(1e-9, np.linalg.norm(plain, axis=1, keepdims=True))).all()


def test_nearest_rows_are_found_by_estimates(monkeypatch):
    """Only few pairs are compared truly, with the same rows and ties by id; before, every pair was."""
    import pandas as pd

    from entlink.ann import exact

    rng = np.random.default_rng(5)
    q, b, ids = rng.integers(-1, 2, (40, 16)).astype(float), rng.integers(-1, 2, (900, 16)).astype(float), rng.permutation(900)
    q[0] = b[3] = 0

    class Rows(list):
        block = 100

    want = np.round(exact.distances(q, b, "cosine"), 9)
    monkeypatch.setattr(exact, "distances", None)
    monkeypatch.setattr(exact, "PAIRS", 50)
    blocks = Rows((pd.DataFrame({"id": ids[i : i + 100]}), b[i : i + 100]) for i in range(0, 900, 100))
    got = pd.concat(exact.nearest_of(6, "cosine", 9)(pd.DataFrame({"id": np.arange(40)}), q, blocks))
    plain = [(i, int(ids[j])) for i in range(40) for j in np.lexsort((ids, want[i]))[:6]]
    assert list(zip(got.query_id, got.result_id)) == plain


def test_extreme_vectors_are_compared_truly():
    import pandas as pd

    from entlink.ann import exact

    class Rows(list):
        block = 9

    b = np.array([[1e80, 0.0], [0.0, 1e-80], [1.0, 1.0]])
    got = list(exact.nearest_of(1, "cosine")(pd.DataFrame({"id": [0]}), np.array([[1e75, 1e75]]), Rows([(pd.DataFrame({"id": [4, 5, 6]}), b)])))
    assert got[0].result_id.tolist() == [6]


def test_few_keys_go_to_the_texts(spark):
    """Before, the words of all texts and whole texts were shuffled for a few names."""
    rows = [(i, f"x{i} one big red rod here, o'k {'no' if i % 3 else 'snowy'} !") for i in range(60)] + [(60, None), (61, "")]
    texts = spark.createDataFrame(rows, "id long, text string")
    names = spark.createDataFrame([("a", "big red rod"), ("b", "x7"), ("c", "o'k"), ("d", " !"), ("e", "now"), ("f", ""), ("g", "red rod hers")], "id string, text string")
    pairs = lambda df: sorted(map(tuple, df.collect()))
    for some in (names, names.where("id in ('a', 'g')"), names.where("id = 'f'")):
        assert pairs(candidates.contained(some, texts, hold=True)) == pairs(candidates.contained(some, texts))
    found = candidates.contained(names.where("id = 'a'"), texts, hold=True)
    assert "hit-texts" in plan(found) and "LeftSemi" in plan(found)


def test_only_copied_documents_are_encoded(spark):
    """Their relation is that of all documents, of which every text was encoded before."""
    from entlink.joint.train import Config
    from entlink.plans.accuracy import relation_vectors
    from entlink.sources.mentions import entity_type

    c = Config(text_dim=16)
    tuples, _ = entity_type(spark, "/root/testdata/sf0.01", "copied-document")
    keys = tuples.selectExpr("cast(tuple_id as bigint) doc_id")
    some = {r.tuple_id: r.vec for r in relation_vectors(spark, "/root/testdata/sf0.01", "copied-document", c, keys=keys).collect()}
    every = {r.tuple_id: r.vec for r in relation_vectors(spark, "/root/testdata/sf0.01", "copied-document", c).collect()}
    assert 0 < len(some) < len(every) and all(every[k] == v for k, v in some.items())


def test_long_texts_are_encoded_in_bounded_runs():
    from entlink.joint.train import _runs_of_tokens

    runs = list(_runs_of_tokens(["a b a", "", " ".join(f"w{i}" for i in range(25)), "a"], most=10))
    assert [len(row) for row, *_ in runs] == [10, 10, 8]
    assert sum(sum(n) for _, _, n, _ in runs) == 29


@pytest.mark.parametrize("spread", [0.05, 1.0])
def test_cells_give_what_the_scan_gives(spark, monkeypatch, spread):
    """Ties, zero vectors, extreme lengths, small and foreign groups: the same rows with and without cells, and fewer pieces read."""
    from entlink.ann import exact

    rng = np.random.default_rng(3)
    centres = rng.normal(size=(12, 8))
    v = centres[rng.integers(0, 12, 4000)] + spread * rng.normal(size=(4000, 8))
    v[5] = 0
    v[6] *= 1e-60
    v[7:30] = v[7]
    rows = [("a" if i % 9 else "b", f"r{i}", x.tolist()) for i, x in enumerate(v)]
    base = spark.createDataFrame(rows, "grp string, id string, vec array<double>")
    asked = [("a", f"q{i}", x.tolist()) for i, x in enumerate(np.concatenate([v[:300], np.zeros((1, 8)), centres]))] + [("b", "q-b", v[0].tolist()), ("none", "q-none", v[0].tolist())]
    queries = spark.createDataFrame(asked, "grp string, id string, vec array<double>")
    for n, digits in ((1, None), (10, 3)):
        want = sorted(map(tuple, exact.grouped_knn(queries, base, n, digits=digits).collect()))
        with monkeypatch.context() as m:
            m.setattr(exact, "LEAST", 100)
            m.setattr(exact, "CELL", 32)
            m.setattr(exact, "_apart", lambda centres, radii: True)
            got = sorted(map(tuple, exact.grouped_knn(queries, base, n, digits=digits, cells=True).collect()))
            assert [x[:3] + x[4:] for x in got] == [x[:3] + x[4:] for x in want] and np.allclose([x[3] for x in got], [x[3] for x in want], atol=1e-12)


def test_far_pieces_are_not_read():
    """Groups far from a query are ruled out by their radius."""
    from entlink.ann import exact

    rng = np.random.default_rng(4)
    centres = np.eye(8)
    base = np.concatenate([c + 0.01 * rng.normal(size=(50, 8)) for c in centres])
    cells = exact.Cells(centres)
    cell, angle = cells.of(base)
    radius = np.array([angle[cell == i].max() for i in range(8)]) + 1e-7
    read = []

    class Few:
        found = [(None, i, i) for i in range(8)]

        def read(self, i):
            read.append(int(i))
            return pd.Series(np.flatnonzero(cell == i)), base[cell == i]

    r, i, d = exact._nearest_in_pieces(centres[3:4] + 0.01, Few(), exact.Cells(centres, np.cos(radius), np.sin(radius)), 5, 0.0, None)
    _, c, want = exact.nearest_positions(centres[3:4] + 0.01, base, 5, "cosine")
    assert read == [3] and i.tolist() == c.tolist() and np.allclose(d, want)
