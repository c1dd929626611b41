"""Invariants of the queries that train, index, stream and time, on the smallest tables."""

import duckdb
import numpy as np
import pandas as pd
import pytest

from entlink import registry
from entlink.joint.network import Tower
from entlink.joint.train import Config
from entlink.operators.evaluate import should_retrain
from entlink.operators.vectorize import signature
from entlink.plans import accuracy, relink
from entlink.sources.mentions import TYPE_NAMES, relations
from entlink.spec import BY_NAME

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def run(spark):
    found, done = registry.queries(), {}

    def rows(name):
        if name not in done:
            done[name] = found[name](spark, SF).collect()
        return done[name]

    return rows


def rates(rows, *keys):
    """Rate by key and k; hits never fall as k grows, and rates are hits over queries."""
    out = {}
    for r in rows:
        assert 0 <= r.hits <= r.queries and r.rate == pytest.approx(r.hits / r.queries, abs=1e-6)
        out.setdefault(tuple(r[k] for k in keys), {})[r.k] = r.rate
    for by_k in out.values():
        assert by_k[1] <= by_k[5] <= by_k[10]
    return out


@pytest.fixture(scope="module")
def supplier(spark):
    c = Config(steps=120)
    tuples, mentions = accuracy.entity_frames(spark, SF, ("supplier",), c)
    return c, tuples, mentions, accuracy.trained(tuples, mentions, c)


def test_towers_read_the_relation(spark, supplier):
    """The relation tower is as wide as the signature with its foreign keys, and its input is the signature itself."""
    c, tuples, mentions, weights = supplier
    sig, layout = signature(relations(spark, SF), BY_NAME["supplier"], c.text_dim)
    width = layout[-1][2] + layout[-1][3]
    assert [k for _, k, *_ in layout] == ["text", "number", "foreign_key"]
    assert {(r.side, r.rows) for r in weights.where("layer = 0 and kind = 'w'").collect()} == {("relation", width), ("text", c.dim)}
    numbers = {str(r.key): r.v_r[c.text_dim] for r in sig.collect()}
    for r in tuples.collect():
        assert len(r.vec) == width and r.vec[c.text_dim] == pytest.approx(numbers[r.tuple_id], abs=1e-6)
        assert any(r.vec[c.text_dim + 1 :])  # what the nation and its region give
    plain = accuracy.relation_vectors(spark, SF, "supplier", c, 0).first()
    assert len(plain.vec) == c.text_dim + 1


def test_forward_pass_equals_sql(spark, supplier):
    """Embeddings of tuples against the layers written out as joins and sums in DuckDB."""
    c, tuples, _, weights = supplier
    con = duckdb.connect()
    layers = [r for r in weights.where(f"side = 'relation' and step = {c.steps}").collect()]
    x = tuples.toPandas()

    cells = pd.DataFrame([(r.tuple_id, i, float(v)) for r in x.itertuples() for i, v in enumerate(r.vec)], columns=["id", "i", "x"])  # noqa: F841
    w = pd.DataFrame([(r.layer, i // r.cols, i % r.cols, v) for r in layers if r.kind == "w" for i, v in enumerate(r["values"])], columns=["l", "i", "o", "w"])  # noqa: F841
    b = pd.DataFrame([(r.layer, i, v) for r in layers if r.kind == "b" for i, v in enumerate(r["values"])], columns=["l", "o", "b"])  # noqa: F841
    con.execute("CREATE TABLE h AS SELECT id, i, x FROM cells")
    for layer in sorted({r.layer for r in layers}):
        con.execute(f"""CREATE OR REPLACE TABLE h AS SELECT id, o AS i, CASE WHEN z > 0 THEN z ELSE exp(z) - 1 END AS x FROM
            (SELECT id, w.o, sum(x * w) + any_value(b) AS z FROM h JOIN w ON h.i = w.i AND w.l = {layer} JOIN b ON b.o = w.o AND b.l = {layer} GROUP BY id, w.o)""")
    want = {}
    for i, at, v in con.execute("SELECT id, i, x FROM h ORDER BY id, i").fetchall():
        want.setdefault(i, []).append(v)
    got = {r.tuple_id: r.vec for r in accuracy.embedded(tuples, {"supplier": accuracy.load_tower(weights, "supplier", "relation", c.steps)}).collect()}
    assert got.keys() == want.keys() and all(np.allclose(got[k], want[k], atol=1e-4) for k in want)


def test_training_samples_matching_rows(spark, supplier):
    """However few rows are kept, both sides keep the same instances, so training pairs remain."""
    from entlink.joint.train import train

    c, tuples, mentions, _ = supplier
    few = train(tuples, mentions.where("split = 'train'"), Config(steps=30), max_rows=4)
    losses = {r.loss for r in few.where("step = 30").collect()}
    assert len(losses) == 1 and not any(np.isnan(x) for x in losses)


def test_retraining_goes_on_from_weights(spark, supplier):
    c, tuples, mentions, weights = supplier
    short = Config(steps=1)
    warm, cold = accuracy.trained(tuples, mentions, short, weights), accuracy.trained(tuples, mentions, short)
    value = lambda w, step: np.array(w.where(f"side = 'text' and layer = 0 and kind = 'w' and step = {step}").first()["values"])
    assert np.abs(value(warm, 1) - value(weights, c.steps)).max() < 0.02 < np.abs(value(cold, 1) - value(weights, c.steps)).max()


def test_every_type_trains(run):
    rows = run("q43_train_joint")
    assert {r.entity_type for r in rows} == set(TYPE_NAMES)
    assert {(r.side, r.layer, r.kind) for r in rows} == {("relation", 0, "w"), ("relation", 0, "b"), ("relation", 1, "w"), ("relation", 1, "b"), ("text", 0, "w"), ("text", 0, "b")}
    assert all(r.loss is not None and r.loss >= 0 for r in rows)


def test_embeddings_cover_both_sides(spark, run):
    parts = spark.read.parquet(f"{SF}/part.parquet").count()
    assert len(run("q44_embed_tuples")) == parts and len(run("q45_embed_mentions")) == 3 * parts
    assert {len(r.vec) for r in run("q44_embed_tuples") + run("q45_embed_mentions")} == {64}


def test_index_finds_what_the_scan_finds(spark, run):
    exact = {(r.query_id, r.result_id) for r in registry.queries()["q12_exact_knn_cosine"](spark, SF).collect()}
    assert len(exact & {(r.query_id, r.result_id) for r in run("q46_forest_knn")}) / len(exact) >= 0.9
    recall = {(r.trees, r.budget): r.recall for r in run("q47_forest_recall")}
    assert recall[2, 30] < recall[8, 30] < recall[16, 30] and all(recall[t, 30] < recall[t, 120] for t in (2, 8, 16)) and recall[16, 120] >= 0.9


def test_snapshots_and_separation(run):
    steps = {0, 100, 200, 600, 1200, 2400}
    assert {r.step for r in run("q48_snapshot_2d")} == steps
    by = {r.step: r for r in run("q111_separation_by_step")}
    gap = {s: r.mean_negative - r.mean_positive for s, r in by.items()}
    assert by.keys() == steps and gap[0] < gap[100] < gap[600] and gap[2400] > gap[0] + 0.3
    assert by[0].outside < by[2400].outside


def test_bootstrap_rounds_do_not_get_worse(run):
    rows = sorted(run("q49_bootstrap_rounds"), key=lambda r: r.round)
    assert [r.round for r in rows] == [0, 1, 2] and rows[0].pairs < rows[1].pairs <= rows[2].pairs
    assert rows[-1].right >= rows[0].right - 0.05


def test_retraining_only_where_data_moved(run):
    rows = run("q50_retrain_cycle")
    assert {r.change for r in rows} == set(relink.CHANGES)
    drift = {r.change: r.drift for r in rows}
    assert drift["none"] == 0 and not any(r.retrained for r in rows if r.change == "none")
    by = rates(rows, "change", "phase", "split")
    for change in relink.CHANGES:
        if not any(r.retrained for r in rows if r.change == change):
            assert by[change, "before", "train"] == by[change, "after", "train"]
        assert by[change, "after", "train"][1] >= by[change, "before", "train"][1] - 0.1


def test_should_retrain_by_threshold(spark):
    a = spark.createDataFrame([("x",)] * 9 + [("y",)], "g string")
    b = spark.createDataFrame([("x",)] * 5 + [("y",)] * 5, "g string")
    assert not should_retrain(a, a, ["g"]) and should_retrain(a, b, ["g"], 0.3) and not should_retrain(a, b, ["g"], 0.5)


def test_stage_times(run):
    rows = run("q51_stage_timing")
    assert {r.entity_type for r in rows} == {"product-name", "customer", "supplier", "mean"}
    assert len(rows) == 4 * 10 and all(r.seconds >= 0 for r in rows)
    assert all(r.recall is None or r.recall >= 0.9 for r in rows) and sum(r.recall is not None for r in rows) == 4
    one = {r.step: r.seconds for r in rows if r.entity_type == "supplier"}
    assert one["total"] == pytest.approx(one["embed tuples"] + one["embed mentions"] + one["index tuples"] + one["index mentions"], abs=0.01)


def test_accuracy_tables(run):
    got = rates(run("q53_accuracy_table"), "entity_type", "pool", "split")
    assert {k[0] for k in got} == set(TYPE_NAMES)
    for (kind, pool, split), by_k in got.items():  # more mentions to choose from never help
        if pool == "all" and split == "unseen":  # other pools add mentions of the same instances
            assert by_k[1] <= got[kind, "split", split][1] + 0.05
    for kind in ("product-name", "customer", "supplier", "nation"):
        assert got[kind, "split", "train"][10] >= 0.9
    cold = rates(run("q115_cold_start"), "entity_type", "pool")
    assert all(cold[k, "all"][1] <= cold[k, "split"][1] + 0.05 for k in ("product-name", "customer", "supplier", "order"))


def test_ablations(run):
    got = rates(run("q54_ablations"), "variant", "entity_type", "split")
    assert len({k[0] for k in got}) == 8
    assert got["signature", "product-name", "train"][1] > got["bags of strings, untrained", "product-name", "train"][1] - 0.05
    assert got["signature", "customer", "train"][10] >= 0.9


def test_rates_by_channel_and_configuration(run):
    rows = run("q55_hits_by_channel")
    assert {r.said for r in rows} >= {"clean", "homonym"} and all(0 <= r.rate <= 1 for r in rows)
    assert len(rates(run("q112_published_configuration"), "configuration", "entity_type", "split")) == 12
    grid = run("q114_configuration_grid")
    assert len({(r.relation, r.text) for r in grid}) == 4 and all(r.rate == pytest.approx(r.hits / r.queries, abs=1e-6) for r in grid)


def test_alerts_follow_the_published_model(spark, run):
    rows = run("q96_stream_alerts")
    names = {r.p_name for r in spark.read.parquet(f"{SF}/part.parquet").select("p_name").collect()}
    assert {r.instance_id for r in rows} <= names and {r.version for r in rows} == {1} and all(0 < r.seconds < 600 for r in rows)
    assert len({(r.hour, r.instance_id) for r in rows}) == len(rows)
    mentions = spark.read.parquet(f"{SF}/part.parquet").count() * 3
    assert 0.3 * spark.read.parquet(f"{SF}/events.parquet").count() < sum(r.n for r in rows) <= spark.read.parquet(f"{SF}/events.parquet").count() and mentions


def test_profiles(spark, run):
    got = {r.entity_type: r for r in run("q102_profile_ten_types")}
    plain = {r.entity_type: r for r in run("q119_profile_columns")}
    assert got.keys() == set(TYPE_NAMES)
    for name in ("product", "customer", "order"):
        assert (got[name].columns, got[name].density, got[name].tuples) == (plain[name].columns, plain[name].density, plain[name].tuples)
        assert got[name].columns == len(BY_NAME[name].attributes) + len(BY_NAME[name].foreign_keys)
        assert got[name].sentences == 3 * got[name].tuples


def test_sweeps(run):
    by = rates(run("q103_density_accuracy"), "density", "split")
    assert by[100, "train"][1] > by[1, "train"][1]
    correlation = {r.split: r.correlation for r in run("q116_density_correlation")}
    assert correlation["train"] > 0
    fan = rates(run("q104_fanout_accuracy"), "fanout", "split")
    assert fan[6, "unseen"][1] >= fan[1, "unseen"][1] - 0.1
    skewed = rates(run("q107_skewed_training"), "sampler", "third", "split")
    assert {k[0] for k in skewed} == {"skew", "uniform"} and {k[1] for k in skewed} == {1, 2, 3}
    rates(run("q108_many_to_many"), "entity_type", "split")
    row = run("q109_accuracy_against_profile")[0]
    assert 8 <= row.types <= 10 and -1 <= row.correlation <= 1


def test_shuffled_gold_is_chance(spark):
    by = rates(registry.queries()["q110_shuffled_gold_control"](spark, "/root/testdata/sf0.01").collect(), "gold", "split")
    assert by["shuffled", "unseen"][1] <= 0.2 and by["shuffled", "unseen"][1] < by["true", "unseen"][1]


def test_towers_are_plugged_in(spark):
    from entlink.joint.registry import register_tower

    seen = []
    register_tower("noted", lambda widths, seed, keep: seen.append(widths) or Tower(widths, seed, keep))
    from entlink.joint.train import fit_towers

    r, t = np.eye(4), np.eye(4)[:, ::-1].copy()
    *_, last = fit_towers(r, t, np.array([(i, i) for i in range(4)]), np.arange(4), np.arange(4), Config(steps=3, batch=4, relation=(3,), text=(3,), tower="noted"))
    assert seen == [(4, 3), (4, 3)] and last[0] == 3


def test_every_row_trains(spark):
    """Of 20,200 instances only the last 200 by hash have inputs other than zero, so weights move only if those are trained on."""
    from pyspark.sql import Window
    from pyspark.sql import functions as F

    from entlink.joint.train import train

    ids = spark.range(20_200).select(F.col("id").cast("string").alias("instance_id"))
    no = F.row_number().over(Window.orderBy(F.xxhash64("instance_id"), "instance_id"))
    x = F.when(no > 20_000, F.xxhash64("instance_id") / 2.0**63).otherwise(0.0).cast("float")
    rows = ids.select(F.lit("k").alias("entity_type"), "instance_id", F.array(x, x * x).alias("vec")).cache()
    w = train(rows.withColumn("tuple_id", F.col("instance_id")), rows.withColumn("mention_id", F.col("instance_id")), Config(steps=40, batch=24, relation=(3,), text=(3,), checkpoints=(0,))).cache()
    for side in ("relation", "text"):
        first, last = (accuracy.load_tower(w, "k", side, step).w[0] for step in (0, 40))
        assert (first != last).all()


def test_snapshots_train_on_all_pairs(spark, monkeypatch):
    """The queries of the snapshots ask for no bound of training: all training mentions and their tuples are given to it."""
    from entlink.workloads import learned

    given = {}

    def noted(tuples, mentions, config, max_rows=None, start=None):
        given.update(bound=max_rows, mentions=mentions.count(), tuples=tuples.count())
        raise InterruptedError

    monkeypatch.setattr(accuracy, "train", noted)
    for q in (learned.snapshots, learned.separation_by_step):
        given.clear()
        with pytest.raises(InterruptedError):
            q(spark, SF)
        _, mentions = accuracy.entity_frames(spark, SF, learned.ONE, learned.STEPS)
        assert given["bound"] is None and given["mentions"] == mentions.where("split = 'train'").count() and given["tuples"] > 0


def test_a_pass_meets_every_pair_once(spark, monkeypatch):
    """Pairs beyond what the steps draw: each is trained on once, all rows of an instance take part, and every group has a non-match."""
    from pyarrow import dataset
    from entlink.joint import train as tr
    from entlink.storage import locate

    rows = [("k", side, str(i), f"{side}{i}-{j}", [float(i), float(j)]) for i, n in ((0, 300), (1, 1), (2, 40)) for side, m in (("tuple", min(n, 7)), ("mention", n)) for j in range(m)]
    rows += [("k", "tuple", "3", f"tuple3-{j}", [3.0, float(j)]) for j in range(9)] + [("k", "mention", "3", "mention3-0", [3.0, 0.0]), ("k", "tuple", "alone", "tuple-x", [9.0, 9.0]), ("k", "mention", None, "mention-x", [9.0, 9.0])]
    both = spark.createDataFrame(rows, "entity_type string, side string, instance_id string, id string, vec array<float>")
    monkeypatch.setattr(tr, "RUN", 50)
    path, kinds = tr._in_order(both, 1, 60)
    assert kinds == [("k", 350, 4, 7)]
    fs, own = locate(path)
    runs = [tr._pairs_of(dataset.dataset(f.path, filesystem=fs, format="parquet").to_table()) for f in sorted(fs.get_file_info(tr.pafs.FileSelector(f"{own}/slot=0")), key=lambda f: f.path) if f.base_name.startswith("file=")]
    made = sorted((a, b) for run in runs for a, b in zip(run.r_id, run.t_id))
    assert len(made) == len(set(made)) == 350 and {x for p in made for x in p} == {r[3] for r in rows if not r[3].endswith("x")}
    assert all(a[5:].split("-")[0] == b[7:].split("-")[0] for a, b in made)
    assert all((run.r[:, 0] == run.t[:, 0]).all() for run in runs)
    seen, groups = [], []
    monkeypatch.setattr(tr._Learner, "learn", lambda self, step, got: (seen.append(sum(g[3] for g in got)), groups.extend(got)))
    steps = [step for step, *_ in tr.fit_pass(iter(runs), 350, Config(steps=10, batch=6, checkpoints=(0, 5)))]
    assert steps == [0, 5, 10] and sum(seen) == 350 and all(g[3] <= 6 and not g[2].all() for g in groups)


def test_cold_start_asks_for_unseen_tuples_only(spark, monkeypatch):
    """The rows are the unseen ones of the whole table, no other tuples are compared, and both sides are embedded once."""
    asked, made, find, sides = [], [], accuracy.grouped_knn, accuracy.embedded_sides
    monkeypatch.setattr(accuracy, "grouped_knn", lambda q, b, *a, **k: asked.append({r.grp for r in q.select("grp").distinct().collect()}) or find(q, b, *a, **k))
    monkeypatch.setattr(accuracy, "embedded_sides", lambda *a, **k: made.append(1) or sides(*a, **k))
    key = ["entity_type", "pool", "k", "hits", "queries", "rate"]
    whole = accuracy.accuracy_table(spark, SF, ("supplier",), Config(steps=20), pools=("split", "all")).where("split = 'unseen'").select(*key).collect()
    assert len(made) == 1 and any(len(x) > 1 for x in asked)
    asked.clear()
    some = accuracy.accuracy_table(spark, SF, ("supplier",), Config(steps=20), pools=("split", "all"), split="unseen").select(*key).collect()
    assert sorted(some) == sorted(whole) and asked == [{"supplier|unseen"}] * 2
