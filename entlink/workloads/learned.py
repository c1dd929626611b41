"""Queries that train, index, stream or time; SQL cannot express them, tests hold them (``tests/test_learned.py``)."""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.ml.feature import PCA
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from entlink.ann.exact import exact_knn
from entlink.ann.forest import Forest
from entlink.joint.registry import ModelRegistry
from entlink.joint.train import PUBLISHED, Config, load_tower
from entlink.operators.evaluate import ann_recall, hit_at_k, separation
from entlink.operators.vectorize import vector_sum
from entlink.plans.accuracy import accuracy_table, embedded, entity_frames, links_of, trained
from entlink.plans.relink import bootstrap, relink_cycle, stage_seconds
from entlink.registry import query
from entlink.sources.triples import read_entries, write_entries
from entlink.storage import materialize, scratch_path, table
from entlink.streaming import alerts
from entlink.workloads.core import vectors

ONE = ("product-name",)
QUICK = Config(steps=150)


@query("q43_train_joint")
def train_joint(spark, d):
    """Loss and shape of every trained layer of the ten types."""
    tuples, mentions = entity_frames(spark, d, config=QUICK)
    return trained(tuples, mentions, QUICK).select("entity_type", "step", "side", "layer", "kind", "rows", "cols", F.round("loss", 4).alias("loss"))


def _embedded(spark, d, side):
    tuples, mentions = entity_frames(spark, d, ONE, QUICK)
    weights = trained(tuples, mentions, QUICK)
    rows, key = (tuples, "tuple_id") if side == "relation" else (mentions, "mention_id")
    out = embedded(rows, {ONE[0]: load_tower(weights, ONE[0], side, QUICK.steps)})
    return out.select(F.col(key).alias("id"), F.lit(side).alias("side"), "vec")


@query("q44_embed_tuples")
def embed_tuples(spark, d):
    return _embedded(spark, d, "relation")


@query("q45_embed_mentions")
def embed_mentions(spark, d):
    return _embedded(spark, d, "text")


@query("q46_forest_knn")
def forest_knn(spark, d):
    base = vectors(spark, d)
    return Forest.fit(base, trees=16, leaf_size=32).query(base, 10, budget=120)


@query("q47_forest_recall")
def forest_recall(spark, d):
    """Recall against the exact scan as trees and budget grow."""
    base, out = materialize(vectors(spark, d), "base"), []
    exact = materialize(exact_knn(base, base, 10), "exact")
    for trees in (2, 8, 16):
        forest = Forest.fit(base, trees=trees, leaf_size=32)
        for budget in (30, 120):
            row = ann_recall(forest.query(base, 10, budget), exact)
            out.append(row.select(F.lit(trees).alias("trees"), F.lit(budget).alias("budget"), "recall", "queries"))
    return reduce(DataFrame.unionByName, out)


STEPS = replace(QUICK, steps=2400, checkpoints=PUBLISHED.checkpoints)


def _both_sides(tuples, mentions, weights, step):
    """Embeddings of both sides at a checkpoint: id, instance_id, side, vec."""
    sides = [
        embedded(df, {ONE[0]: load_tower(weights, ONE[0], s, step)}).select(F.col(k).alias("id"), "instance_id", F.lit(s).alias("side"), "vec")
        for s, df, k in (("relation", tuples, "tuple_id"), ("text", mentions, "mention_id"))
    ]
    return materialize(sides[0].unionByName(sides[1]), "snapshot")


@query("q48_snapshot_2d")
def snapshots(spark, d):
    """Two principal components of both sides at the published checkpoints of training."""
    tuples, mentions = entity_frames(spark, d, ONE, STEPS)
    weights, out = trained(tuples, mentions, STEPS), []
    for step in STEPS.checkpoints:
        both = _both_sides(tuples, mentions, weights, step).withColumn("v", array_to_vector("vec"))
        xy = vector_to_array("xy")
        flat = PCA(k=2, inputCol="v", outputCol="xy").fit(both).transform(both)
        out.append(flat.select("id", "instance_id", "side", xy[0].alias("x"), xy[1].alias("y"), F.lit(step).alias("step")))
    return reduce(DataFrame.unionByName, out)


@query("q111_separation_by_step")
def separation_by_step(spark, d):
    """Mean distance of matches and of non-matches, and the share of non-matches beyond the margin, at every checkpoint.

    Every tuple meets the mean of each instance's mentions, so pairs are tuples times instances.
    """
    tuples, mentions = entity_frames(spark, d, ONE, STEPS)
    weights, out = trained(tuples, mentions, STEPS), []
    for step in STEPS.checkpoints:
        both = _both_sides(tuples, mentions, weights, step)
        width = both.select(F.size("vec").alias("n")).first().n
        means = vector_sum(both.where("side = 'text'").select("instance_id", F.transform("vec", lambda x: x.cast("double")).alias("vec")), "instance_id", "vec", width)
        left = both.where("side = 'relation'").select("id", "vec")
        n = means.count()  # one for each instance
        pairs = exact_knn(left, means.select(F.col("instance_id").alias("id"), "vec"), n)
        own = both.where("side = 'relation'").select(F.col("id").alias("query_id"), "instance_id")
        scores = pairs.join(own, "query_id").select(F.col("query_id").alias("r_id"), F.col("result_id").alias("t_id"), F.col("distance").alias("dist"), (F.col("result_id") == F.col("instance_id")).alias("is_match"))
        out.append(separation(scores, STEPS.margin).select(F.lit(step).alias("step"), "*"))
    return reduce(DataFrame.unionByName, out)


@query("q112_published_configuration")
def published_configuration(spark, d):
    """Hit rates of two types with the printed widths, rate, decay, margin and dropout, beside the small configuration."""
    rows = [accuracy_table(spark, d, ("supplier", "nation"), c).withColumn("configuration", F.lit(n)) for n, c in (("published", PUBLISHED), ("small", QUICK))]
    return rows[0].unionByName(rows[1])


@query("q114_configuration_grid")
def configuration_grid(spark, d):
    """Unseen and test hit rates at 1 over a grid of layers and widths."""
    tuples, mentions = entity_frames(spark, d, ("supplier",), QUICK)
    rows = []
    for relation, text in (((64,), (64,)), ((128, 64), (64,)), ((256, 128), (128,)), ((128, 128, 64), (128, 64))):
        c = replace(QUICK, relation=relation, text=text)
        got = hit_at_k(links_of(tuples, mentions, trained(tuples, mentions, c), c), ["split"]).where("k = 1")
        rows.append(got.select(F.lit("-".join(map(str, relation))).alias("relation"), F.lit("-".join(map(str, text))).alias("text"), "split", "hits", "queries", "rate"))
    return reduce(DataFrame.unionByName, rows)


@query("q115_cold_start")
def cold_start(spark, d):
    """Unseen entities against their own mentions and against all mentions of the type, without training again."""
    return accuracy_table(spark, d, ("product-name", "customer", "supplier", "order"), QUICK, pools=("split", "all"), split="unseen").drop("split")


@query("q49_bootstrap_rounds")
def bootstrap_rounds(spark, d):
    return bootstrap(spark, d)


@query("q50_retrain_cycle")
def retrain(spark, d):
    return relink_cycle(spark, d)


@query("q51_stage_timing")
def timing(spark, d):
    """Three types and their mean; each index beside the scan, with its recall."""
    return stage_seconds(spark, d, ("product-name", "customer", "supplier"))


@query("q52_xml_roundtrip", "SELECT p_partkey::VARCHAR AS eid, p_name AS subject, unnest(['brand', 'maker', 'size']) AS predicate, unnest([p_brand, replace(p_type, '_', ' '), p_size::VARCHAR]) AS object FROM part")
def xml(spark, d):
    name = F.translate("p_name", " ", "_")
    triple = lambda p, o: F.concat(name, F.lit(f" | {p} | "), o)
    part = table(spark, d, "part")
    rows = part.select(
        F.col("p_partkey").cast("string").alias("eid"), F.lit("part").alias("category"),
        F.array(triple("brand", F.concat(F.lit('"'), F.col("p_brand"), F.lit('"'))), triple("maker", F.col("p_type")), triple("size", F.col("p_size").cast("string"))).alias("triples"),
        F.array(F.concat(F.lit("A "), F.col("p_name"), F.lit("."))).alias("lex"),
    )
    path = scratch_path(spark, "entries")
    write_entries(rows, path)
    return read_entries(spark, path)[0]


@query("q53_accuracy_table")
def accuracy(spark, d):
    return accuracy_table(spark, d, config=QUICK, pools=("split", "all"))


@query("q54_ablations")
def ablations(spark, d):
    """Hit rates of two types with each part left out or exchanged: inputs of the towers, loss, sampler, distance, direction."""
    types, rows = ("product-name", "customer"), []
    by_inputs = {i: entity_frames(spark, d, types, QUICK, i) for i in ("signature", "attributes", "string")}
    tuples, mentions = by_inputs["signature"]
    base = trained(tuples, mentions, QUICK)
    runs = {
        "signature": (tuples, mentions, base, {}),
        "without foreign keys": (*by_inputs["attributes"], trained(*by_inputs["attributes"], QUICK), {}),
        "bags of strings": (*by_inputs["string"], trained(*by_inputs["string"], QUICK), {}),
        "bags of strings, untrained": (*by_inputs["string"], None, {}),
        "single positive": (tuples, mentions, trained(tuples, mentions, replace(QUICK, positive="each")), {}),
        "uniform sampler": (tuples, mentions, trained(tuples, mentions, replace(QUICK, sampler="uniform")), {}),
        "euclidean": (tuples, mentions, base, {"metric": "euclidean"}),
        "mention as query": (tuples, mentions, base, {"by": "mention"}),
    }
    for name, (t, m, w, how) in runs.items():
        rows.append(hit_at_k(links_of(t, m, w, QUICK, **how), ["entity_type", "split"]).withColumn("variant", F.lit(name)))
    return reduce(DataFrame.unionByName, rows)


@query("q55_hits_by_channel")
def channels(spark, d):
    """Share of right first links of each error channel, with the mention as the query."""
    tuples, mentions = entity_frames(spark, d, ONE, QUICK)
    links = links_of(tuples, mentions, trained(tuples, mentions, QUICK), QUICK, n=1, by="mention")
    said = mentions.select(F.col("mention_id").alias("query_id"), F.col("channel").alias("said"))
    return links.join(said, "query_id").groupBy("split", "said").agg(F.count("*").alias("n"), F.round(F.avg(F.col("correct").cast("int")), 6).alias("rate"))


@query("q96_stream_alerts")
def stream_alerts(spark, d):
    """Alerts by the hour from learned links: arriving mentions are embedded by the published model and meet stored tuples.

    Returns hour, instance and number of links, and the seconds from a batch's start to its alerts.
    """
    tuples, mentions = entity_frames(spark, d, ONE, QUICK)
    models = ModelRegistry(spark, scratch_path(spark, "models"))
    models.publish(ONE[0], trained(tuples, mentions, QUICK))
    n = mentions.count()
    numbered = materialize(mentions.select(F.pmod(F.xxhash64("mention_id"), F.lit(n)).alias("mention_no"), "entity_type", "vec").dropDuplicates(["mention_no"]), "stream-mentions")
    events = table(spark, d, "events")
    stream = alerts.event_stream(spark, alerts.event_files(events)).withColumn("mention_no", F.pmod(F.xxhash64("event_id"), F.lit(n)))
    return alerts.learned_alerts(stream, numbered, tuples, models, ONE[0])


@query("q97_stream_dedup_join", "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")
def stream_dedup(spark, d):
    events = table(spark, d, "events")
    path = alerts.event_files(events.unionByName(events.where("event_id % 10 = 0")))
    once = alerts.once_per_event(alerts.event_stream(spark, path))
    customers = table(spark, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return alerts.drain(once.join(customers, "user_id").select("event_id", "c_mktsegment"), "dedup")


@query("q98_stream_state", "SELECT user_id, count(*) AS seen FROM events GROUP BY 1")
def stream_state(spark, d):
    stream = alerts.event_stream(spark, alerts.event_files(table(spark, d, "events")))
    return alerts.drain(alerts.seen_counts(stream), "state").groupBy("user_id").agg(F.max("seen").alias("seen"))
