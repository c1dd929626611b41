"""Bootstrapping, retraining on change, and wall-clock seconds of the stages."""

from __future__ import annotations

import time
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from entlink.ann.exact import exact_knn
from entlink.ann.forest import Forest
from entlink.functions.text import h, tokens
from entlink.joint.train import Config, load_tower, mention_vector
from entlink.operators.candidates import shared_word
from entlink.operators.evaluate import ann_recall, drift, hit_at_k
from entlink.plans.accuracy import embedded, entity_frames, links_of, trained
from entlink.sources.mentions import entity_type
from entlink.storage import materialize


def bootstrap(spark: SparkSession, sf_dir: str, rounds: int = 2, config: Config = Config(steps=80), type_name: str = "product-name", within: float = 0.3) -> DataFrame:  # noqa: B008
    """Pairs per round: seed by shared words, train on them, match again within a distance, and so on.

    Returns round, pairs and the share of pairs that are true.
    """
    tuples, mentions = entity_frames(spark, sf_dir, (type_name,), config)
    names = tuples.groupBy("instance_id").agg(F.min("tuple_id").alias("tuple_id")).select(F.col("instance_id").alias("id"), F.col("instance_id").alias("text"))
    texts = mentions.select(F.col("mention_id").alias("id"), "text")
    pairs = materialize(shared_word(names, texts, 2).select(F.col("name_id").alias("instance_id"), F.col("text_id").alias("mention_id")), "seed-pairs")
    truth = mentions.select("mention_id", F.col("instance_id").alias("true_instance"))
    out = []
    for r in range(rounds + 1):
        row = pairs.join(truth, "mention_id").agg(F.count("*").alias("pairs"), F.round(F.avg((F.col("instance_id") == F.col("true_instance")).cast("int")), 6).alias("right")).first()
        out.append((r, row.pairs, row.right))
        if r == rounds:
            break
        guessed = pairs.join(mentions.drop("instance_id"), "mention_id").withColumn("split", F.lit("train"))
        weights = trained(tuples, guessed, config)
        links = links_of(tuples, mentions.withColumn("split", F.lit("all")), weights, config, n=1, by="mention")
        near = links.where(F.col("distance") < within).select(F.col("query_id").alias("mention_id"), F.col("result_id").alias("tuple_id"))
        found = near.join(tuples.select("tuple_id", "instance_id"), "tuple_id").select("instance_id", "mention_id")
        pairs = materialize(pairs.unionByName(found).distinct(), "pairs")
    return spark.createDataFrame(out, "round int, pairs long, right double")


def should_relink(old: DataFrame, new: DataFrame, threshold: float = 0.05) -> dict[str, float]:
    """Total variation between two versions of a type's rows (entity_type, text): of their words, and of their numbers of words.

    Both are distributions over a vocabulary, so new rows like the old ones move neither, and rows unlike them move them.
    """
    words = lambda df: df.select(F.explode(tokens(F.col("text"))).alias("v"))
    sizes = lambda df: df.select(F.size(tokens(F.col("text"))).alias("v"))
    return {k: drift(f(old), f(new), "v").first()["total_variation"] or 0.0 for k, f in (("words", words), ("sizes", sizes))}


CHANGES = ("none", "insert", "update", "delete")


def relink_cycle(spark: SparkSession, sf_dir: str, config: Config = Config(steps=120), type_name: str = "product-name", threshold: float = 0.015,  # noqa: B008
                 changes: tuple[str, ...] = CHANGES) -> DataFrame:
    """Hit rates around each kind of change: train, change the tables, measure drift, retrain from the weights at hand if it is large.

    ``insert`` adds a third of the instances that were held back, ``update`` renames a word in the sentences of half of the
    instances, ``delete`` takes a third of the instances away, ``none`` changes nothing.  One row for every change, phase
    (before, after), split and k, with the drift of words and whether it led to retraining.
    """
    tuples, mentions = entity_frames(spark, sf_dir, (type_name,), config)
    part = lambda salt, n: h(F.concat(F.lit(salt), F.col("instance_id"))) % 12 < n
    renamed = F.when(part("update", 6), F.regexp_replace("text", r"(?i)\bsize\b", "format")).otherwise(F.col("text"))
    moved = mentions.withColumn("text", renamed)
    if "update" in changes:  # sentences that changed are encoded anew
        _, full = entity_type(spark, sf_dir, type_name)
        spoken = full.select("mention_id", "span", "context")
        moved = materialize(moved.join(spoken, "mention_id").withColumn("vec", mention_vector(config)).select(mentions.columns), "updated")
    states = {
        "none": ((tuples, mentions), (tuples, mentions)),
        "insert": ((tuples.where(~part("late", 4)), mentions.where(~part("late", 4))), (tuples, mentions)),
        "update": ((tuples, mentions), (tuples, moved)),
        "delete": ((tuples, mentions), (tuples.where(~part("gone", 4)), mentions.where(~part("gone", 4)))),
    }
    rows = []
    for change in changes:
        (old_t, old_m), (new_t, new_m) = states[change]
        before = trained(old_t, old_m, config)
        drifts = should_relink(old_m, new_m)
        again = max(drifts.values()) > threshold
        after = trained(new_t, new_m, config, before) if again else before
        for phase, w in (("before", before), ("after", after)):
            got = hit_at_k(links_of(new_t, new_m, w, config), ["entity_type", "split"])
            rows.append(got.select(F.lit(change).alias("change"), F.lit(phase).alias("phase"), F.lit(round(drifts["words"], 6)).alias("drift"), F.lit(again).alias("retrained"), "*"))
    return reduce(DataFrame.unionByName, rows)


def stage_seconds(spark: SparkSession, sf_dir: str, types: tuple[str, ...] = ("product-name",), config: Config = Config(steps=60), trees: int = 8, budget: int = 160) -> DataFrame:  # noqa: B008
    """Seconds and rows of every load and query stage, scan against index in both directions, for each type and their mean.

    The index stages carry the share of the scan's links that they find.
    """
    out = []
    for type_name in types:
        out += _stages(spark, sf_dir, type_name, config, trees, budget)
    if len(types) > 1:
        steps = list(dict.fromkeys((p, s) for _, p, s, *_ in out))
        for phase, step in steps:
            own = [r for r in out if r[1:3] == (phase, step)]
            recalls = [r[5] for r in own if r[5] is not None]
            out.append(("mean", phase, step, sum(r[3] for r in own) // len(own), round(sum(r[4] for r in own) / len(own), 3), round(sum(recalls) / len(recalls), 6) if recalls else None))
    return spark.createDataFrame(out, "entity_type string, phase string, step string, rows long, seconds double, recall double")


def _stages(spark: SparkSession, sf_dir: str, type_name: str, config: Config, trees: int, budget: int) -> list[tuple]:
    tuples, mentions = entity_frames(spark, sf_dir, (type_name,), config)
    weights = trained(tuples, mentions, config)
    out, side = [], {}

    def clock(phase, step, work):
        at = time.perf_counter()
        made = work()
        rows = made.count() if isinstance(made, DataFrame) else 1
        out.append([type_name, phase, step, rows, round(time.perf_counter() - at, 3), None])
        return made

    def embed(df, key, tower, tag):
        return materialize(embedded(df, {type_name: tower}).select(F.col(key).alias("id"), "vec"), tag)

    clock("load", "model", lambda: side.update(r=load_tower(weights, type_name, "relation", config.steps), t=load_tower(weights, type_name, "text", config.steps)))
    e_t = clock("load", "embed tuples", lambda: embed(tuples, "tuple_id", side["r"], "e-t"))
    e_m = clock("load", "embed mentions", lambda: embed(mentions, "mention_id", side["t"], "e-m"))

    def index(base):
        side["f"] = Forest.fit(base, trees=trees)
        return side["f"].stored()

    clock("load", "index tuples", lambda: index(e_t))
    on_tuples = side["f"]
    clock("load", "index mentions", lambda: index(e_m))
    on_mentions = side["f"]
    scan = clock("query", "scan top 10", lambda: materialize(exact_knn(e_t, e_m, 10), "scan"))
    found = clock("query", "index top 10 mentions", lambda: materialize(on_mentions.query(e_t, 10, budget), "by-index"))
    out[-1][5] = ann_recall(found, scan).first()["recall"]
    clock("query", "index top 10 tuples", lambda: materialize(on_tuples.query(e_m, 10, budget), "by-index"))
    total = sum(r[4] for r in out if r[1] == "load" and r[2] != "model")
    out.append([type_name, "load", "total", 0, round(total, 3), None])
    out.append([type_name, "load", "total with model", 0, round(total + out[0][4], 3), None])
    return [tuple(r) for r in out]
