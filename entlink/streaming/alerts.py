"""Streams: hourly alerts on arriving mentions, deduplication, joins, running counts."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from entlink.ann.exact import exact_knn
from entlink.joint.train import load_tower
from entlink.operators.ordering import ntile
from entlink.plans.accuracy import embedded
from entlink.storage import materialize, scratch_path


def drain(stream: DataFrame, tag: str, mode: str = "append", sink: Callable | None = None) -> DataFrame:
    """Run a stream over all input that is there and return what it wrote."""
    spark = stream.sparkSession
    out, checkpoint = scratch_path(spark, tag), scratch_path(spark, f"{tag}-checkpoint")
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True)
    writer = writer.foreachBatch(sink(out)) if sink else writer.format("parquet").option("path", out)
    query = writer.start()
    query.awaitTermination()
    return spark.read.parquet(out)


def event_files(events: DataFrame, files: int = 6) -> str:
    """Events as files in time order, for replay as a stream."""
    path = scratch_path(events.sparkSession, "event-files")
    timed = ntile(events.withColumn("ts", F.col("ts").cast("timestamp")), ["ts", "event_id"], files, "_part", "event-order")
    for i in range(1, files + 1):  # one after the other: the file source reads by modification time
        timed.where(F.col("_part") == i).drop("_part").coalesce(1).write.mode("append").parquet(path)
    return path


def event_stream(spark: SparkSession, path: str) -> DataFrame:
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 2).parquet(path)


def hourly_links(events: DataFrame, mentions: DataFrame, names: DataFrame) -> DataFrame:
    """Alerts (hour, name, n): mentions timed by events, linked to names that they contain, counted by the hour.

    ``events`` is a stream with ts and mention_no; ``mentions`` (mention_no, text) and ``names`` (name) are static.
    """
    said = events.withWatermark("ts", "1 hour").join(mentions, "mention_no")
    hits = said.select("ts", F.explode(F.split(F.lower("text"), r"[^\p{L}]+")).alias("w1"), "text").join(
        names.select(F.substring_index("name", " ", 1).alias("w1"), "name"), "w1"
    )
    return hits.where(F.contains(F.lower("text"), "name")).groupBy(F.window("ts", "1 hour").alias("w"), "name").agg(F.count("*").alias("n")).select(
        F.col("w.start").alias("hour"), "name", "n"
    )


def learned_alerts(events: DataFrame, mentions: DataFrame, tuples: DataFrame, models, entity_type: str) -> DataFrame:
    """Alerts (hour, instance_id, n, seconds, version) of a stream with ts and mention_no, by learned links.

    ``mentions`` (mention_no, entity_type, vec) and ``tuples`` (tuple_id, instance_id, entity_type, vec) hold what the
    towers read.  Every batch asks the model store for the current version, so a model that is published while the
    stream runs serves from the next batch on; the tuples are embedded once for each version.  ``seconds`` is the time
    from the start of a batch to its alerts.
    """
    spark = events.sparkSession
    out, checkpoint = scratch_path(spark, "alerts"), scratch_path(spark, "alerts-checkpoint")
    held: dict[int, tuple] = {}

    def link(batch: DataFrame, number: int) -> None:
        at = time.perf_counter()
        version = models.current(entity_type)
        if version not in held:
            weights = models.load(entity_type, version)
            step = weights.agg(F.max("step")).first()[0]
            towers = [load_tower(weights, entity_type, side, step) for side in ("relation", "text")]
            held.clear()
            held[version] = (materialize(embedded(tuples, {entity_type: towers[0]}).select(F.col("tuple_id").alias("id"), "instance_id", "vec"), "alert-tuples"), towers[1])
        stored, text = held[version]
        said = materialize(embedded(batch.join(mentions, "mention_no"), {entity_type: text}).select("event_id", "ts", "vec"), "alert-mentions")
        links = exact_knn(said.select(F.col("event_id").alias("id"), "vec"), stored.select("id", "vec"), 1)
        named = links.join(stored.select(F.col("id").alias("result_id"), "instance_id"), "result_id").join(said.select(F.col("event_id").alias("query_id"), "ts"), "query_id")
        found = materialize(named.groupBy(F.date_trunc("hour", "ts").alias("hour"), "instance_id").agg(F.count("*").alias("n")), "alert-counts")
        found.withColumn("seconds", F.lit(time.perf_counter() - at)).withColumn("version", F.lit(version)).withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{out}/batch={number}")

    writer = events.writeStream.option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(link)
    writer.start().awaitTermination()
    rows = spark.read.parquet(f"{out}/batch=*")
    # An hour may end in a later batch than it began.
    return rows.groupBy("hour", "instance_id").agg(F.sum("n").alias("n"), F.max("seconds").alias("seconds"), F.max("version").alias("version"))


def once_per_event(stream: DataFrame) -> DataFrame:
    """Drop repeated deliveries of an event within the watermark."""
    return stream.withWatermark("ts", "1 day").dropDuplicatesWithinWatermark(["event_id"])


def seen_counts(stream: DataFrame) -> DataFrame:
    """Running number of events of each user as of every batch, in keyed state."""

    def update(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "seen": [n]})

    return stream.groupBy("user_id").applyInPandasWithState(update, "user_id long, seen long", "seen long", "append", "NoTimeout")
