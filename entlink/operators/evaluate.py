"""Accuracy, profile and skew measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from entlink.operators.ordering import ranked, sums_before

KS = (1, 5, 10)


def hit_at_k(links: DataFrame, by: list[str], ks: tuple[int, ...] = KS) -> DataFrame:
    """Share of queries with a right answer among the first k, for each group of ``by``.

    ``links`` has query_id, rank, correct (boolean) and the columns of ``by``, one row or more for every query.
    """
    best = links.groupBy(*by, "query_id").agg(F.min(F.when(F.col("correct"), F.col("rank"))).alias("best"))
    rows = best.withColumn("k", F.explode(F.array(*[F.lit(k) for k in ks])))
    return rows.groupBy(*by, "k").agg(
        F.sum(F.when(F.col("best") <= F.col("k"), 1).otherwise(0)).cast("bigint").alias("hits"), F.count("*").alias("queries")
    ).withColumn("rate", F.round(F.col("hits") / F.col("queries"), 6))


def ranking_metrics(links: DataFrame, relevant: DataFrame, k: int) -> DataFrame:
    """Per query: precision, recall, reciprocal rank and average precision at ``k``; relevant is (query_id, n)."""
    w = Window.partitionBy("query_id").orderBy("rank").rowsBetween(Window.unboundedPreceding, 0)
    top = links.where(F.col("rank") <= k).withColumn("right", F.col("correct").cast("int"))
    top = top.withColumn("so_far", F.sum("right").over(w))
    per = top.groupBy("query_id").agg(
        F.sum("right").alias("found"),
        F.min(F.when(F.col("right") == 1, F.col("rank"))).alias("first"),
        F.sum(F.when(F.col("right") == 1, F.col("so_far") / F.col("rank")).otherwise(0.0)).alias("gain"),
    )
    return per.join(relevant, "query_id").select(
        "query_id",
        F.round(F.col("found") / k, 6).alias("precision_at_k"),
        F.round(F.col("found") / F.col("n"), 6).alias("recall_at_k"),
        F.round(F.coalesce(1 / F.col("first"), F.lit(0.0)), 6).alias("reciprocal_rank"),
        F.round(F.col("gain") / F.least(F.col("n"), F.lit(k)), 6).alias("average_precision"),
    )


def profile(tuples: DataFrame, columns: list[str], instance: str, mentions: DataFrame) -> DataFrame:
    """Instances, tuples, sentences, sentences per instance, columns and mean share of non-null attributes."""
    filled = sum((F.col(c).isNotNull().cast("int") for c in columns), F.lit(0)) / len(columns)
    left = tuples.agg(F.countDistinct(instance).alias("instances"), F.count("*").alias("tuples"), F.round(F.avg(filled), 6).alias("density"))
    right = mentions.agg(F.count("*").alias("sentences"))
    return left.crossJoin(right).select(  # one row each
        "instances", "tuples", "sentences", F.round(F.col("sentences") / F.col("instances"), 6).alias("per_instance"), F.lit(len(columns)).alias("columns"), "density"
    )


def skew(gold: DataFrame, item: str) -> DataFrame:
    """Items by popularity with their rank and the share that they and all more popular ones hold."""
    counts = gold.groupBy(item).agg(F.count("*").alias("n"))
    order = [F.desc("n"), F.col(item).asc_nulls_first()]
    placed, _ = ranked(counts, order, "rank", "skew")
    before = sums_before(placed, ["rank"], "n", "before", "skew-sums")
    total = counts.agg(F.sum("n").alias("total"))  # one row
    share = F.round((F.col("before") + F.col("n")) / F.col("total"), 6)
    return before.crossJoin(F.broadcast(total)).select(item, "n", (F.col("rank") + 1).cast("int").alias("rank"), share.alias("share"))


def ann_recall(approx: DataFrame, exact: DataFrame) -> DataFrame:
    """Share of the exact neighbours that an index finds; both have query_id, result_id."""
    hits = exact.select("query_id", "result_id").join(approx.select("query_id", "result_id").withColumn("hit", F.lit(1)), ["query_id", "result_id"], "left")
    return hits.agg(F.round(F.avg(F.coalesce("hit", F.lit(0))), 6).alias("recall"), F.countDistinct("query_id").alias("queries"))


def separation(scores: DataFrame, margin: float) -> DataFrame:
    """Mean distance of matches and of non-matches, and the share of non-matches beyond the margin circle of their tuple."""
    w = Window.partitionBy("r_id")
    pos = F.avg(F.when(F.col("is_match"), F.col("dist"))).over(w)
    rows = scores.withColumn("ring", pos + margin)
    return rows.agg(
        F.round(F.avg(F.when(F.col("is_match"), F.col("dist"))), 6).alias("mean_positive"),
        F.round(F.avg(F.when(~F.col("is_match"), F.col("dist"))), 6).alias("mean_negative"),
        F.round(F.avg(F.when(~F.col("is_match"), (F.col("dist") > F.col("ring")).cast("int"))), 6).alias("outside"),
    )


def drift(old: DataFrame, new: DataFrame, column: str) -> DataFrame:
    """Total variation between the distributions of a column in two versions of a table."""

    def share(df: DataFrame, name: str) -> DataFrame:
        total = df.agg(F.count("*").alias("total"))  # one row
        return df.groupBy(column).agg(F.count("*").alias("n")).crossJoin(F.broadcast(total)).select(column, (F.col("n") / F.col("total")).alias(name))

    both = share(old, "p").join(share(new, "q"), column, "full")
    return both.agg(F.round(F.sum(F.abs(F.coalesce("p", F.lit(0.0)) - F.coalesce("q", F.lit(0.0)))) / 2, 6).alias("total_variation"))


def should_retrain(old: DataFrame, new: DataFrame, columns: list[str], threshold: float = 0.05) -> bool:
    """Whether the distribution of any column has moved by more than the threshold."""
    return any((drift(old, new, c).first()["total_variation"] or 0.0) > threshold for c in columns)
