"""The contrastive loss as DataFrame aggregates over a table of scores.

``scores`` has r_id, t_id, dist and is_match.  A side's loss sums, over each of
its non-matches, how far margin plus mean distance of the matches exceeds the
non-match's distance.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from entlink.ann.exact import Blocks, distances, scanned

SIDES = {"relation": "r_id", "text": "t_id"}


def mean_positive(scores: DataFrame, side: str) -> DataFrame:
    return scores.where("is_match").groupBy(SIDES[side]).agg(F.avg("dist").alias("mean_positive"), F.count("*").alias("n"))


def partial_loss(scores: DataFrame, side: str, margin: float) -> DataFrame:
    """Loss of every item of a side that has a match."""
    key = SIDES[side]
    near = F.avg(F.when(F.col("is_match"), F.col("dist"))).over(Window.partitionBy(key))
    rows = scores.withColumn("near", near).where(~F.col("is_match") & F.col("near").isNotNull())
    return rows.groupBy(key).agg(F.sum(F.greatest(F.lit(0.0), margin + F.col("near") - F.col("dist"))).alias("loss"))


def total_loss(scores: DataFrame, margin: float) -> DataFrame:
    both = [partial_loss(scores, s, margin).select("loss") for s in SIDES]
    return both[0].unionByName(both[1]).agg(F.round(F.sum("loss"), 4).alias("loss"))


def single_positive_loss(scores: DataFrame, side: str, margin: float) -> DataFrame:
    """The earlier form: each match against each non-match of an item."""
    key = SIDES[side]
    pos = scores.where("is_match").select(key, F.col("dist").alias("near"))
    neg = scores.where("not is_match").select(key, "dist")
    return pos.join(neg, key).groupBy(key).agg(F.sum(F.greatest(F.lit(0.0), margin + F.col("near") - F.col("dist"))).alias("loss"))


def _masks(label: np.ndarray, other: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which pairs match and which do not; pairs with an unknown label are neither."""
    same = label[:, None] == other[None]
    return same, ~same & ~np.isnan(label)[:, None] & ~np.isnan(other)[None]


def _scores(label: np.ndarray, q: np.ndarray, blocks: Blocks, digits: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    for right, b in blocks:
        yield np.round(distances(q, b, "cosine"), digits), *_masks(label, right.label.to_numpy(float))


def scanned_loss(items: DataFrame, others: DataFrame, margin: float | None = None, digits: int = 9) -> DataFrame:
    """``(id, n, mean_positive, negatives, loss)`` of every item, as ``mean_positive`` and ``partial_loss`` give them for all pairs.

    Inputs are (id, vec, label); labels are numbers, and equal ones match.  Pairs are summed where their distances are
    made, in one scan for the means and one for the loss, so none is stored.  Without ``margin`` there is no second scan.
    """

    def visit(left: pd.DataFrame, q: np.ndarray, blocks: Blocks) -> Iterator[pd.DataFrame]:
        label, n, total, lost, negatives = left.label.to_numpy(float), *np.zeros((4, len(left)))
        for d, same, _ in _scores(label, q, blocks, digits):
            n += same.sum(1)
            total += np.where(same, d, 0.0).sum(1)
        near = np.divide(total, n, out=np.full(len(n), np.nan), where=n > 0)
        if margin is not None:
            for d, _, apart in _scores(label, q, blocks, digits):
                negatives += apart.sum(1)
                lost += np.where(apart, np.maximum(0.0, margin + near[:, None] - d), 0.0).sum(1)
        yield pd.DataFrame({"id": left.id, "n": n.astype(int), "mean_positive": near, "negatives": negatives.astype(int), "loss": lost})

    return _scanned(items, others, visit, "n bigint, mean_positive double, negatives bigint, loss double")


def scanned_single_loss(items: DataFrame, others: DataFrame, margin: float, digits: int = 9) -> DataFrame:
    """``(id, n, negatives, loss)``, as ``single_positive_loss`` gives it for all pairs: each match against each non-match.

    An item's distances are held together; with sums over its sorted matches no pair of match and non-match is formed.
    """

    def one(near: np.ndarray, far: np.ndarray) -> float:
        near = np.sort(near)
        rest = np.append(np.cumsum(near[::-1])[::-1], 0.0)
        at = np.searchsorted(near, far - margin, side="right")
        return float((rest[at] + (len(near) - at) * (margin - far)).sum())

    def visit(left: pd.DataFrame, q: np.ndarray, blocks: Blocks) -> Iterator[pd.DataFrame]:
        found = list(_scores(left.label.to_numpy(float), q, blocks, digits))
        if found:
            d, same, apart = (np.concatenate(x, axis=1) for x in zip(*found))
            lost = [one(d[i][same[i]], np.sort(d[i][apart[i]])) for i in range(len(d))]
            yield pd.DataFrame({"id": left.id, "n": same.sum(1), "negatives": apart.sum(1), "loss": lost})

    return _scanned(items, others, visit, "n bigint, negatives bigint, loss double", keep_all=True)


def _scanned(items: DataFrame, others: DataFrame, visit, columns: str, keep_all: bool = False) -> DataFrame:
    own = lambda df: df.select(F.lit("all").alias("grp"), "id", "vec", F.col("label").cast("double").alias("label"))
    schema = f"grp string, id {dict(items.dtypes)['id']}, {columns}"
    return scanned(own(items), own(others), visit, schema, keep_all=keep_all).drop("grp")


def sampler_weights(counts: DataFrame, power: float = 1.0, omit_above: float = 4.0) -> DataFrame:
    """Weight of every true pair by how often it was seen; pairs seen far more than the mean are left out."""
    rows = counts.crossJoin(F.broadcast(counts.agg(F.avg("seen").alias("mean_seen"))))  # one row
    return rows.where(F.col("seen") <= omit_above * F.col("mean_seen") + 1).withColumn("weight", F.pow(1.0 + F.col("seen"), F.lit(-power))).drop("mean_seen")


def draw_pairs(weighted: DataFrame, n: int, seed: str) -> DataFrame:
    """Weighted sample without replacement: the ``n`` least of -ln(u) / weight, u by hash of seed and pair."""
    from entlink.functions.text import h

    u = (h(F.concat(F.lit(seed), F.col("tuple_id"), F.lit("|"), F.col("mention_id"))) + 0.5) / 4294967296.0
    return weighted.withColumn("draw", -F.log(u) / F.col("weight")).orderBy("draw", "tuple_id", "mention_id").limit(n)
