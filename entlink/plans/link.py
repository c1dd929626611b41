"""The link predicate: one call, several strategies, each rewritten to a plan that does not enumerate pairs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from entlink.ann.exact import exact_knn
from entlink.ann.forest import Forest
from entlink.operators import candidates
from entlink.operators.evaluate import ann_recall
from entlink.storage import materialize


def link(names: DataFrame, texts: DataFrame, strategy: str | list[str] = "shared_word", gold: DataFrame | None = None, n: int = 10,
         max_distance: float | None = None, search: str = "exact", trees: int = 16, budget: int = 400, **how) -> DataFrame:
    """Candidates ``(name_id, text_id, ...)``.

    ``equal``, ``contains`` and ``shared_word`` read (id, text); ``gold`` is a semi join with known pairs; ``semantic``
    reads (id, vec) and searches as ``search`` says, at every size alike: ``exact`` scans all pairs in blocks, ``index``
    goes through a forest of ``trees`` with ``budget`` candidates in each (see ``index_recall`` for what it finds).
    """
    if isinstance(strategy, list):
        return candidates.union_of({s: link(names, texts, s, gold, n, max_distance, search, trees, budget) for s in strategy})
    if strategy == "equal":
        return candidates.equal(names, texts)
    if strategy == "contains":
        return candidates.contained(names, texts)
    if strategy == "shared_word":
        return candidates.shared_word(names, texts, **how)
    if strategy == "gold":
        return gold.join(names.select(F.col("id").alias("name_id")), "name_id", "left_semi").join(texts.select(F.col("id").alias("text_id")), "text_id", "left_semi")
    if strategy == "semantic":
        if search not in ("exact", "index"):
            raise ValueError(f"no search {search}")
        found = exact_knn(names, texts, n) if search == "exact" else Forest.fit(texts, trees=trees, **how).query(names, n, budget)
        found = found.select(F.col("query_id").alias("name_id"), F.col("result_id").alias("text_id"), "distance", "rank")
        return found.where(F.col("distance") <= max_distance) if max_distance is not None else found
    raise ValueError(f"no strategy {strategy}")


def index_recall(names: DataFrame, texts: DataFrame, n: int = 10, asked: int = 1000, trees: int = 16, budget: int = 400, **how) -> DataFrame:
    """Share of the exact links that the index finds, for the first ``asked`` names by hash of their id, against all texts."""
    some = materialize(names.orderBy(F.xxhash64("id"), "id").limit(asked), "asked")
    found = Forest.fit(texts, trees=trees, **how).query(some, n, budget)
    return ann_recall(found, exact_knn(some, texts, n))
