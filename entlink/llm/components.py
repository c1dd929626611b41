"""Connected components of an edge table by alternating large and small stars.

Every round is two aggregates and joins over the edges; the result is written
to the shared folder, so lineage stays short.  Rounds end when the edge set no
longer changes, which takes a number of rounds that grows with the logarithm
of the longest path.  Nothing but two checksums per round reaches the driver.

A star's centre meets all its neighbours.  Least neighbours are aggregated
before the shuffle, and where they are joined back, centres with more than one
in ``HOT_SHARE`` of the edges, of which there are fewer than twice as many, are
broadcast, so their edges stay where they are.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from entlink.storage import discard, materialize

HOT_SHARE = 1000


def _with_least(edges: DataFrame, total: int) -> DataFrame:
    """Edges with ``m``, the least of the centre ``u`` and all its neighbours."""
    low = edges.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"), F.count("*").alias("n"))
    hot = F.col("n") * HOT_SHARE > total
    often = F.broadcast(low.where(hot).select("u", "m"))
    rest = edges.join(F.broadcast(low.where(hot).select("u")), "u", "left_anti").join(low.where(~hot).select("u", "m"), "u")
    return edges.join(often, "u").select("u", "v", "m").unionByName(rest.select("u", "v", "m"))


def _large_star(edges: DataFrame, total: int) -> DataFrame:
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    return _with_least(both, 2 * total).where("v > u").select(F.col("m").alias("u"), "v").where("u != v")


def _small_star(edges: DataFrame, total: int) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    hung = _with_least(down, total).select(F.col("m").alias("u"), "v").where("u != v")
    low = down.groupBy("u").agg(F.min("v").alias("m"))
    return hung.unionByName(low.select(F.col("m").alias("u"), F.col("u").alias("v")))


def _state(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v"))).first())


def connected_components(edges: DataFrame) -> DataFrame:
    """``edges(u, v)`` of long ids → ``(node, root)`` for every node with a link; root is the least node.

    Self loops and repeated edges do no harm; an empty table gives an empty table.
    """
    links = edges.where("u != v").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct()
    now = materialize(links, "components")
    state = _state(now)
    while state[0]:
        starred = materialize(_large_star(now, state[0]).distinct(), "components")
        then = materialize(_small_star(starred, state[0]).distinct(), "components")
        discard(starred)
        discard(now)
        now, before, state = then, state, _state(then)
        if state == before:
            break
    return now.select(F.col("v").alias("node"), F.col("u").alias("root")).unionByName(
        now.select(F.col("u").alias("node"), F.col("u").alias("root")).distinct()
    )
