"""Sharding along a Hilbert curve over document metadata, in DataFrame functions only.

Each metadata dimension is cut into ``2**bits`` equal-depth steps, the steps of
all dimensions give a point, and the point's index on the Hilbert curve orders
the documents.  Cutting that order into runs of equal row counts gives shards
whose files cover small boxes in every dimension, so min/max statistics prune
on any of them.

The step of a value is the share of rows with lesser values, times the number of
steps, rounded down.  Values are counted first and the counts summed in order by
range, so the cuts are exact and the same on any cluster; at most one edge for
each step reaches the driver.  The curve is walked once for each cell of the
grid, not for each row.  The global order is a range partitioning, so no task
sees more than its range.

Defined results: nulls fall into the first step; a null text has size 1 and the
checksum of nothing; ties are ordered by identifier (null first), then size and
checksum; repeated rows each have a slot; an empty table gives an empty table;
other columns of the input are ignored, and ``write_shards`` keeps them all.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from entlink.operators.ordering import ranked, sums_before
from entlink.storage import materialize

#: Cells of a grid that may be broadcast with their place on the curve.
MOST_CELLS = 1 << 16


def curve_tables(dims: int) -> tuple[list[int], list[int]]:
    """Transition tables of the curve: for state and quadrant, the next state and the digit.

    A state is an entry corner and a direction (``corner * dims + direction``).
    """
    size = 1 << dims
    rotate = lambda x, k: ((x >> k % dims) | (x << (dims - k % dims))) & (size - 1)
    gray = [i ^ (i >> 1) for i in range(size)]
    rank = {g: i for i, g in enumerate(gray)}
    entry = [0 if i == 0 else gray[2 * ((i - 1) // 2)] for i in range(size)]
    low_ones = lambda i: (i ^ (i + 1)).bit_length() - 1
    turn = [0 if i == 0 else low_ones(i - 1 if i % 2 == 0 else i) % dims for i in range(size)]
    nxt, digit = [], []
    for corner in range(size):
        for direction in range(dims):
            for quadrant in range(size):
                w = rank[rotate(quadrant ^ corner, direction + 1)]
                e = corner ^ rotate(entry[w], dims - (direction + 1) % dims)
                nxt.append(e * dims + (direction + turn[w] + 1) % dims)
                digit.append(w)
    return nxt, digit


def hilbert_index(coords: list[Column], bits: int) -> Column:
    """Curve index of a point whose coordinates are integers of ``bits`` bits."""
    dims = len(coords)
    nxt, digit = curve_tables(dims)
    step = F.array(*[F.lit(n * (1 << dims) + d) for n, d in zip(nxt, digit, strict=True)])
    quadrants = F.array(
        *[
            sum((F.shiftleft(F.shiftright(c.cast("int"), b).bitwiseAND(1), k) for k, c in enumerate(coords)), F.lit(0))
            for b in range(bits - 1, -1, -1)
        ]
    )

    def walk(acc: Column, q: Column) -> Column:
        found = F.element_at(step, (acc["state"] * (1 << dims) + q + 1).cast("int"))
        return F.struct(
            F.shiftright(found, dims).alias("state"),
            (F.shiftleft(acc["index"], dims) + F.pmod(found, F.lit(1 << dims))).cast("long").alias("index"),
        )

    start = F.struct(F.lit(0).alias("state"), F.lit(0).cast("long").alias("index"))
    return F.aggregate(quadrants, start, walk, lambda acc: acc["index"])


def edges(df: DataFrame, column: str, bits: int) -> list[tuple[int, object]]:
    """``(step, least value)`` of every equal-depth step that holds values, in order; exact."""
    counts = materialize(df.where(F.col(column).isNotNull()).groupBy(F.col(column).alias("value")).agg(F.count("*").alias("n")), "hilbert-counts")
    total = counts.agg(F.sum("n").alias("n")).first()["n"]
    if not total:
        return []
    below = sums_before(counts, ["value"], "n", "below", "hilbert-values")
    step = F.floor(F.col("below") * (1 << bits) / F.lit(total)).cast("int")
    found = below.groupBy(step.alias("step")).agg(F.min("value").alias("value")).collect()  # 2**bits rows at most
    return sorted((r["step"], r["value"]) for r in found)


def step_of(value: Column, cut: list[tuple[int, object]]) -> Column:
    """The step whose edge is the greatest that does not exceed the value; null falls into the first."""
    out = F.lit(0)
    for step, edge in cut[1:]:
        out = F.when(value >= F.lit(edge), F.lit(step)).otherwise(out)
    return out


def curve_index(steps: list[Column], bits: int, spark) -> tuple[Column, DataFrame | None]:
    """The cell of a point, and the table ``(cell, curve)`` to join it with; None if the cell is the index itself."""
    dims = len(steps)
    if 1 << bits * dims > MOST_CELLS:
        return hilbert_index(steps, bits), None
    cell = sum((F.shiftleft(s.cast("long"), bits * k) for k, s in enumerate(steps)), F.lit(0).cast("long"))
    mask = (1 << bits) - 1
    back = [F.shiftright("id", bits * k).bitwiseAND(mask) for k in range(dims)]
    return cell, spark.range(1 << bits * dims).select(F.col("id").alias("cell"), hilbert_index(back, bits).alias("curve"))


def curve_order(docs: DataFrame, dims: list[str], id_col: str = "doc_id", text_col: str = "text", bits: int = 5, carry: bool = False) -> tuple[DataFrame, int]:
    """Documents with curve index and global rank: id, ``size``, ``text_crc32``, ``curve``, ``rank``; and their number.

    With ``carry`` the whole row comes along as the struct ``row``.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    slim = docs.select(
        F.col(id_col).alias("id"),
        *[F.col(d).alias(f"dim_{i}") for i, d in enumerate(dims)],
        (F.octet_length(text) + 1).cast("long").alias("size"),
        F.crc32(F.encode(text, "UTF-8")).alias("text_crc32"),
        *([F.struct("*").alias("row")] if carry else []),
    )
    kept = ["row"] if carry else []
    meta = materialize(slim.drop("row"), "hilbert-meta")
    names = [f"dim_{i}" for i in range(len(dims))] + ["size"]
    cell, curve = curve_index([step_of(F.col(n), edges(meta, n, bits)) for n in names], bits, docs.sparkSession)
    points = (slim if carry else meta).withColumn("cell", cell)
    # The grid has at most MOST_CELLS rows.
    points = points.withColumn("curve", F.col("cell")) if curve is None else points.join(F.broadcast(curve), "cell")
    keys = ["curve", "id", "size", "text_crc32"]
    return ranked(points.select(*keys, *kept), keys, "rank", "hilbert-order")


def _shard_and_slot(ordered: DataFrame, total: int, shards: int) -> tuple[Column, Column]:
    # Shard s holds ranks from floor(s * total / shards) up to the next such bound.
    shard = F.floor(((F.col("rank") + 1) * shards - 1) / F.lit(max(1, total)))
    return shard.cast("int"), (F.col("rank") - F.floor(shard * F.lit(total) / shards)).cast("long")


def assign_shards(
    docs: DataFrame, shards: int = 16, dims: tuple[str, ...] = ("lang", "source"), id_col: str = "doc_id", text_col: str = "text"
) -> DataFrame:
    """Shard and slot of every document; row counts of shards differ by one at most."""
    ordered, total = curve_order(docs, list(dims), id_col, text_col)
    shard, slot = _shard_and_slot(ordered, total, shards)
    return ordered.select(F.col("id").alias(id_col), "size", "text_crc32", "curve", shard.alias("shard"), slot.alias("slot"))


def write_shards(docs: DataFrame, path: str, shards: int = 16, dims: tuple[str, ...] = ("lang", "source"), id_col: str = "doc_id", text_col: str = "text") -> None:
    """Write whole documents as Parquet, one folder per shard; each range of the order is a task that writes its own files, rows in curve order."""
    ordered, total = curve_order(docs, list(dims), id_col, text_col, carry=True)
    shard, slot = _shard_and_slot(ordered, total, shards)
    rows = ordered.select("row.*", shard.alias("_shard"), slot.alias("_slot"))
    rows.sortWithinPartitions("_shard", "_slot").drop("_slot").write.partitionBy("_shard").parquet(path)
