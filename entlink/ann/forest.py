"""Forest of random hyperplane trees.

A node takes two of its points and splits by the plane between them.  Planes are
grown on the driver from a bounded sample and broadcast; the larger the base is
beside the sample, the smaller the sample's leaves, so a leaf of the base stays
small.  Every row of the base is assigned to one leaf per tree, a whole batch
going down a tree level by level, and stored by (tree, leaf).  A query visits
leaves best first, by the smallest margin by which a plane was crossed, until its
budget of candidates is met; candidates are merged and ranked by exact distance.
Vectors travel as 32-bit floats in bytes.
"""

from __future__ import annotations

import pickle

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from entlink.ann.exact import BLOCK, nearest_positions
from entlink.storage import materialize

SAMPLE = 50_000
LEAST_LEAF = 4  # sample points in a leaf, however large the base is
ROWS_AT_ONCE = 16_384  # base rows, about, of the leaves in one bucket of a tree


class Tree:
    """Planes in arrays: node i splits by ``normal[i] @ x + offset[i] > 0`` into right, else left; leaves are negative."""

    def __init__(self, points: np.ndarray, leaf_size: int, rng: np.random.Generator):
        self.normal, self.offset, self.kids, self.sizes = [], [], [], []
        self.root = self._grow(points, np.arange(len(points)), leaf_size, rng, 0)
        self.normal = np.array(self.normal).reshape(-1, points.shape[1])
        self.offset, self.kids = np.array(self.offset), np.array(self.kids, int).reshape(-1, 2)
        self.sizes = np.array(self.sizes)  # of the sample

    def _leaf(self, n: int) -> int:
        self.sizes.append(n)
        return -len(self.sizes)

    def _grow(self, x, own, leaf_size, rng, depth) -> int:
        if len(own) <= leaf_size or depth > 40:
            return self._leaf(len(own))
        for _ in range(3):
            a, b = x[rng.choice(own, 2, replace=False)]
            normal, offset = a - b, -(a - b) @ (a + b) / 2
            side = x[own] @ normal + offset > 0
            if 0.05 < side.mean() < 0.95:
                break
        else:
            if not side.any() or side.all():
                return self._leaf(len(own))
        node = len(self.normal)
        self.normal.append(normal)
        self.offset.append(offset)
        self.kids.append(None)
        self.kids[node] = (self._grow(x, own[~side], leaf_size, rng, depth + 1), self._grow(x, own[side], leaf_size, rng, depth + 1))
        return node

    def leaf_of(self, x: np.ndarray) -> np.ndarray:
        """The leaf of every row of ``x``, one level of the tree at a time."""
        node = np.full(len(x), self.root)
        while (live := np.flatnonzero(node >= 0)).size:
            at = node[live]
            right = np.einsum("ij,ij->i", self.normal[at], x[live]) + self.offset[at] > 0
            node[live] = self.kids[at, right.astype(int)]
        return -node - 1

    def leaves_of(self, x: np.ndarray, budget: int) -> tuple[np.ndarray, np.ndarray]:
        """Rows of ``x`` and their leaves, best first, until these hold ``budget`` sample points.

        The cost of a leaf is the largest margin of the planes that its path crosses against the row's own side.
        """
        cost = np.zeros((len(self.sizes), len(x)), np.float32)
        if len(self.normal):
            margin = (self.normal @ x.T + self.offset[:, None]).astype(np.float32)
            reach = [(self.root, np.zeros(len(x), np.float32))]
            while reach:
                node, so_far = reach.pop()
                if node < 0:
                    cost[-node - 1] = so_far
                    continue
                m = margin[node]
                # Where the side is the row's own the margin has the other sign and changes nothing.
                reach += [(self.kids[node, 0], np.maximum(so_far, m)), (self.kids[node, 1], np.maximum(so_far, -m))]
        cost, sizes = np.ascontiguousarray(cost.T), np.maximum(1, self.sizes)
        # Enough leaves for the budget in nearly all cases; rows that need more are sorted whole.
        some = min(len(sizes), 4 + int(3 * budget / sizes.mean()))
        rows, leaves, rest = _first(cost, sizes, budget, some)
        if len(rest):
            more, own, _ = _first(cost[rest], sizes, budget, len(sizes))
            rows, leaves = np.concatenate((rows, rest[more])), np.concatenate((leaves, own))
            order = np.argsort(rows, kind="stable")
            rows, leaves = rows[order], leaves[order]
        return rows, leaves


def _first(cost: np.ndarray, sizes: np.ndarray, budget: int, some: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows and their cheapest leaves until these hold the budget, and the rows for which ``some`` leaves are too few."""
    part = np.argpartition(cost, some - 1, axis=1)[:, :some] if some < cost.shape[1] else np.broadcast_to(np.arange(cost.shape[1]), cost.shape)
    part = np.take_along_axis(part, np.argsort(np.take_along_axis(cost, part, axis=1), axis=1, kind="stable"), axis=1)
    held = np.cumsum(sizes[part], axis=1)
    few = (held[:, -1] < budget) & (some < cost.shape[1])
    taken = np.concatenate((np.ones((len(cost), 1), bool), held[:, :-1] < budget), axis=1) & ~few[:, None]
    rows, place = np.nonzero(taken)
    return rows, part[rows, place], np.flatnonzero(few)


def packed(vec: Column) -> Column:
    """Vectors as 32-bit floats in bytes."""

    @F.pandas_udf("binary")
    def run(vecs: pd.Series) -> pd.Series:
        return vecs.map(lambda v: np.asarray(v, "<f4").tobytes())

    return run(vec)


def matrix(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    """Packed vectors of one length as a matrix, straight from their buffer."""
    raw = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    if not len(raw):
        return np.zeros((0, 0))
    ends = np.frombuffer(raw.buffers()[1], np.int32)[raw.offset : raw.offset + len(raw) + 1]
    data = np.frombuffer(raw.buffers()[2], np.uint8)[ends[0] : ends[-1]]
    return data.view("<f4").reshape(len(raw), -1).astype(float)


def _whole(column: pa.Array | pa.ChunkedArray) -> pa.Array:
    return column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column


class Forest:
    def __init__(self, trees: list[Tree], scale: float, leaves: DataFrame | None = None):
        self.trees, self.scale, self.leaves = trees, scale, leaves

    @classmethod
    def fit(cls, base: DataFrame, trees: int = 16, leaf_size: int = 64, seed: int = 1, sample: int = SAMPLE) -> Forest:
        """Grow planes from at most ``sample`` rows of (id, vec), chosen by hash of the id, and assign every row."""
        total = base.count()
        rows = base.orderBy(F.xxhash64("id"), "id").limit(sample).collect() if total > sample else base.orderBy("id").collect()
        points = np.array([r.vec for r in rows], float)
        scale = max(1.0, total / max(1, len(points)))
        own = max(LEAST_LEAF, int(leaf_size / scale))
        forest = cls([Tree(points, own, np.random.default_rng([seed, t])) for t in range(trees)] if len(points) else [], scale)
        forest.leaves = forest.assign(base)
        return forest

    def assign(self, base: DataFrame) -> DataFrame:
        """``(tree, leaf, id, vec)`` of every base row in every tree, vectors packed."""
        shared, kind = base.sparkSession.sparkContext.broadcast(self.trees), dict(base.dtypes)["id"]

        def run(batches):
            for b in batches:
                x = matrix(b.column(1))
                for i, t in enumerate(shared.value if len(x) else ()):
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(x), i, np.int32)), pa.array(t.leaf_of(x).astype(np.int32)), b.column(0), b.column(1)], ["tree", "leaf", "id", "vec"])

        return base.select("id", packed(F.col("vec")).alias("vec")).mapInArrow(run, f"tree int, leaf int, id {kind}, vec binary")

    def stored(self) -> DataFrame:
        """Write the leaves to the shared folder and use those from now on."""
        self.leaves = materialize(self.leaves, "leaves")
        return self.leaves

    def query(self, queries: DataFrame, n: int = 10, budget: int = 400, metric: str = "cosine") -> DataFrame:
        """``(query_id, result_id, distance, rank)`` by visiting about ``budget`` candidates in every tree."""
        shared, share = queries.sparkSession.sparkContext.broadcast(self.trees), max(1, int(budget / self.scale))
        counts = [len(t.sizes) for t in self.trees]
        mean = self.scale * max((t.sizes.sum() / len(t.sizes) for t in self.trees), default=1.0)
        buckets = max(1, int(max(counts, default=1) * mean / ROWS_AT_ONCE))
        kind = dict(self.leaves.dtypes)["id"], dict(queries.dtypes)["id"]

        def probe(batches):
            for b in batches:
                for at in range(0, b.num_rows, BLOCK):
                    part = b.slice(at, BLOCK)
                    x = matrix(part.column(1))
                    for i, t in enumerate(shared.value):
                        rows, leaves = t.leaves_of(x, share)
                        rows = pa.array(rows)
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(rows), i, np.int32)), pa.array(leaves.astype(np.int32)), part.column(0).take(rows), part.column(1).take(rows)], ["tree", "leaf", "id", "vec"])

        def best(left: pa.Table, right: pa.Table) -> pa.Table:
            """The best ``n`` within the leaves of one bucket, in one row for a query and leaf: a leaf holds few rows, and no others can matter."""
            left, right = left.take(pc.sort_indices(left, [("leaf", "ascending")])), right.take(pc.sort_indices(right, [("leaf", "ascending"), ("id", "ascending")]))
            q, b = matrix(left["vec"]), matrix(right["vec"])
            ql, bl = left["leaf"].to_numpy(), right["leaf"].to_numpy()
            found = [(np.zeros(0, int), np.zeros(0, int), np.zeros(0))]
            for leaf in np.intersect1d(ql, bl):
                (i, j), (k, m) = (np.searchsorted(x, [leaf, leaf + 1]) for x in (ql, bl))
                for at in range(i, j, BLOCK):
                    r, c, d = nearest_positions(q[at : min(j, at + BLOCK)], b[k:m], n, metric)
                    found.append((r + at, c + k, d))
            r, c, d = (np.concatenate(x) for x in zip(*found))
            cuts = np.flatnonzero(np.concatenate(([True], r[1:] != r[:-1]))) if len(r) else np.zeros(0, int)
            offsets = pa.array(np.append(cuts, len(r)).astype(np.int32))
            results = pa.ListArray.from_arrays(offsets, _whole(right["id"]).take(pa.array(c)))
            return pa.table({"query_id": _whole(left["id"]).take(pa.array(r[cuts])), "results": results, "distances": pa.ListArray.from_arrays(offsets, pa.array(d))})

        keys = ["tree", "bucket"]
        bucket = (F.col("leaf") % buckets).alias("bucket")
        slim = queries.select(F.col("id").alias("id"), packed(F.col("vec")).alias("vec"))
        asked = slim.mapInArrow(probe, f"tree int, leaf int, id {kind[1]}, vec binary").select("*", bucket)
        # New names for old columns: queries and leaves may come from the same frame.
        held = self.leaves.select(*[F.col(c).alias(c) for c in ("tree", "leaf", "id", "vec")]).select("*", bucket)
        scored = asked.groupBy(*keys).cogroup(held.groupBy(*keys)).applyInArrow(best, f"query_id {kind[1]}, results array<{kind[0]}>, distances array<double>")
        # One row for each query, with trees * leaves * n links at most; equal ones stand side by side once sorted.
        each = scored.select("query_id", F.arrays_zip(F.col("distances").alias("distance"), F.col("results").alias("result_id")).alias("links"))
        merged = each.groupBy("query_id").agg(F.array_sort(F.flatten(F.collect_list("links"))).alias("links"))
        once = F.filter("links", lambda x, i: (i == 0) | (x["result_id"] != F.get("links", i - 1)["result_id"]))
        top = merged.select("query_id", F.posexplode(F.slice(once, 1, n)).alias("at", "link"))
        return top.select("query_id", "link.result_id", "link.distance", (F.col("at") + 1).alias("rank"))

    def upsert(self, rows: DataFrame) -> Forest:
        """The forest with rows added or replaced, by the planes it has."""
        kept = self.leaves.join(rows.select("id"), "id", "left_anti")
        return Forest(self.trees, self.scale, kept.unionByName(self.assign(rows).select(*kept.columns)))

    def delete(self, ids: DataFrame) -> Forest:
        return Forest(self.trees, self.scale, self.leaves.join(ids.select("id"), "id", "left_anti"))

    def save(self, path: str) -> None:
        """Planes and leaves as Parquet, leaves by tree."""
        spark = self.leaves.sparkSession
        self.leaves.write.mode("overwrite").partitionBy("tree").parquet(f"{path}/leaves")
        spark.createDataFrame([(bytearray(pickle.dumps(self.trees)), float(self.scale))], "planes binary, scale double").write.mode("overwrite").parquet(f"{path}/planes")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> Forest:
        row = spark.read.parquet(f"{path}/planes").first()
        return cls(pickle.loads(row.planes), row.scale, spark.read.parquet(f"{path}/leaves"))
