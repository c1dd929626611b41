"""Exact links of similar shingle sets within candidate classes.

Fingerprints name candidates; whether two documents are similar is decided
here, on their whole shingle sets.  A candidate class holds every pair that the
fingerprints joined, directly or through others, so comparing inside classes
loses none of them.

Blocks.  A class is cut into blocks of about ``BLOCK`` shingles by a hash of
the identifier, so no task holds a large class whole.  In a block, pivots are
compared with all members.  Two classes of a block need no further comparison
once one of them has had all its members as pivots; so the smallest open class
gives the next pivot, and a family of near copies costs a few pivots, not its
square.

Across blocks the same rule goes in rounds: members outside the largest open
class of a candidate class are drawn as pivots, go to all its blocks, and their
links join classes, until one class at most is open.  The number drawn doubles
each round.

Defined results: sets without members have no links; a repeated identifier is
linked by any of its texts; similarity is that of Jaccard, compared as a quotient.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from entlink.llm.components import connected_components
from entlink.storage import materialize, release_memory

BLOCK = 1 << 18


class Members:
    """Shingle sets of one block, indexed for comparison with any set."""

    def __init__(self, sets: list[np.ndarray]):
        self.sizes = np.array([len(s) for s in sets], np.int64)
        self.known, self.at = np.unique(np.concatenate(sets), return_inverse=True)
        self.starts = np.cumsum(self.sizes) - self.sizes

    def similar(self, one: np.ndarray, similarity: float) -> np.ndarray:
        """Which members are similar to ``one``; every set has a member."""
        place = np.minimum(np.searchsorted(self.known, one), len(self.known) - 1)
        mark = np.zeros(len(self.known), bool)
        mark[place[self.known[place] == one]] = True
        both = np.add.reduceat(mark[self.at], self.starts, dtype=np.int64)
        return both / (self.sizes + len(one) - both) >= similarity


def spanning_links(sets: list[np.ndarray], similarity: float) -> list[tuple[int, int]]:
    """Links between positions of ``sets`` (none empty) that join all sets connected by pairs of the similarity."""
    if len(sets) < 2:
        return []
    members, root, open_ = Members(sets), np.arange(len(sets)), np.ones(len(sets), bool)
    links = []
    while True:
        left = np.bincount(root[open_], minlength=len(sets))
        classes = np.flatnonzero(left)
        if len(classes) < 2:
            return links
        pivot = int(np.flatnonzero(open_ & (root == classes[np.argmin(left[classes])]))[0])
        open_[pivot] = False
        near = members.similar(sets[pivot], similarity) & (root != root[pivot])
        met, first = np.unique(root[near], return_index=True)
        links += [(pivot, int(j)) for j in np.flatnonzero(near)[first]]
        root[np.isin(root, met)] = root[pivot]


def _blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """The rows of each (class, salt), which stand together."""
    held: list[pa.RecordBatch] = []
    for b in batches:
        if not b.num_rows:
            continue
        keys = np.stack([b.column("class").to_numpy(), b.column("salt").to_numpy()])
        cuts = np.flatnonzero((keys[:, 1:] != keys[:, :-1]).any(axis=0)) + 1
        if held and (held[-1].column("class")[-1].as_py(), held[-1].column("salt")[-1].as_py()) != tuple(keys[:, 0].tolist()):
            yield pa.Table.from_batches(held)
            held = []
        for lo, hi in zip([0, *cuts.tolist()], [*cuts.tolist(), b.num_rows]):
            held.append(b.slice(lo, hi - lo))
            if hi < b.num_rows:
                yield pa.Table.from_batches(held)
                held = []
    if held:
        yield pa.Table.from_batches(held)


def _sets(t: pa.Table) -> list[np.ndarray]:
    return [np.frombuffer(s, np.uint64) for s in t.column("shingles").to_pylist()]


def _in_blocks(rows: DataFrame, link: Callable[[pa.Table], tuple[np.ndarray, np.ndarray]]) -> DataFrame:
    """Links ``(u, v)`` that ``link`` finds in each block of ``rows``."""

    def run(batches):
        for t in _blocks(batches):
            u, v = link(t)
            if len(u):
                yield pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], ["u", "v"])
        release_memory()

    parts = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return rows.repartition(parts, "class", "salt").sortWithinPartitions("class", "salt").mapInArrow(run, "u long, v long")


def _across(rows: DataFrame, links: DataFrame, similarity: float, block: int) -> DataFrame:
    """``links`` and those between blocks of one class; ``rows`` are the members of classes of several blocks."""

    def compare(t: pa.Table):
        own = t.column("comp").to_numpy()
        node, pivot = t.column("node").to_numpy(), t.column("pivot").to_numpy(zero_copy_only=False)
        sets, u, v = _sets(t), [], []
        here = np.flatnonzero(~pivot)
        if len(here):
            members = Members([sets[i] for i in here])
            for p in np.flatnonzero(pivot):
                near = here[members.similar(sets[p], similarity) & (own[here] != own[p])]
                _, first = np.unique(own[near], return_index=True)
                u += [node[p]] * len(first)
                v += node[near[first]].tolist()
        return np.array(u, np.int64), np.array(v, np.int64)

    done, cap, turn = rows.select("node").where("false"), block, 0
    while True:
        roots = materialize(connected_components(links), "exact-roots")
        state = materialize(
            rows.select("class", "node", "n", "blocks")
            .join(roots, "node", "left")
            .join(done.withColumn("done", F.lit(True)), "node", "left")
            .select("class", "node", "n", "blocks", F.coalesce("root", "node").alias("comp"), F.coalesce("done", F.lit(False)).alias("done")),
            "exact-state",
        )
        sizes = state.where("not done").groupBy("class", "comp").agg(F.sum("n").alias("m"))
        todo = materialize(
            sizes.groupBy("class").agg(F.count("*").alias("open"), F.max(F.struct("m", "comp")).alias("top"), F.sum("m").alias("m"))
            .where("open > 1").select("class", F.col("top.comp").alias("largest"), (F.col("m") - F.col("top.m")).alias("rest")),
            "exact-todo",
        )
        if not todo.head(1):
            return links
        share = F.pmod(F.xxhash64("node", F.lit(turn)), F.lit(1 << 20)) * F.col("rest") < F.lit(cap << 20)
        drawn = materialize(
            state.where("not done").join(todo, "class").where((F.col("comp") != F.col("largest")) & share).select("class", "node", "comp", "blocks").distinct(), "exact-pivots"
        )
        cap, turn = min(2 * cap, 1 << 40), turn + 1
        sent = drawn.join(rows.select("node", "shingles"), "node").select(
            "class", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)).alias("salt"), "node", "shingles", "comp", F.lit(True).alias("pivot")
        )
        held = rows.join(todo.select("class"), "class", "left_semi").join(state.select("node", "comp").distinct(), "node")
        both = held.select("class", "salt", "node", "shingles", "comp", F.lit(False).alias("pivot")).unionByName(sent)
        made = materialize(_in_blocks(both, compare), "exact-links")
        links = materialize(links.unionByName(made), "exact-links")
        done = materialize(done.unionByName(drawn.select("node")).distinct(), "exact-done")


def exact_links(sets: DataFrame, similarity: float = 0.8, block: int = BLOCK) -> DataFrame:
    """Spanning links ``(u, v)`` of the pairs of one class whose sets have at least the similarity.

    ``sets`` has class, node and shingles (sorted distinct unsigned 64-bit numbers as bytes).
    """
    filled = materialize(sets.where("length(shingles) > 0").withColumn("n", (F.length("shingles") / 8).cast("long")), "exact-sets")
    # Few classes are longer than a block: fewer than one for each BLOCK shingles.
    large = materialize(filled.groupBy("class").agg(F.ceil(F.sum("n") / block).cast("long").alias("blocks")).where("blocks > 1"), "exact-large")
    rows = filled.join(large, "class", "left").withColumn("blocks", F.coalesce("blocks", F.lit(1).cast("long")))
    rows = rows.withColumn("salt", F.pmod(F.xxhash64("node"), F.col("blocks")))

    def within(t: pa.Table):
        node = t.column("node").to_numpy()
        made = np.array(spanning_links(_sets(t), similarity), np.int64).reshape(-1, 2)
        return node[made[:, 0]], node[made[:, 1]]

    links = materialize(_in_blocks(rows.select("class", "salt", "node", "shingles"), within), "exact-links")
    if not large.head(1):
        return links
    return _across(rows.where("blocks > 1"), links, similarity, block)
