"""SimHash near-duplicates: a self-join of binary tries under a Hamming budget.

Fingerprints.  A document's words are its runs of bytes other than ASCII white
space, after folding A-Z; its shingles are runs of ``width`` words (a shorter
text is one shingle, a text without words has none and fingerprint zero).  Bit
b is set if more than half of the shingles' XXH64 hashes (seed 42) have it.

Join.  Two fingerprints that differ in at most three of 64 bits agree in one of
four 16-bit blocks.  So each distinct fingerprint goes into four tries, rotated
to put one block first, and a trie is joined with itself with no errors allowed
on that block.  That prefix is the partition key.  Below it, pairs of nodes are
walked together: both sides split by the next bit, unlike branches cost one
error, and a pair is dropped once it has spent more than the budget, or once
all its leaves are known to be in one class.  The last rule bounds the links of
a trie by its leaves, however dense a group of near copies is, and loses no
connection between them.

A trie with more than ``CROWDED`` leaves is dealt out again by its next level:
the remaining 48 bits are cut into four sub-blocks of 12, one of which must
agree too.

Similar documents.  Fingerprints of 64 bits cannot tell documents that share
four fifths of their shingles from the rest: such pairs differ in ten bits on
average.  ``similar_classes`` therefore takes 512 bits of the set of five-word
shingles, in which those pairs differ in 78 bits, give or take 8, and others in
about 250.  The same join of tries under a budget finds them, with prefixes
drawn from the bits in another order each time: the number of tries follows from
the number of documents, the similarity and the recall wanted of pairs that are
just similar enough (more similar ones are found more often).  Classes so found
are candidates: ``exact_links`` compares whole shingle sets inside each.

Defined results: null text counts as empty; null identifiers are carried but
name a class only if no other identifier does; equal texts have equal
fingerprints, so copies meet before any join; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from entlink.llm.components import connected_components
from entlink.llm.exact_links import exact_links
from entlink.llm.unions import Classes
from entlink.llm.wide_trie import FEW, bit_counts, leaf_pairs, links_in_groups, permutation, prefixes, tries_for
from entlink.storage import materialize, release_memory

SEED = 42
BUDGET = 3
BLOCKS = 4
CROWDED = 4096
FRONTIER = 1 << 13
HOT_SHARE = 1000


def fingerprint(text: str | None, width: int = 3) -> int:
    """The 64-bit SimHash of one whole text."""
    words = (text or "").encode("utf-8").lower().split()  # bytes: folds A-Z, splits at ASCII white space
    if not words:
        return 0
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    n = max(1, len(words) - width + 1)
    starts = np.concatenate(([0], ends[: n - 1] + 1)).tolist()
    stops = ends[len(words) - n :].tolist()
    digest = xxhash.xxh64_digest
    ones = np.zeros(64, np.int64)
    for at in range(0, n, 1 << 15):
        hashes = b"".join([digest(joined[s:e], SEED) for s, e in zip(starts[at : at + (1 << 15)], stops[at : at + (1 << 15)])])
        bits = np.unpackbits(np.frombuffer(hashes, np.uint8).reshape(-1, 8), axis=1)
        ones += bits.sum(axis=0, dtype=np.int32)
    return int.from_bytes(np.packbits(ones * 2 > n).tobytes(), "big")


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 3) -> DataFrame:
    """``(id, fp)``, the fingerprint as a signed long."""

    def run(batches):
        for b in batches:
            fps = np.fromiter((fingerprint(t, width) for t in b.column(1).to_pylist()), np.uint64, b.num_rows)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps.view(np.int64))], ["id", "fp"])
        release_memory()

    slim = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    return slim.mapInArrow(run, "id long, fp long")


def trie_links(keys: np.ndarray, depth: int, budget: int = BUDGET) -> list[tuple[int, int]]:
    """Spanning links between positions of ``keys`` (sorted, distinct, 64 bits) at most ``budget`` bits apart,
    among keys whose first ``depth`` bits agree."""
    n = len(keys)
    if n < 2:
        return []
    classes, links = Classes(n), []
    head = keys >> np.uint64(64 - depth) if depth else np.zeros(n, np.uint64)
    cut = np.flatnonzero(np.concatenate(([True], head[1:] != head[:-1], [True])))
    lo, hi = cut[:-1], cut[1:]
    lo, hi = lo[hi - lo > 1], hi[hi - lo > 1]
    # Blocks of node pairs: the ranges of leaves below each, the depth of both nodes, the errors spent.
    stack = [(lo[i : i + FRONTIER], hi[i : i + FRONTIER], lo[i : i + FRONTIER], hi[i : i + FRONTIER], depth, np.zeros(len(lo[i : i + FRONTIER]), np.int8)) for i in range(0, len(lo), FRONTIER)]
    while stack:
        alo, ahi, blo, bhi, d, err = stack.pop()
        open_ = ~classes.one_class(alo, ahi, blo, bhi)
        alo, ahi, blo, bhi, err = alo[open_], ahi[open_], blo[open_], bhi[open_], err[open_]
        few = (ahi - alo) * (bhi - blo) <= FEW
        if few.any():
            a, b = leaf_pairs(alo[few], ahi[few], blo[few], bhi[few])
            near = np.bitwise_count(keys[a] ^ keys[b]) <= budget
            near &= classes.root[a] != classes.root[b]
            links += classes.link(a[near], b[near])
            alo, ahi, blo, bhi, err = alo[~few], ahi[~few], blo[~few], bhi[~few], err[~few]
        if not len(alo) or d == 64:
            continue
        amid, bmid = _split(keys, alo, ahi, d), _split(keys, blo, bhi, d)
        own = (alo == blo) & (ahi == bhi)
        cross = err < budget
        sides = [
            (alo[cross], amid[cross], bmid[cross], bhi[cross], err[cross] + 1),
            (amid[cross & ~own], ahi[cross & ~own], blo[cross & ~own], bmid[cross & ~own], err[cross & ~own] + 1),
            (amid, ahi, bmid, bhi, err),
            (alo, amid, blo, bmid, err),
        ]
        # One block for all four, so that blocks stay long; like branches stand last and are walked first.
        al, ah, bl, bh, e = (np.concatenate(c) for c in zip(*sides))
        k = np.flatnonzero((al < ah) & (bl < bh) & ~((al == bl) & (ah == bh) & (ah - al == 1)))
        for i in range(0, len(k), FRONTIER):
            j = k[i : i + FRONTIER]
            stack.append((al[j], ah[j], bl[j], bh[j], d + 1, e[j].astype(np.int8)))
    return links


def _split(keys: np.ndarray, lo: np.ndarray, hi: np.ndarray, d: int) -> np.ndarray:
    """Where bit ``d`` turns to one in each sorted range whose first ``d`` bits agree."""
    bit = np.uint64(1) << np.uint64(63 - d)
    base = keys[lo] & ~((bit << np.uint64(1)) - np.uint64(1)) if d else np.zeros(len(lo), np.uint64)
    return np.clip(np.searchsorted(keys, base | bit), lo, hi)


def _rotated(fp: Column, block: int) -> Column:
    """The fingerprint with its ``block``-th 16 bits first."""
    r = 16 * block
    return fp if not r else F.shiftleft(fp, r).bitwiseOR(F.shiftrightunsigned(fp, 64 - r))


def _deeper(key: Column, sub: int) -> Column:
    """A rotated fingerprint with 12 of its last 48 bits moved up behind the first block."""
    low = (1 << 48) - 1
    r = 12 * sub
    tail = key.bitwiseAND(low)
    turned = tail if not r else F.shiftleft(tail, r).bitwiseOR(F.shiftrightunsigned(tail, 48 - r)).bitwiseAND(low)
    return key.bitwiseAND(F.lit(~low)).bitwiseOR(turned)


def near_links(distinct: DataFrame, crowded: int = CROWDED) -> DataFrame:
    """Spanning links ``(u, v)`` between the distinct fingerprints of column ``fp``."""
    tries = distinct.select(
        "fp", F.posexplode(F.array(*[_rotated(F.col("fp"), b) for b in range(BLOCKS)])).alias("block", "key")
    ).withColumn("head", F.shiftrightunsigned("key", 48))
    # At most 4 * 2**16 groups exist, so this table has a fixed bound.
    full = tries.groupBy("block", "head").agg(F.count("*").alias("n")).where(F.col("n") > crowded).select("block", "head", F.lit(True).alias("full"))
    levels = (
        tries.join(F.broadcast(full), ["block", "head"], "left")
        .select(
            "fp",
            "block",
            F.posexplode(
                F.when(F.col("full"), F.array(*[_deeper(F.col("key"), s) for s in range(4)])).otherwise(F.array("key"))
            ).alias("sub", "key"),
            F.when(F.col("full"), F.lit(28)).otherwise(F.lit(16)).alias("depth"),
        )
        .withColumn("head", F.shiftrightunsigned("key", 36))
        .withColumn("head", F.when(F.col("depth") == 16, F.shiftrightunsigned("head", 12)).otherwise(F.col("head")))
    )

    def join(batches):
        got = [b for b in batches if b.num_rows]
        if not got:
            return
        t = pa.Table.from_batches(got)
        fp, key = (t.column(c).to_numpy().view(np.uint64) for c in ("fp", "key"))
        kind = t.column("kind").to_numpy()
        for k in np.unique(kind):
            own = kind == k
            f, q = fp[own], key[own]
            order = np.argsort(q, kind="stable")
            f, q = f[order].view(np.int64), q[order]
            made = trie_links(q, 28 if k >= 64 else 16)
            if made:
                a, b = np.array(made).T
                yield pa.RecordBatch.from_arrays([pa.array(f[a]), pa.array(f[b])], ["u", "v"])

    kind = F.when(F.col("depth") == 28, 64 + F.col("block") * 4 + F.col("sub")).otherwise(F.col("block"))
    keyed = levels.select("fp", "key", kind.cast("int").alias("kind"), "head")
    parts = int(distinct.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return keyed.repartition(parts, "kind", "head").select("fp", "key", "kind").mapInArrow(join, "u long, v long")


def _by_row(prints: DataFrame, every: DataFrame, id_col: str) -> DataFrame:
    """Class of every row of ``prints`` (id, fp); ``every`` has fp, copies and component_id once for each fingerprint."""
    # A fingerprint of more than one in HOT_SHARE rows would load one task; there are fewer than HOT_SHARE of them.
    total = every.agg(F.sum("copies").alias("total"))
    hot = every.join(F.broadcast(total), F.col("copies") * HOT_SHARE > F.col("total")).select("fp", "component_id")
    rows = prints.join(F.broadcast(hot), "fp").unionByName(
        prints.join(F.broadcast(hot), "fp", "left_anti").join(every.select("fp", "component_id"), "fp")
    )
    return rows.select(F.col("id").alias(id_col), "fp", "component_id")


def near_duplicate_classes(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 3
) -> DataFrame:
    """One row per document: id, ``fp`` (signed long) and ``component_id``, the least id of its class."""
    prints = materialize(fingerprints(docs, id_col, text_col, width), "simhash")
    distinct = materialize(prints.groupBy("fp").agg(F.min("id").alias("least"), F.count("*").alias("copies")), "simhash-distinct")
    roots = materialize(connected_components(materialize(near_links(distinct), "simhash-links")), "simhash-roots")
    linked = roots.withColumnRenamed("node", "fp").join(distinct, "fp")
    named = linked.groupBy("root").agg(F.min("least").alias("class"))
    classes = linked.join(named, "root").select("fp", "class")
    every = distinct.join(classes, "fp", "left").select("fp", "copies", F.coalesce("class", "least").alias("component_id"))
    return _by_row(prints, materialize(every, "simhash-classes"), id_col)


WIDE_WORDS = 8
AT_ONCE = 1 << 14  # shingles whose 512 bits are held at a time
_MIX = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB)]


def shingle_set(text: str | None, width: int = 5) -> np.ndarray:
    """The sorted 64-bit hashes of a text's distinct shingles; empty if it has no words."""
    words = (text or "").encode("utf-8").lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    one = np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))
    n = max(1, len(words) - width + 1)
    shingles = np.zeros(n, np.uint64)
    for k in range(min(width, len(words))):
        shingles = (shingles ^ (shingles >> np.uint64(29))) * _MIX[0] + one[k : k + n]
    return np.unique(shingles)


def wide_fingerprint(text: str | None, width: int = 5) -> bytes:
    """The SimHash of 512 bits of the set of a text's shingles; 64 zero bytes if it has no words."""
    shingles = shingle_set(text, width)
    if not len(shingles):
        return bytes(8 * WIDE_WORDS)
    counts = np.zeros(64 * WIDE_WORDS, np.int64)
    for at in range(0, len(shingles), AT_ONCE):
        wide = shingles[at : at + AT_ONCE, None] + _MIX[0] * np.arange(1, WIDE_WORDS + 1, dtype=np.uint64)
        for shift, factor in ((30, _MIX[1]), (27, _MIX[2])):
            wide ^= wide >> np.uint64(shift)
            wide *= factor
        wide ^= wide >> np.uint64(31)
        counts += bit_counts(wide)
    return np.packbits(counts * 2 > len(shingles)).tobytes()


def wide_fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5) -> DataFrame:
    """``(id, fp)``, the fingerprint as 64 bytes."""

    def run(batches):
        for b in batches:
            fps = [wide_fingerprint(t, width) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps, pa.binary())], ["id", "fp"])
        release_memory()

    slim = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    return slim.mapInArrow(run, "id long, fp binary")


def _spread(nodes: DataFrame, bits: int, tries: int, salt: int) -> DataFrame:
    """``(grp, node, fp)``: each row of (grp, node, fp) once for every trie, under the hash of its group, the trie and the prefix."""

    def run(batches):
        orders = [permutation(64 * WIDE_WORDS, salt + t) for t in range(tries)]
        for b in batches:
            for at in range(0, b.num_rows, 2048):
                part = b.slice(at, 2048)
                raw = np.frombuffer(b"".join(part.column("fp").to_pylist()), np.uint8).reshape(part.num_rows, -1)
                flat = np.unpackbits(raw, axis=1)
                held = part.column("grp").to_numpy().view(np.uint64)
                for t, order in enumerate(orders):
                    head = prefixes(flat, order, bits)
                    grp = (held ^ ((head << np.uint64(8)) + np.uint64(t) + np.uint64(salt << 56))) * _MIX[1]
                    grp = (grp ^ (grp >> np.uint64(32))) * _MIX[2]
                    yield pa.RecordBatch.from_arrays([pa.array(grp.view(np.int64)), part.column("node"), part.column("fp")], ["grp", "node", "fp"])

    return nodes.select("grp", "node", "fp").mapInArrow(run, "grp long, node long, fp binary")


def similar_links(distinct: DataFrame, similarity: float = 0.8, recall: float = 0.95, crowded: int = CROWDED) -> DataFrame:
    """Spanning links ``(u, v)`` between the nodes of ``distinct`` (node, fp) whose shingle sets are similar by their fingerprints.

    Groups of more than ``crowded`` rows are dealt out again by prefixes of other bits, so no task holds a family of near copies whole.
    """
    n = distinct.count()
    bits, tries, budget = tries_for(n, 64 * WIDE_WORDS, similarity, recall)
    first = materialize(_spread(distinct.select(F.lit(0).cast("long").alias("grp"), "node", "fp"), bits, tries, 1), "similar-tries")
    full = materialize(first.groupBy("grp").agg(F.count("*").alias("n")).where(F.col("n") > crowded).select("grp"), "similar-full")
    parts = int(distinct.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def join(batches):
        got = [b for b in batches if b.num_rows]
        if got:
            t = pa.Table.from_batches(got)
            raw = np.frombuffer(b"".join(t.column("fp").to_pylist()), np.uint8).reshape(t.num_rows, -1)
            node = t.column("node").to_numpy()
            made = links_in_groups(t.column("grp").to_numpy(), raw, budget)
            if made:
                a, b = np.array(made).T
                yield pa.RecordBatch.from_arrays([pa.array(node[a]), pa.array(node[b])], ["u", "v"])
            del got, t, raw, made
        release_memory()

    calm, busy = first, None
    if full.head(1):
        busy = first.join(full, "grp", "left_semi")
        calm = first.join(full, "grp", "left_anti")
        more, again, _ = tries_for(1 << 14, 64 * WIDE_WORDS, similarity, recall)
        calm = calm.unionByName(_spread(busy, more, again, 2))
    return calm.repartition(parts, "grp").mapInArrow(join, "u long, v long")


def shingle_sets(members: DataFrame, width: int = 5) -> DataFrame:
    """``(class, node, shingles)`` of rows (class, node, text): the whole set of each as bytes."""

    def run(batches):
        for b in batches:
            sets = [shingle_set(t, width).tobytes() for t in b.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("class"), b.column("node"), pa.array(sets, pa.binary())], ["class", "node", "shingles"])
        release_memory()

    return members.select("class", "node", "text").mapInArrow(run, "class long, node long, shingles binary")


def similar_classes(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, similarity: float = 0.8, recall: float = 0.95
) -> DataFrame:
    """One row per document: id, ``fp`` (64 bytes) and ``component_id``, the least id of its class of similar documents.

    Documents are of one class if pairs of at least the similarity connect them: fingerprints find candidate classes,
    and inside these whole sets of shingles are compared.  A class has no name where no row has an identifier.
    """
    prints = materialize(wide_fingerprints(docs, id_col, text_col, width), "similar")
    distinct = materialize(prints.groupBy("fp").agg(F.min("id").alias("node"), F.count("*").alias("copies")), "similar-distinct")
    links = materialize(similar_links(distinct.where("node is not null"), similarity, recall), "similar-links")
    met = materialize(connected_components(links), "similar-met").withColumnRenamed("root", "class")
    texts = docs.select(F.col(id_col).cast("long").alias("node"), F.col(text_col).alias("text"))
    checked = exact_links(shingle_sets(texts.join(met, "node"), width), similarity)
    roots = materialize(connected_components(checked), "similar-roots")
    every = distinct.join(roots, "node", "left").select("fp", "copies", F.coalesce("root", "node").alias("component_id"))
    return _by_row(prints, materialize(every, "similar-classes"), id_col)
