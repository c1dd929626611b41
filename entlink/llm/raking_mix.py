"""Mixing by iterative proportional fitting.

Documents fall into cells of source, language and topic.  Raking scales the
cells' token totals in turn to the target shares of each dimension until all
three marginals hold, and a document's chance of being drawn is the budget's
share of its cell over the cell's tokens.  No cell gives more tokens than it
has: the drawn shares are raked again under that bound, so what a full cell
cannot give comes from cells of the same source, language and topic, and the
drawn tokens hold the targets too.  A category asked for more than all its
tokens gives all, and the others grow in proportion.  Targets that cannot hold
are reported by a ``RakingWarning`` with the residual.

Draws.  Within a cell documents stand in order of length, ties by hash of
what they hold and the seed, and a document is drawn where the sum of the chances
up to it passes the next whole number after the cell's random start.  So each
document is drawn with its chance, a cell gives its number of documents to the
nearest whole, and its drawn tokens differ from the expected ones by less than
its longest document.  Nothing depends on how rows are dealt out.

Topics are ``TOPICS`` clusters of the documents' words: square roots of hashed
word counts, less the corpus mean, at unit length, clustered by ``ROUNDS`` of
spherical k-means over all documents from starts that are far apart in a sample
of ``STARTS``.  Vectors are whole numbers, so sums and clusters are the same on
any cluster.  Tokens are words.

Targets default to tempered shares (``share ** TEMPERATURE``, normalised), which
lift small categories; explicit shares per category may be given (``None`` is
the key of null), categories that they leave out get share zero.

Raking runs over the cell table in one task; its size follows the categories
that occur together, not the documents.  Only the last error, and the sums of
``TOPICS`` clusters, reach the driver.

Defined results: null source or language is a category of its own, apart from
the empty string; a null text counts as empty; an empty text has weight one
token so that it can be drawn; rows equal in identifier, text, source and
language are drawn alike, as one unit; an empty table gives an empty table; columns of the input
cannot clash with ours.
"""

from __future__ import annotations

import warnings
import zlib
from collections.abc import Iterator, Mapping

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from entlink.operators.ordering import ranked
from entlink.storage import materialize, release_memory

TOPICS = 8
TEMPERATURE = 0.5
SWEEPS, TOLERANCE = 20_000, 1e-6
DRAWN_TOLERANCE = 1e-4
STALLED = 200  # sweeps at least before targets may be called contradictory
DIMS = ("source", "lang", "topic")
FEW_CELLS = 100_000  # rows of four numbers and three names


class RakingWarning(UserWarning):
    """Targets that the table cannot meet."""


#: Hashed words of a topic vector, its length in whole numbers, rounds of clustering and rows that starts are chosen from.
DIM, UNIT, ROUNDS, STARTS = 128, 1000, 4, 512


def word_vector(text: str | None) -> tuple[int, np.ndarray]:
    """Number of words, and square roots of their counts by hash at length ``UNIT``, of one whole text."""
    words = (text or "").encode("utf-8").lower().split()
    if not words:
        return 0, np.zeros(DIM, np.int16)
    counts = np.sqrt(np.bincount(np.fromiter(map(zlib.crc32, words), np.int64, len(words)) % DIM, minlength=DIM))
    return len(words), np.rint(counts * (UNIT / np.linalg.norm(counts))).astype(np.int16)


def _category(column: str) -> Column:
    """A category as a string that is never null: empty for null, else the value behind a mark."""
    return F.coalesce(F.concat(F.lit("="), F.col(column).cast("string")), F.lit(""))


def _key(id_col: str, text_col: str, source_col: str, lang_col: str) -> Column:
    """Rows with the same key are one unit."""
    return F.xxhash64(id_col, text_col, _category(source_col), _category(lang_col))


def _marked(targets: Mapping[str, Mapping | None] | None) -> dict:
    """Targets by the strings of ``_category``."""
    mark = lambda d, k: str(k) if d == "topic" else "" if k is None else f"={k}"
    return {d: shares and {mark(d, k): v for k, v in shares.items()} for d, shares in (targets or {}).items()}


def _shown(category: str) -> Column:
    return F.when(F.col(category) != "", F.substring(F.col(category), F.lit(2), F.length(category))).alias(category)


def _vectors(docs: DataFrame, id_col: str, text_col: str, source_col: str, lang_col: str) -> DataFrame:
    @F.pandas_udf("tokens long, vec binary")
    def run(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        for texts in batches:
            rows = [word_vector(t) for t in texts]
            yield pd.DataFrame({"tokens": [n for n, _ in rows], "vec": [v.tobytes() for _, v in rows]})
        release_memory()

    slim = docs.select(F.col(id_col).alias("id"), _key(id_col, text_col, source_col, lang_col).alias("key"), _category(source_col).alias("source"), _category(lang_col).alias("lang"), run(F.col(text_col)).alias("t"))
    return slim.select("id", "key", "source", "lang", F.greatest(F.col("t.tokens"), F.lit(1)).alias("tokens"), F.col("t.vec").alias("vec"))


def _matrix(column: pa.Array) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.int16).reshape(len(column), DIM)


def _nearest(x: np.ndarray, mean: np.ndarray, centres: np.ndarray) -> np.ndarray:
    """Cluster of each vector; a vector's own length does not matter, and ties go to the least cluster."""
    return (np.round((x - mean) @ centres.T, 6)).argmax(axis=1)


def _unit(x: np.ndarray) -> np.ndarray:
    return x / np.maximum(1e-9, np.linalg.norm(x, axis=-1, keepdims=True))


def topic_centres(known: DataFrame, topics: int = TOPICS, rounds: int = ROUNDS) -> tuple[np.ndarray, np.ndarray]:
    """Corpus mean and cluster centres of the vectors of ``known`` (key, vec); every round reads all of them."""

    def sums(centres):
        shared = known.sparkSession.sparkContext.broadcast(centres)

        def run(batches):
            total, n = np.zeros((topics, DIM), np.int64), np.zeros(topics, np.int64)
            for b in batches:
                x = _matrix(b.column(0))
                own = _nearest(x, *shared.value) if shared.value is not None else np.zeros(len(x), np.int64)
                which = (own[:, None] == np.arange(topics)).astype(float)
                total += np.rint(which.T @ x).astype(np.int64)  # exact: whole numbers far below 2**53
                n += np.bincount(own, minlength=topics)
            yield pa.RecordBatch.from_arrays([pa.array(range(topics)), pa.array(n), pa.array(total.tolist())], ["topic", "n", "total"])

        parts = known.select("vec").mapInArrow(run, "topic long, n long, total array<long>")
        cells = parts.select("topic", "n", F.posexplode("total").alias("i", "v")).groupBy("topic", "i").agg(F.sum("n").alias("n"), F.sum("v").alias("v"))
        total, n = np.zeros((topics, DIM)), np.zeros(topics)
        for r in cells.collect():  # topics * DIM rows
            total[r.topic, r.i], n[r.topic] = r.v, r.n
        return total, n

    total, n = sums(None)
    mean = total[0] / max(1.0, n[0])
    sample = known.select("key", "vec").orderBy(F.xxhash64("key"), "key").limit(STARTS).collect()
    if not sample:
        return mean, np.zeros((topics, DIM))
    x = _unit(np.array([np.frombuffer(r.vec, np.int16) for r in sample]) - mean)
    starts = [0]
    while len(starts) < topics:  # the vector least like those chosen so far
        starts.append(int(np.round((x @ x[starts].T).max(axis=1), 9).argmin()))
    centres = x[starts]
    for _ in range(rounds):
        total, n = sums((mean, centres))
        moved = _unit(total - n[:, None] * mean)
        centres = np.where((n > 0)[:, None], moved, centres)
    return mean, centres


def described(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", lang_col: str = "lang") -> DataFrame:
    """``(id, key, source, lang, topic, tokens)`` of every document, written once."""
    known = materialize(_vectors(docs, id_col, text_col, source_col, lang_col), "mix-vectors")
    shared = docs.sparkSession.sparkContext.broadcast(topic_centres(known))

    def run(batches):
        for b in batches:
            topic = pa.array(_nearest(_matrix(b.column(5)), *shared.value)).cast(pa.string())
            yield pa.RecordBatch.from_arrays([*b.columns[:4], topic, b.column(4)], ["id", "key", "source", "lang", "topic", "tokens"])

    kind = known.schema["id"].dataType.simpleString()
    out = known.select("id", "key", "source", "lang", "tokens", "vec").mapInArrow(run, f"id {kind}, key long, source string, lang string, topic string, tokens long")
    return materialize(out, "mix-docs")


def target_shares(cells: DataFrame, dim: str, shares: Mapping[str, float] | None, temperature: float = TEMPERATURE) -> DataFrame:
    """``(dim, goal)`` with goals that sum to one."""
    spark = cells.sparkSession
    own = cells.groupBy(dim).agg(F.sum("tokens").alias("n"))
    if shares is not None:
        given = spark.createDataFrame([(str(k), float(v)) for k, v in shares.items()], f"{dim} string, raw double")
        goal = own.join(given, dim, "left").select(dim, F.coalesce("raw", F.lit(0.0)).alias("raw"))
    else:
        goal = own.select(dim, F.pow(F.col("n").cast("double"), F.lit(temperature)).alias("raw"))
    total = goal.agg(F.sum("raw").alias("total"))
    return goal.crossJoin(F.broadcast(total)).select(dim, (F.col("raw") / F.col("total")).alias("goal"))  # total has one row


def rake(cells: DataFrame, targets: Mapping[str, Mapping[str, float] | None] | None = None, temperature: float = TEMPERATURE,
         sweeps: int = SWEEPS, tolerance: float = TOLERANCE) -> DataFrame:
    """Cells with ``share``: fitted shares whose sums along each dimension equal the targets."""
    return _fitted(cells, _goals(cells, targets, temperature), sweeps, tolerance)


def _goals(cells: DataFrame, targets: Mapping[str, Mapping[str, float] | None] | None, temperature: float) -> dict[str, DataFrame]:
    targets = targets or {}
    return {d: materialize(target_shares(cells, d, targets.get(d), temperature), "rake-goal") for d in DIMS}


def _fitted(cells: DataFrame, goals: Mapping[str, DataFrame], sweeps: int, tolerance: float) -> DataFrame:
    total = cells.agg(F.sum("tokens").alias("all")).first()["all"]
    start = cells.withColumn("share", F.col("tokens") / F.lit(float(total or 1))).withColumn("cap", F.lit(float("inf")))
    fitted, off = _swept(start, goals, sweeps, tolerance)
    if off > tolerance:
        warnings.warn(f"raking stopped {off:.2g} (relative) off its targets", RakingWarning, stacklevel=3)
    return fitted.drop("cap")


def _swept(start: DataFrame, goals: Mapping[str, DataFrame], sweeps: int, tolerance: float) -> tuple[DataFrame, float]:
    """Sweep until the sums of min(share, cap) are within ``tolerance`` of the goals; also the last relative error.

    The sweeps run over the cell table in one task: a row for each source, language and topic that occur together.
    """
    wide = start
    for d in DIMS:
        wide = wide.join(goals[d].withColumnRenamed("goal", f"g_{d}"), d)

    def run(batches):
        got = [b for b in batches if len(b)]
        if got:
            cells = pd.concat(got, ignore_index=True)
            codes, wanted = [], []
            for d in DIMS:
                code, _ = pd.factorize(cells[d])
                codes.append(code)
                wanted.append(cells[f"g_{d}"].to_numpy()[np.unique(code, return_index=True)[1]])
            share, off = sweep(codes, wanted, cells["share"].to_numpy(), cells["cap"].to_numpy(), sweeps, tolerance)
            yield cells[[*DIMS, "tokens", "cap"]].assign(share=share, off=off)

    done = wide.repartition(1).mapInPandas(run, "source string, lang string, topic string, tokens long, cap double, share double, off double")
    done = materialize(done, "rake")
    return done.drop("off"), float(done.agg(F.max("off").alias("off")).first()["off"] or 0.0)


def sweep(codes: list[np.ndarray], goals: list[np.ndarray], share: np.ndarray, cap: np.ndarray, sweeps: int, tolerance: float) -> tuple[np.ndarray, float]:
    """Scaled shares and the largest relative error of the last sweep; gives up once half the sweeps brought next to nothing."""
    past = []
    for _ in range(sweeps):
        worst = 0.0
        for code, goal in zip(codes, goals):
            full = share >= cap
            free = np.bincount(code, np.where(full, 0.0, share), len(goal))
            fixed = np.bincount(code, np.where(full, cap, 0.0), len(goal))
            has = free + fixed
            asked = goal > 0
            if asked.any():
                worst = max(worst, float(np.abs(has[asked] / goal[asked] - 1).max()))
            factor = np.ones(len(goal))
            less = (goal <= fixed) & (has > 0)
            more = (goal > fixed) & (free > 0)
            factor[less] = goal[less] / has[less]
            factor[more] = (goal[more] - fixed[more]) / free[more]
            factor[has <= 0] = 0.0
            # The bound keeps shares far beyond their cap from growing without end.
            share = np.minimum(share * factor[code], cap * 1e6)
        past.append(worst)
        if worst <= tolerance or len(past) > STALLED and worst > 0.9 * past[len(past) // 2]:
            break
    return share, past[-1]


def drawn_shares(fitted: DataFrame, goals: Mapping[str, DataFrame], budget: float) -> DataFrame:
    """``fitted`` with shares that no cell's tokens bound any more: those of the tokens to be drawn."""
    total = float(fitted.agg(F.sum("tokens").alias("n")).first()["n"] or 0)
    want = budget * total
    bounded = {}
    for d in DIMS:
        own = materialize(fitted.groupBy(d).agg(F.sum("tokens").alias("tokens")).join(goals[d], d).withColumnRenamed("goal", "share"), "rake-bounded")
        scale = _scale(own, want)
        bounded[d] = materialize(own.select(d, (F.least(F.col("tokens"), F.col("share") * scale) / F.lit(want or 1.0)).alias("goal")), "rake-goal")
    raked, _ = _swept(fitted.withColumn("cap", F.col("tokens") / F.lit(want or 1.0)), bounded, SWEEPS, DRAWN_TOLERANCE)
    given = raked.withColumn("share", F.least("share", "cap")).drop("cap")
    drawn = given.agg(F.sum("share").alias("s")).first()["s"] or 1.0
    return given.withColumn("share", F.col("share") / F.lit(drawn))


def drawn_marginals(cells: DataFrame, goals: Mapping[str, DataFrame]) -> DataFrame:
    """``(dim, category, goal, drawn)`` of cells with tokens and chance: target and expected shares of the drawn tokens."""
    parts = []
    for d in DIMS:
        own = cells.groupBy(d).agg(F.sum(F.col("tokens") * F.col("chance")).alias("n"))
        all_ = cells.agg(F.sum(F.col("tokens") * F.col("chance")).alias("all"))
        parts.append(own.join(goals[d], d).crossJoin(F.broadcast(all_)).select(F.lit(d).alias("dim"), F.col(d).alias("category"), "goal", (F.col("n") / F.col("all")).alias("drawn")))
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


def _scale(fitted: DataFrame, want: float) -> float:
    """The scale at which min(tokens, scale * share) sums to ``want``, by fixing rows in rounds that each keep at least one more."""
    scale = want
    while True:
        full = F.col("share") * scale >= F.col("tokens")
        row = fitted.agg(F.sum(F.when(full, F.col("tokens"))).alias("spent"), F.sum(F.when(~full, F.col("share"))).alias("left")).first()
        left, spent = row["left"] or 0.0, float(row["spent"] or 0)
        grown = (want - spent) / left if left > 0 and want > spent else scale
        if grown <= scale * (1 + 1e-9):
            return scale
        scale = grown


def chances(fitted: DataFrame, budget: float) -> DataFrame:
    """Cells with ``weight`` (fitted over own share) and ``chance``; ``budget`` is a share of all tokens.

    The chance is min(1, scale * share / tokens); the scale is such that expected tokens meet the budget,
    found by fixing cells at one in rounds that each keep at least one more.
    """
    total = float(fitted.agg(F.sum("tokens").alias("n")).first()["n"] or 0)
    scale = _scale(fitted, budget * total)
    return fitted.select(
        *DIMS,
        (F.col("share") * total / F.col("tokens")).alias("weight"),
        F.least(F.lit(1.0), F.col("share") * scale / F.col("tokens")).alias("chance"),
    )


def _beside(rows: DataFrame, cells: DataFrame) -> DataFrame:
    """Rows with the columns of their cell; up to ``FEW_CELLS`` cells are broadcast, so a large cell's rows stay where they are."""
    return rows.join(F.broadcast(cells) if cells.count() <= FEW_CELLS else cells, list(DIMS))


def drawn_units(known: DataFrame, cells: DataFrame, seed: int) -> DataFrame:
    """``(key, selected)`` once for each identifier and text: draws at even steps along each cell, shortest first."""
    units = known.groupBy("key", *DIMS).agg(F.sum("tokens").alias("tokens")).withColumn("draw", F.xxhash64(F.lit(seed), "key"))
    placed, _ = ranked(units, [*DIMS, "tokens", "draw", "key"], "rank", "mix-order")
    first = placed.groupBy(*DIMS).agg(F.min("rank").alias("first"))
    start = F.shiftrightunsigned(F.xxhash64(F.lit(seed), *DIMS), 11) / float(1 << 53)
    chance = materialize(cells.join(first, list(DIMS)).select(*DIMS, "first", "chance", start.alias("start")), "mix-steps")
    along = lambda r: F.floor(F.col("start") + r * F.col("chance") + 1e-9)
    at = F.col("rank") - F.col("first")
    return _beside(placed, chance).select("key", (along(at + 1) > along(at)).alias("selected"))


def cell_chances(known: DataFrame, budget: float, targets=None, temperature: float = TEMPERATURE) -> DataFrame:
    cells = materialize(known.groupBy(*DIMS).agg(F.sum("tokens").alias("tokens")), "rake-cells")
    goals = _goals(cells, targets, temperature)
    fitted = materialize(_fitted(cells, goals, SWEEPS, TOLERANCE), "rake-fitted")
    drawn = chances(materialize(drawn_shares(fitted, goals, budget), "rake-drawn"), budget).select(*DIMS, "chance")
    total = fitted.agg(F.sum("tokens").alias("all"))
    weighted = fitted.crossJoin(F.broadcast(total)).select(*DIMS, "tokens", (F.col("share") * F.col("all") / F.col("tokens")).alias("weight"))
    out = materialize(weighted.join(drawn, list(DIMS)), "rake-chances")
    off = drawn_marginals(out, goals).groupBy("dim").agg(F.max(F.abs(F.col("goal") - F.col("drawn"))).alias("off")).where(F.col("off") > DRAWN_TOLERANCE).collect()
    if off:
        worst = ", ".join(f"{r['dim']} {r['off']:.2g}" for r in sorted(off))
        warnings.warn(f"at a budget of {budget} the drawn shares miss their targets by up to: {worst}", RakingWarning, stacklevel=2)
    return out.drop("tokens")


def mixture(docs: DataFrame, budget: float = 0.5, targets=None, temperature: float = TEMPERATURE, seed: int = 7,
            id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: id, source, lang, topic, tokens, weight, chance and whether it is drawn."""
    known = described(docs, id_col, text_col)
    cells = cell_chances(known, budget, _marked(targets), temperature)
    drawn = materialize(drawn_units(known, cells, seed), "mix-drawn")
    out = _beside(known, cells).join(drawn, "key")
    return out.select(F.col("id").alias(id_col), _shown("source"), _shown("lang"), "topic", "tokens", "weight", "chance", "selected")


def sampled(docs: DataFrame, budget: float = 0.5, targets=None, temperature: float = TEMPERATURE, seed: int = 7,
            id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", lang_col: str = "lang") -> DataFrame:
    """The drawn documents, whole, with the columns of the input."""
    known = described(docs, id_col, text_col, source_col, lang_col)
    drawn = drawn_units(known, cell_chances(known, budget, _marked(targets), temperature), seed)
    left = materialize(drawn.where("not selected").select(F.col("key").alias("_key")), "mix-left")
    rows = docs.select(F.struct("*").alias("row"), _key(id_col, text_col, source_col, lang_col).alias("_key"))
    return rows.join(left, "_key", "left_anti").select("row.*")
