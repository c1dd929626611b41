"""Exact nearest neighbours in blocks: the full-scan baseline.

The base stands once in the shared folder; every task reads it block by block for
its chunk of queries, each pair of chunk and block is one matrix product, and
only the best ``n`` of each query leave the task.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyarrow import dataset
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from entlink.storage import discard, locate, materialize, scratch_path

BLOCK = 4096


def distances(q: np.ndarray, b: np.ndarray, metric: str) -> np.ndarray:
    if metric == "cosine":
        size = np.sqrt(np.outer((q * q).sum(1), (b * b).sum(1)))
        return np.where(size > 0, 1 - (q @ b.T) / np.where(size > 0, size, 1), 1.0)
    return np.sqrt(np.maximum(0, (q * q).sum(1)[:, None] + (b * b).sum(1)[None] - 2 * q @ b.T))


def nearest_positions(q: np.ndarray, b: np.ndarray, n: int, metric: str, digits: int | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row numbers of queries and of their best ``n`` base rows, with distances; ties go to the earlier base row."""
    d = distances(q, b, metric)
    if digits is not None:
        d = np.round(d, digits)
    n = min(n, d.shape[1])
    r, c = np.nonzero(d <= np.partition(d, n - 1, axis=1)[:, n - 1 : n])
    order = np.lexsort((c, d[r, c], r))
    r, c = r[order], c[order]
    place = np.arange(len(r)) - np.searchsorted(r, r)
    r, c = r[place < n], c[place < n]
    return r, c, d[r, c]


def _matrix(column: pa.ListArray) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(column), -1)


class Blocks:
    """A base table in the shared folder, read block by block: ``(columns without vec, vectors)``, in no fixed order."""

    def __init__(self, uri: str, grp: str, block: int):
        fs, path = locate(uri)
        self.rows = dataset.dataset(path, filesystem=fs, format="parquet")
        self.grp, self.block = grp, block

    def __iter__(self) -> Iterator[tuple[pd.DataFrame, np.ndarray]]:
        for batch in self.rows.to_batches(filter=dataset.field("grp") == self.grp, batch_size=self.block, batch_readahead=1, fragment_readahead=1, use_threads=False):
            if len(batch):
                yield batch.drop_columns(["grp", "vec"]).to_pandas(), _matrix(batch.column("vec"))


Visit = Callable[[pd.DataFrame, np.ndarray, Blocks], Iterator[pd.DataFrame]]
CELLS = 1 << 22  # distances held at once by a task


def scanned(queries: DataFrame, base: DataFrame, visit: Visit, schema: str, block: int = BLOCK, keep_all: bool = False, cells: int = CELLS) -> DataFrame:
    """What ``visit`` makes of every chunk of queries of one group and the blocks of that group's base rows.

    Both inputs have grp, id and vec.  The base is written once to the shared folder and each task reads it block by
    block, so neither side is copied for the other and no pair is stored.  With ``keep_all`` a chunk is so small that
    ``visit`` may hold its distances to the whole base.
    """
    spark = base.sparkSession
    stored = materialize(base, "scan-base")
    n, m = queries.count(), stored.groupBy("grp").count().agg(F.max("count")).first()[0] or 1
    uri, chunk = stored._scratch, max(1, cells // (m if keep_all else block))
    parts = max(1, min(math.ceil(n / 256), 4 * spark.sparkContext.defaultParallelism), math.ceil(n / 16384))

    def run(frames: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = to_arrow_schema(schema)
        for batch in frames:
            kinds = batch.column("grp").to_pandas()
            for grp in kinds.unique():
                own = np.flatnonzero((kinds == grp).to_numpy())
                blocks = Blocks(uri, grp, block)
                for at in range(0, len(own), chunk):
                    rows = batch.take(pa.array(own[at : at + chunk]))
                    for found in visit(rows.drop_columns(["grp", "vec"]).to_pandas(), _matrix(rows.column("vec")), blocks):
                        found.insert(0, "grp", grp)
                        yield pa.RecordBatch.from_pandas(found, schema=out, preserve_index=False)

    return queries.repartition(parts, "grp", "id").mapInArrow(run, schema)


def to_arrow_schema(ddl: str) -> pa.Schema:
    kinds = {"string": pa.string(), "double": pa.float64(), "bigint": pa.int64(), "long": pa.int64(), "int": pa.int32(), "smallint": pa.int16(), "tinyint": pa.int8()}
    return pa.schema([(name, kinds[kind]) for name, kind in (c.split() for c in ddl.split(", "))])


def _sortable(ids: pd.Series) -> np.ndarray:
    """Ids that numpy can sort: numbers, or strings of fixed width by code points, which is the order of their bytes."""
    return ids.to_numpy() if ids.dtype.kind in "iu" else ids.to_numpy(dtype=str)


class _Estimates:
    """Distances of queries to blocks, within ``slack`` of the true ones, and the true ones of single pairs.

    For the cosine they come of one product of unit vectors in single precision, or in another; vectors of extreme
    length, and other metrics, are compared truly at once.
    """

    def __init__(self, q: np.ndarray, metric: str, kind: type = np.float32):
        self.q, self.metric, self.kind = q, metric, kind
        self.squares, self.unit = self._units(q)

    def _units(self, v: np.ndarray) -> tuple[np.ndarray, np.ndarray | None]:
        squares = (v * v).sum(1)
        if self.metric != "cosine" or not ((squares == 0) | ((squares > 1e-100) & (squares < 1e100))).all():
            return squares, None
        return squares, (v / np.sqrt(np.where(squares > 0, squares, 1))[:, None]).astype(self.kind)

    def rows(self, at: np.ndarray) -> _Estimates:
        """Those of some queries."""
        if len(at) == len(self.q):
            return self
        out = object.__new__(_Estimates)
        out.q, out.metric, out.kind, out.squares, out.unit = self.q[at], self.metric, self.kind, self.squares[at], None if self.unit is None else self.unit[at]
        return out

    def of(self, b: np.ndarray) -> tuple[np.ndarray, float, Callable[[np.ndarray, np.ndarray], np.ndarray]]:
        squares, unit = self._units(b)
        if unit is None or self.unit is None:
            d = distances(self.q, b, self.metric)
            return d, 0.0, lambda r, c: d[r, c]

        def true(r: np.ndarray, c: np.ndarray) -> np.ndarray:
            size = np.sqrt(self.squares[r] * squares[c])
            return np.where(size > 0, 1 - np.einsum("ij,ij->i", self.q[r], b[c]) / np.where(size > 0, size, 1), 1.0)

        near = self.unit @ unit.T
        np.subtract(self.kind(1), near, out=near)
        return near, (b.shape[1] + 16) * 2.0 * float(np.finfo(self.kind).eps), true  # four times what the sums of products can be off


PAIRS = 1 << 16  # pairs compared truly at once


def _runs(sizes: np.ndarray, most: int) -> Iterator[tuple[int, int]]:
    """Runs of rows that hold ``most`` entries together, or one row of more."""
    ends, at = np.cumsum(sizes), 0
    while at < len(sizes):
        end = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + most, side="right")))
        yield at, end
        at = end


def _kept(near: np.ndarray, slack: float, limit: np.ndarray, unit: float, n: int) -> np.ndarray:
    """Pairs that estimates within ``slack`` do not rule out of the best ``n`` of a block, nor by the limits of rows so far."""

    def within(some: np.ndarray, cut: np.ndarray) -> np.ndarray:
        return some <= (np.nextafter(cut.astype(some.dtype), np.asarray(np.inf, some.dtype)) if slack else cut)[:, None]

    kept = within(near, limit + slack + unit)
    many = np.flatnonzero(np.count_nonzero(kept, axis=1) > n)
    if len(many):
        some = near if len(many) == len(near) else near[many]
        kept[many] &= within(some, np.partition(some, n - 1, axis=1)[:, n - 1] + 2 * slack + unit)
    return kept


def _first(found: list[tuple[np.ndarray, ...]], n: int) -> tuple[np.ndarray, ...]:
    """Of (row, id, distance) the ``n`` nearest of each row in order, ties by id."""
    r, i, d = (np.concatenate(x) for x in zip(*found))
    order = np.lexsort((i, d, r))
    r, i, d = r[order], i[order], d[order]
    near = np.arange(len(r)) - np.searchsorted(r, r) < n
    return r[near], i[near], d[near]


def nearest_of(n: int, metric: str, digits: int | None = None) -> Visit:
    """The best ``n`` base rows of every query, ties by id, with one block and the best so far in memory.

    Only pairs whose estimate does not rule them out are compared truly.  If a block cannot hold more than ``n`` rows,
    the best of every block come apart.
    """

    def frame(left: pd.DataFrame, r: np.ndarray, i: np.ndarray, d: np.ndarray) -> pd.DataFrame:
        return pd.DataFrame({"query_id": left.id.to_numpy()[r], "result_id": i if i.dtype.kind in "iu" else i.astype(object), "distance": d})

    def visit(left: pd.DataFrame, q: np.ndarray, blocks: Blocks) -> Iterator[pd.DataFrame]:
        best, limit, estimates = None, np.full(len(q), np.inf), _Estimates(q, metric)
        unit = 0.0 if digits is None else 10.0**-digits
        for right, b in blocks:
            ids = _sortable(right.id)
            if n >= blocks.block:
                order = np.argsort(ids, kind="stable")
                r, c, d = nearest_positions(q, b[order], n, metric, digits)
                yield frame(left, r, ids[order][c], d)
                continue
            near, slack, true = estimates.of(b)
            kept = _kept(near, slack, limit, unit, n)
            found = [] if best is None else [best]
            for a, z in _runs(np.count_nonzero(kept, axis=1), PAIRS):
                r, c = np.nonzero(kept[a:z])
                if len(r):
                    d = true(r + a, c)
                    found.append(_first([(r + a, ids[c], d if digits is None else np.round(d, digits))], n))
            if not found:
                continue
            r, i, d = best = _first(found, n)
            last = np.searchsorted(r, np.arange(len(q)), side="right") - 1
            whole = np.bincount(r, minlength=len(q)) >= n
            limit[whole] = d[last[whole]]
        if best is not None:
            yield frame(left, *best)

    return visit


CELL = 256  # base rows of a cell, about
MANY_CELLS = 4096
LEAST = 1 << 15  # base rows of a group from which cells pay
ERROR = 3e-5  # of cosines between queries and centres in single precision, with room


@dataclass(frozen=True)
class Cells:
    """Centres of a group's cells, unit vectors in an order that puts like ones together, and the cosine and sine of each cell's radius."""

    centres: np.ndarray
    cos: np.ndarray | None = None
    sin: np.ndarray | None = None

    @classmethod
    def among(cls, rows: np.ndarray) -> Cells:
        size = np.sqrt((rows * rows).sum(1))
        unit = rows[_plain(rows)] / size[_plain(rows)][:, None]
        near = unit @ unit[:64].T
        return cls(unit[np.lexsort((-near.max(1), near.argmax(1)))] if len(unit) else unit)

    def of(self, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Nearest cell of every row and the angle to its centre; rows without a proper direction are in cell -1."""
        cell, angle, plain = np.full(len(v), -1), np.full(len(v), np.pi), _plain(v)
        if len(self.centres):
            for at in np.array_split(np.flatnonzero(plain), max(1, len(v) * len(self.centres) // CELLS)):
                unit = v[at] / np.sqrt((v[at] * v[at]).sum(1))[:, None]
                cell[at] = (unit.astype(np.float32) @ self.centres.T.astype(np.float32)).argmax(1)
                angle[at] = np.arccos(np.clip((unit * self.centres[cell[at]]).sum(1), -1, 1))
        return cell, angle


def _plain(v: np.ndarray) -> np.ndarray:
    squares = (v * v).sum(1)
    return (squares > 1e-100) & (squares < 1e100)


def _with_cells(rows: DataFrame, cells: dict[str, Cells], tag: str) -> DataFrame:
    """Rows (grp, id, vec) with their cell and the angle to its centre, written in the order of cells, in small row groups."""
    spark = rows.sparkSession
    shared, kinds = spark.sparkContext.broadcast(cells), dict(rows.dtypes)
    out = pa.schema([("cell", pa.int32()), ("angle", pa.float64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            grps, cell, angle = batch.column("grp").to_pandas(), np.zeros(len(batch), np.int32), np.zeros(len(batch))
            for grp in grps.unique():
                own = np.flatnonzero((grps == grp).to_numpy())
                cell[own], angle[own] = shared.value[grp].of(_matrix(batch.column("vec").take(pa.array(own))))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(cell), pa.array(angle)], schema=pa.unify_schemas([batch.schema, out]))

    named = rows.select("grp", "id", "vec").mapInArrow(run, f"grp string, id {kinds['id']}, vec {kinds['vec']}, cell int, angle double")
    parts = 4 * spark.sparkContext.defaultParallelism
    path = scratch_path(spark, tag)
    # Cells are no key of the work: a range of rows may begin within one.
    named.repartitionByRange(parts, "grp", "cell", "id").sortWithinPartitions("grp", "cell", "id").write.option("parquet.block.size", 1 << 18).parquet(path)
    stored = spark.read.schema(named.schema).parquet(path)
    stored._scratch = path
    return stored


class Pieces:
    """The row groups of one group's base rows, each with its first and last cell."""

    def __init__(self, uri: str, grp: str):
        fs, path = locate(uri)
        self.grp, self.found = grp, []
        for fragment in dataset.dataset(path, filesystem=fs, format="parquet").get_fragments(filter=dataset.field("grp") == grp):
            for piece in fragment.split_by_row_group(dataset.field("grp") == grp):
                stats = piece.row_groups[0].statistics or {}
                same = "grp" in stats and stats["grp"]["min"] == stats["grp"]["max"]
                self.found.append((piece, stats["cell"]["min"], stats["cell"]["max"]) if same and "cell" in stats else (piece, -1, MANY_CELLS))

    def read(self, i: int) -> tuple[pd.Series, np.ndarray]:
        rows = self.found[i][0].to_table(columns=["id", "vec"], filter=dataset.field("grp") == self.grp, use_threads=False).combine_chunks()
        return rows["id"].to_pandas(), np.concatenate([_matrix(c) for c in rows["vec"].chunks if len(c)] or [np.zeros((0, 0))])


def _nearest_in_pieces(q: np.ndarray, pieces: Pieces, cells: Cells, n: int, unit: float, digits: int | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, id, distance) of the best ``n`` base rows by cosine; pieces are left out for queries whose limit no cell of theirs can meet.

    A base row is at most its cell's radius from the centre, so its angle to a query is that of the centre less the
    radius or more.
    """
    # What is left is near, often within the error of single precision, so estimates are double.
    estimates, whole = _Estimates(q, "cosine", np.float64), ~_plain(q)
    near = np.zeros((len(q), len(cells.centres)), np.float32)
    near[~whole] = (q[~whole] / np.sqrt((q[~whole] * q[~whole]).sum(1))[:, None]).astype(np.float32) @ cells.centres.T.astype(np.float32)
    mean = near.mean(0)
    like = [np.inf if lo < 0 else mean[lo : hi + 1].max() for _, lo, hi in pieces.found]
    limit, best = np.full(len(q), np.inf), None
    for i in np.argsort(-np.array(like), kind="stable"):
        _, lo, hi = pieces.found[i]
        cos = 1 - (limit + unit)  # of the angle within which a row can still be among the best
        if lo < 0:
            rows = np.arange(len(q))
        else:
            at = slice(lo, hi + 1)
            c = np.clip(cos, -1, 1)[:, None]
            wide = (cos <= 0)[:, None] | (cells.cos[at] <= 0)[None]
            meets = wide | (near[:, at] >= c * cells.cos[at] - np.sqrt(1 - c * c) * cells.sin[at] - ERROR)
            rows = np.flatnonzero(whole | meets.any(1))
        if not len(rows):
            continue
        ids, b = pieces.read(i)
        if not len(b):
            continue
        ids = _sortable(ids)
        some = estimates.rows(rows)
        about, slack, true = some.of(b)
        kept = _kept(about, slack, limit[rows], unit, n)
        found = []
        for a, z in _runs(np.count_nonzero(kept, axis=1), PAIRS):
            r, c = np.nonzero(kept[a:z])
            if len(r):
                d = true(r + a, c)
                found.append(_first([(rows[r + a], ids[c], d if digits is None else np.round(d, digits))], n))
        if not found:
            continue
        if best is None:
            best = _first(found, n)
        else:  # only the queries that met something new are ordered again
            new = np.zeros(len(q), bool)
            for r, _, _ in found:
                new[r] = True
            again = new[best[0]]
            fresh = _first([tuple(x[again] for x in best), *found], n)
            best = tuple(np.concatenate([x[~again], y]) for x, y in zip(best, fresh))
            order = np.argsort(best[0], kind="stable")
            best = tuple(x[order] for x in best)
        last = np.searchsorted(best[0], np.arange(len(q)), side="right") - 1
        full = np.bincount(best[0], minlength=len(q)) >= n
        limit[full] = best[2][last[full]]
    return best if best is not None else (np.zeros(0, int), np.zeros(0, int), np.zeros(0))


def _apart(centres: np.ndarray, radii: np.ndarray) -> bool:
    """Whether a row about a radius away from its neighbours meets fewer than half of the cells: only then do cells pay."""
    reach = np.minimum(np.pi, radii + radii.mean())
    some = centres[:: max(1, len(centres) // 256)]
    return (np.clip(some @ centres.T, -1, 1) >= np.cos(reach)).mean() < 0.5


def _cells_knn(queries: DataFrame, stored: DataFrame, n: int, digits: int | None, schema: str) -> tuple[DataFrame | None, list[str]]:
    """The groups that are large and fall into cells apart from each other, and what a scan gives for them; cells too far are left out."""
    spark = stored.sparkSession
    sizes = {r.grp: r.n for r in stored.groupBy("grp").agg(F.count("*").alias("n")).collect() if r.n >= LEAST}  # one row a group
    if not sizes:
        return None, []
    large = stored.where(F.col("grp").isin(list(sizes)))
    want = F.create_map(*[F.lit(x) for g, m in sizes.items() for x in (g, min(MANY_CELLS, max(1, m // CELL)) / m)])
    # Any rows do as centres, so a few more or less than wanted are taken by hash.
    chance = (F.xxhash64("id").cast("double") / 2.0**64 + 0.5) < want[F.col("grp")]
    at: dict[str, list] = {g: [] for g in sizes}
    for r in large.where(chance).select("grp", "vec").toLocalIterator():
        if len(at[r.grp]) < MANY_CELLS:
            at[r.grp].append(np.array(r.vec))
    cells = {g: Cells.among(np.stack(v).astype(float)) for g, v in at.items() if v}
    large = large.where(F.col("grp").isin(list(cells)))
    dealt = _with_cells(large, cells, "cells")
    radii = {g: np.full(len(c.centres), 1e-7) for g, c in cells.items()}
    for r in dealt.where("cell >= 0").groupBy("grp", "cell").agg(F.max("angle").alias("angle")).collect():  # one number a cell
        radii[r.grp][r.cell] = r.angle + 1e-7
    cells = {g: Cells(c.centres, np.cos(radii[g]), np.sin(radii[g])) for g, c in cells.items() if len(c.centres) and _apart(c.centres, radii[g])}
    if not cells:
        discard(dealt)
        return None, []
    asked = _with_cells(queries.where(F.col("grp").isin(list(cells))), cells, "cells-queries").select("grp", "id", "vec")
    shared, uri, unit = spark.sparkContext.broadcast(cells), dealt._scratch, 0.0 if digits is None else 10.0**-digits

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out, pieces = to_arrow_schema(schema), {}
        for batch in batches:
            kinds = batch.column("grp").to_pandas()
            for grp in kinds.unique():
                own = np.flatnonzero((kinds == grp).to_numpy())
                pieces.setdefault(grp, None)
                pieces[grp] = pieces[grp] or Pieces(uri, grp)
                for a in range(0, len(own), 2048):
                    rows = batch.take(pa.array(own[a : a + 2048]))
                    r, i, d = _nearest_in_pieces(_matrix(rows.column("vec")), pieces[grp], shared.value[grp], n, unit, digits)
                    ids = rows.column("id").to_pandas().to_numpy()[r]
                    found = pd.DataFrame({"grp": grp, "query_id": ids, "result_id": i if i.dtype.kind in "iu" else i.astype(object), "distance": d})
                    yield pa.RecordBatch.from_pandas(found, schema=out, preserve_index=False)

    return asked.mapInArrow(run, schema), list(cells)


def grouped_knn(queries: DataFrame, base: DataFrame, n: int = 10, metric: str = "cosine", block: int = BLOCK, digits: int | None = None, cells: bool = False) -> DataFrame:
    """``(grp, query_id, result_id, distance, rank)``: nearest base rows of the same group; inputs are (grp, id, vec).

    With ``digits`` distances are rounded before they are compared.  ``cells`` is for learned vectors, which stand in
    clusters: the same rows are found with those cells of large groups left out that are too far by their radius.
    """
    kind = dict(base.dtypes)["id"], dict(queries.dtypes)["id"]
    schema = f"grp string, query_id {kind[1]}, result_id {kind[0]}, distance double"
    # Estimates are single and need no copies, so a task holds more of them.
    scan = lambda q, b: scanned(q, b, nearest_of(n, metric, digits), schema, block, cells=2 * CELLS if metric == "cosine" and n < block else CELLS)
    if cells and metric == "cosine" and n < CELL:
        base = materialize(base.select("grp", "id", "vec"), "cells-base")
        pairs, apart = _cells_knn(queries, base, n, digits, schema)
        if pairs is not None:
            others = ~F.col("grp").isin(apart)
            pairs = pairs.unionByName(scan(queries.where(others), base.where(others)))
    else:
        pairs = None
    pairs = scan(queries, base) if pairs is None else pairs
    w = Window.partitionBy("grp", "query_id").orderBy("distance", "result_id")
    return pairs.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= n)


def exact_knn(queries: DataFrame, base: DataFrame, n: int = 10, metric: str = "cosine", block: int = BLOCK, digits: int | None = None) -> DataFrame:
    """``(query_id, result_id, distance, rank)``; inputs are (id, vec).  Ties are ordered by result id."""
    one = F.lit("all").alias("grp")
    return grouped_knn(queries.select(one, "id", "vec"), base.select(one, "id", "vec"), n, metric, block, digits).drop("grp")
