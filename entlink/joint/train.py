"""Training of one joint space per entity type, types in parallel."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, replace
from functools import lru_cache, reduce
from operator import and_

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.fs as pafs
from pyarrow import dataset
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from entlink.functions.text import hashed_bag, python_tokens
from entlink.joint.registry import ENCODERS, TOWERS, register_encoder, register_tower
from entlink.joint.network import Adam, Sgd, SkewSampler, Tower, UniformSampler, learning_rate, loss_and_gradients
from entlink.storage import locate, materialize, scratch_path

WEIGHTS = "entity_type string, step int, side string, layer int, kind string, rows int, cols int, values array<double>, loss double, rate double"


@dataclass(frozen=True)
class Config:
    dim: int = 256
    relation: tuple[int, ...] = (128, 64)  # widths after the input
    text: tuple[int, ...] = (64,)
    steps: int = 200
    batch: int = 48
    keep: float = 0.9
    rate: float = 2e-3
    decay: float = 0.9
    every: int = 1000
    margin: float = 0.1
    positive: str = "mean"  # or "each"
    optimizer: str = "adam"
    sampler: str = "skew"
    seed: int = 1
    checkpoints: tuple[int, ...] = ()
    text_dim: int = 128  # width of an encoded text attribute in the relation's vector
    encoder: str = "bag"  # of registry.ENCODERS
    tower: str = "dense"  # of registry.TOWERS


#: The published widths, rate, decay, margin and keep; batch and number of steps are not published.
PUBLISHED = Config(dim=1024, relation=(512, 256), text=(256,), steps=2400, keep=0.75, rate=1e-5, margin=0.001, checkpoints=(0, 100, 200, 600, 1200, 2400))


@lru_cache(maxsize=100_000)
def _cells(token: str, dim: int) -> tuple[np.ndarray, np.ndarray]:
    """Places and values of one token, itself and its trigrams; all values are halves, so sums of them are exact."""
    v = hashed_bag(token, dim) + 0.5 * hashed_bag(token, dim, (3, 3))
    at = np.flatnonzero(v)
    return at, v[at]


def _runs_of_tokens(texts, most: int = 1 << 16) -> Iterator[tuple[list[int], list[int], list[int], list[str]]]:
    """Number of the text, token and how often it stands there, and the distinct tokens: runs of at most ``most``, however long the texts are."""
    row, code, n, tokens = [], [], [], {}
    for i, text in enumerate(texts):
        for token, times in Counter(python_tokens(text)).items():
            row.append(i)
            code.append(tokens.setdefault(token, len(tokens)))
            n.append(times)
            if len(row) == most:
                yield row, code, n, list(tokens)
                row, code, n, tokens = [], [], [], {}
    if row:
        yield row, code, n, list(tokens)


def bags(texts, dim: int) -> np.ndarray:
    """Unit hashed bags of words and character trigrams.  Equal texts are taken once, and a token's cells are kept."""
    if not len(texts):
        return np.zeros((0, dim))
    unique: dict[str, int] = {}
    codes = [unique.setdefault(text or "", len(unique)) for text in texts]
    out = np.zeros((len(unique), dim))
    for row, code, n, tokens in _runs_of_tokens(unique):
        at, values = zip(*[_cells(t, dim) for t in tokens])
        sizes = np.array([len(x) for x in at])
        at, values, own = np.concatenate(at), np.concatenate(values), sizes[code]
        first = (np.cumsum(sizes) - sizes)[code]  # a token's cells stand together
        cell = np.arange(own.sum()) + np.repeat(first - (np.cumsum(own) - own), own)
        low, high = row[0], row[-1] + 1
        place = np.repeat(np.array(row) - low, own) * dim + at[cell]
        out[low:high] += np.bincount(place, np.repeat(n, own) * values[cell], (high - low) * dim).reshape(-1, dim)
    return (out / np.maximum(1e-9, np.linalg.norm(out, axis=1, keepdims=True)))[codes]


class BagEncoder:
    """The encoder ``bag``: unit hashed bags of words and character trigrams, of any width."""

    def encode(self, texts, width: int) -> np.ndarray:
        return bags(texts, width)


register_encoder("bag", BagEncoder())
register_tower("dense", lambda widths, seed, keep: Tower(widths, seed, keep))


def encoded(text: Column, width: int, encoder: str = "bag") -> Column:
    """A text by a registered encoder, in one Arrow function; null counts as empty."""
    model = ENCODERS[encoder]

    @F.pandas_udf("array<float>")
    def run(texts: pd.Series) -> pd.Series:
        return pd.Series(list(model.encode(texts.tolist(), width).astype(np.float32)))

    return run(F.coalesce(text, F.lit("")))


def mention_vector(config: Config) -> Column:
    """v_T of a mention (span, text, context): a quarter of the width for the span, a half for the sentence, a quarter for its context."""
    quarter = config.dim // 4
    parts = (("span", quarter), ("text", config.dim - 2 * quarter), ("context", quarter))
    return F.concat(*[encoded(F.col(c), w, config.encoder) for c, w in parts])


def fit_towers(r: np.ndarray, t: np.ndarray, pairs: np.ndarray, r_inst: np.ndarray, t_inst: np.ndarray, c: Config,
               start: tuple[Tower, Tower] | None = None, popularity: np.ndarray | None = None) -> Iterator[tuple[int, Tower, Tower, float, float]]:
    """Yields (step, relation tower, text tower, loss per pair, rate) at every checkpoint and at the end.

    A batch holds the tuples and mentions of the drawn pairs; all pairs of one instance in it are matches.  A batch
    without a non-match, which happens where few instances are known, gets the tuples of another instance.
    """
    learner = _Learner(r.shape[1], t.shape[1], c, start)
    sampler = (SkewSampler if c.sampler == "skew" else UniformSampler)(len(pairs), seed=c.seed)
    for step in range(c.steps + 1):
        if step in c.checkpoints or step == c.steps:
            yield step, *learner.state()
        if step == c.steps or not len(pairs):
            continue
        pick = pairs[sampler.draw(c.batch, popularity)]
        ri, ti = np.unique(pick[:, 0]), np.unique(pick[:, 1])
        match = r_inst[ri][:, None] == t_inst[ti][None]
        if match.all():
            others = np.flatnonzero(r_inst != r_inst[ri[0]])
            if not len(others):  # a single instance: nothing to tell apart
                continue
            ri = np.append(ri, learner.rng.choice(others, min(len(others), c.batch), replace=False))
            match = r_inst[ri][:, None] == t_inst[ti][None]
        learner.learn(step, [(r[ri], t[ti], match, len(pick))])


class _Learner:
    """Two towers, their optimiser and the loss of the last step."""

    def __init__(self, r_width: int, t_width: int, c: Config, start: tuple[Tower, Tower] | None = None):
        make = TOWERS[c.tower]
        self.gr, self.gt = start or (make((r_width, *c.relation), c.seed, c.keep), make((t_width, *c.text), c.seed + 1, c.keep))
        self.c, self.rng = c, np.random.default_rng(c.seed)
        self.opt = (Adam if c.optimizer == "adam" else Sgd)(self.gr.parameters() + self.gt.parameters())
        self.loss, self.rate = float("nan"), c.rate

    def state(self) -> tuple[Tower, Tower, float, float]:
        return self.gr, self.gt, self.loss, self.rate

    def learn(self, step: int, groups: list[tuple[np.ndarray, np.ndarray, np.ndarray, int]]) -> None:
        """One step by the mean gradient of groups (tuples, mentions, matches, number of pairs); rows of other groups are no non-matches."""
        c = self.c
        x = self.gr.forward(np.concatenate([g[0] for g in groups]).astype(float), self.rng)
        y = self.gt.forward(np.concatenate([g[1] for g in groups]).astype(float), self.rng)
        dx, dy, total, i, j = np.empty_like(x), np.empty_like(y), 0.0, 0, 0
        for r, t, match, n in groups:
            u, v = i + len(r), j + len(t)
            loss, gx, gy = loss_and_gradients(x[i:u], y[j:v], match, c.margin, c.positive)
            scale = 1 / max(1, n) / len(groups)
            dx[i:u], dy[j:v], total, i, j = gx * scale, gy * scale, total + loss, u, v
        self.loss, self.rate = total / max(1, sum(g[3] for g in groups)), learning_rate(step, c.rate, c.decay, c.every)
        self.opt.step(self.gr.backward(dx) + self.gt.backward(dy), self.rate)


@dataclass(frozen=True)
class Pairs:
    """Pairs in the order of training: instance, id and vector of each side."""

    inst: np.ndarray
    r_id: np.ndarray
    t_id: np.ndarray
    r: np.ndarray
    t: np.ndarray

    def __len__(self) -> int:
        return len(self.inst)

    def of(self, rows) -> Pairs:
        return Pairs(self.inst[rows], self.r_id[rows], self.t_id[rows], self.r[rows], self.t[rows])

    def then(self, more: Pairs) -> Pairs:
        return Pairs(*[np.concatenate([a, b]) for a, b in ((getattr(self, n), getattr(more, n)) for n in ("inst", "r_id", "t_id", "r", "t"))])


def fit_pass(runs: Iterable[Pairs], n: int, c: Config, start: tuple[Tower, Tower] | None = None) -> Iterator[tuple[int, Tower, Tower, float, float]]:
    """As ``fit_towers``, for ``n`` pairs beyond what the steps can draw: every pair is trained on once, with one run in memory.

    The steps share the pairs evenly; a step goes by the mean gradient of groups of ``batch`` pairs at most.  A group
    without a non-match gets tuples of other instances met lately, or waits for the next step if none were met yet.
    """
    runs = iter(runs)
    held = next(runs)
    learner, lately = _Learner(held.r.shape[1], held.t.shape[1], c, start), {}

    def group(rows: Pairs):
        _, ri = np.unique(rows.r_id, return_index=True)
        _, ti = np.unique(rows.t_id, return_index=True)
        r, r_inst, t_inst = rows.r[ri], rows.inst[ri], rows.inst[ti]
        for inst, v in zip(r_inst, r):
            lately.pop(inst, None)
            lately[inst] = v
        while len(lately) > c.batch + 1:
            del lately[next(iter(lately))]
        if (t_inst == t_inst[0]).all():
            others = [(i, v) for i, v in lately.items() if i != t_inst[0]][-c.batch :]
            if not others:
                return None
            r, r_inst = np.concatenate([r, np.stack([v for _, v in others])]), np.append(r_inst, [i for i, _ in others])
        return r, rows.t[ti], r_inst[:, None] == t_inst[None], len(rows)

    waiting = held.of(slice(0, 0))
    for step in range(c.steps + 1):
        if step in c.checkpoints or step == c.steps:
            yield step, *learner.state()
        if step == c.steps:
            return
        need = (step + 1) * n // c.steps - step * n // c.steps
        while len(held) < need and (more := next(runs, None)) is not None:
            held = held.then(more)
        rows, held = waiting.then(held.of(slice(0, need))), held.of(slice(need, None))
        waiting, groups = rows.of(slice(0, 0)), []
        for at in np.array_split(np.arange(len(rows)), max(1, -(-len(rows) // c.batch))):
            got = group(rows.of(at)) if len(at) else None
            if got is None:
                waiting = waiting.then(rows.of(at))
            else:
                groups.append(got)
        if len(waiting) and len(lately) > 1 and step == c.steps - 1:  # others were met after these
            groups += [group(waiting)]
        if groups:
            learner.learn(step, groups)


def _rows(kind: str, step: int, towers: dict[str, Tower], loss: float, rate: float) -> list[tuple]:
    return [
        (kind, step, side, i, k, *(v.shape if v.ndim == 2 else (1, len(v))), v.ravel().tolist(), loss, rate)
        for side, tower in towers.items()
        for i, (w, b) in enumerate(zip(tower.w, tower.b))
        for k, v in (("w", w), ("b", b))
    ]


def _columns() -> list[str]:
    return [c.split()[0] for c in WEIGHTS.split(", ")]


def _fitted(pdf: pd.DataFrame, config: Config, start: dict[str, tuple[Tower, Tower]] | None) -> pd.DataFrame:
    """Weights of one type from its rows (entity_type, id, instance_id, vec, side)."""
    pdf = pdf.sort_values(["side", "id"], kind="stable")
    a, b = pdf[pdf.side == "tuple"], pdf[pdf.side == "mention"]
    if not len(a) or not len(b):
        return pd.DataFrame(columns=_columns())
    codes = {v: i for i, v in enumerate(sorted(set(a.instance_id) | set(b.instance_id)))}
    ri, ti = a.instance_id.map(codes).to_numpy(int), b.instance_id.map(codes).to_numpy(int)
    first = {}
    for i, inst in enumerate(ri):
        first.setdefault(inst, []).append(i)
    pairs = np.array([(first[inst][j % len(first[inst])], j) for j, inst in enumerate(ti) if inst in first]).reshape(-1, 2)
    out, kind = [], pdf.entity_type.iloc[0]
    for step, gr, gt, loss, rate in fit_towers(np.stack(a.vec), np.stack(b.vec), pairs, ri, ti, config, (start or {}).get(kind)):
        out += _rows(kind, step, {"relation": gr, "text": gt}, loss, rate)
    return pd.DataFrame(out, columns=_columns())


NAMES = ["entity_type", "side", "instance_id", "id"]
RUN = 4096  # pairs of a training task's files, about


def _in_order(both: DataFrame, seed: int, draws: int) -> tuple[str, list[tuple[str, int, int, int]]]:
    """Folder of the rows of all types in the order of training, and of every type (name, pairs, instances, files).

    An instance with T tuples and M mentions has max(T, M) pairs: the k-th is of tuple k mod T and mention k mod M, numbered
    by hash.  A row stands once for each of its pairs, in the file that a hash of the pair tells; types of ``draws`` pairs
    at most are held whole and have each row once.  Rows are numbered without their vectors.
    """
    own = Window.partitionBy("entity_type", "side", "instance_id").orderBy(F.xxhash64("id"), "id")
    named = both.select(*NAMES).where("instance_id IS NOT NULL")
    numbered = named.withColumn("no", F.row_number().over(own) - 1)
    size = lambda side: F.count(F.when(F.col("side") == side, 1))
    sizes = named.groupBy("entity_type", "instance_id").agg(size("tuple").alias("t"), size("mention").alias("m")).where("t > 0 AND m > 0")
    sizes = materialize(sizes, "training-sizes")
    known = sizes.groupBy("entity_type").agg(F.sum(F.greatest("t", "m")).alias("pairs"), F.count("*").alias("instances"))  # one row a type
    kinds = sorted((r.entity_type, r.pairs, r.instances, max(1, round(r.pairs / RUN))) for r in known.collect())
    if not kinds:
        return "", []
    at = {k: (i, files, n > draws) for i, (k, n, _, files) in enumerate(kinds)}
    pick = lambda j: F.create_map(*[x for k, v in at.items() for x in (F.lit(k), F.lit(v[j]))])[F.col("entity_type")]
    last = F.when(pick(2), F.greatest("t", "m") - 1).otherwise(F.col("no"))
    of_row = numbered.join(sizes, ["entity_type", "instance_id"])
    of_row = of_row.withColumn("k", F.explode(F.sequence(F.col("no").cast("bigint"), last.cast("bigint"), F.when(F.col("side") == "tuple", F.col("t")).otherwise(F.col("m")))))
    of_row = of_row.withColumn("mark", F.xxhash64(F.lit(seed), "entity_type", "instance_id", "k"))
    place = F.floor((F.col("mark").cast("double") / 2.0**64 + 0.5) * pick(1)).cast("int")
    of_row = of_row.select(*NAMES, "k", "mark", pick(0).alias("slot"), F.greatest(F.lit(0), F.least(place, pick(1) - 1)).alias("file"))
    same = reduce(and_, [F.col(f"a.{n}").eqNullSafe(F.col(f"b.{n}")) for n in NAMES])
    rows = both.alias("a").join(of_row.alias("b"), same).select("a.*", "b.k", "b.mark", "b.slot", "b.file")
    path, files = scratch_path(both.sparkSession, "training"), sum(k[3] for k in kinds)
    parts = max(1, min(files, 4 * both.sparkSession.sparkContext.defaultParallelism), files // 64)
    rows.repartition(parts, "slot", "file").sortWithinPartitions("slot", "file").write.partitionBy("slot", "file").parquet(path)
    return path, kinds


def _vectors(column: pa.ChunkedArray) -> np.ndarray:
    return np.concatenate([c.flatten().to_numpy(zero_copy_only=False).reshape(len(c), -1) for c in column.chunks])


def _pairs_of(rows: pa.Table) -> Pairs:
    """The pairs of one file in order."""
    sides = []
    for side in ("tuple", "mention"):
        own = rows.filter(pc.equal(rows["side"], side))
        inst = own["instance_id"].to_pandas().to_numpy(dtype=str)
        order = np.lexsort((own["k"].to_numpy(), inst, own["mark"].to_numpy()))
        sides.append((inst[order], own["id"].to_pandas().to_numpy(dtype=str)[order], _vectors(own["vec"])[order]))
    (inst, r_id, r), (_, t_id, t) = sides
    return Pairs(inst, r_id, t_id, r, t)


def train(tuples: DataFrame, mentions: DataFrame, config: Config, max_rows: int | None = None, start: dict[str, tuple[Tower, Tower]] | None = None) -> DataFrame:
    """Weights of every entity type, of all rows that have a row of their instance on the other side.

    ``tuples`` has entity_type, tuple_id, instance_id, vec; ``mentions`` has entity_type, mention_id, instance_id,
    vec and holds training mentions only.  One task trains a type.  If its steps can draw all pairs, it holds the type's
    rows and draws batches of all pairs; otherwise it reads the pairs once in the order of a hash, a run at a time, and
    the steps share them (``fit_pass``).  Towers in ``start`` are trained on: retraining begins with the weights at hand.

    A caller who wants a bounded training gives ``max_rows``, rows of each side: both sides take instances in one order,
    by hash, and of every instance its first row before any second, so the rows kept match each other.
    """
    left = tuples.select("entity_type", F.col("tuple_id").alias("id"), "instance_id", "vec", F.lit("tuple").alias("side"))
    right = mentions.select("entity_type", F.col("mention_id").alias("id"), "instance_id", "vec", F.lit("mention").alias("side"))
    both = left.unionByName(right)
    if max_rows is not None:
        return _first_rows(both, max_rows).groupBy("entity_type").applyInPandas(lambda pdf: _fitted(pdf, config, start), WEIGHTS)
    spark, draws = both.sparkSession, config.steps * config.batch
    path, kinds = _in_order(both, config.seed, draws)
    if not kinds:
        return spark.createDataFrame([], WEIGHTS)

    def learn(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for slot in (int(i) for pdf in batches for i in pdf.id):
            kind, pairs, instances, _ = kinds[slot]
            fs, own = locate(f"{path}/slot={slot}")
            files = sorted((int(f.base_name.split("=")[1]), f.path) for f in fs.get_file_info(pafs.FileSelector(own)) if f.base_name.startswith("file="))
            runs = (dataset.dataset(f, filesystem=fs, format="parquet").to_table(use_threads=False) for _, f in files)
            if pairs <= draws:
                yield _fitted(pa.concat_tables(runs).to_pandas(), config, start)
                continue
            # With a single instance there is nothing to tell apart.
            fit = fit_pass((_pairs_of(run) for run in runs), pairs if instances > 1 else 0, config, (start or {}).get(kind))
            yield pd.DataFrame([x for step, gr, gt, loss, rate in fit for x in _rows(kind, step, {"relation": gr, "text": gt}, loss, rate)], columns=_columns())

    return spark.range(0, len(kinds), 1, len(kinds)).mapInPandas(learn, WEIGHTS)


def _first_rows(both: DataFrame, max_rows: int) -> DataFrame:
    own = Window.partitionBy("entity_type", "side", "instance_id").orderBy(F.xxhash64("id"), "id")
    some = Window.partitionBy("entity_type", "side").orderBy("turn", F.xxhash64("instance_id"), "instance_id")

    def first_rows(rows: DataFrame) -> DataFrame:
        # Spark keeps the first rows of each group in every task before it shuffles.
        rows = rows.withColumn("turn", F.row_number().over(own)).where(F.col("turn") <= max_rows)
        return rows.withColumn("n", F.row_number().over(some)).where(F.col("n") <= max_rows).drop("n", "turn")

    # Rows are picked without their vectors, which are then read for those alone; the second pick undoes equal hashes.
    mark = F.xxhash64(*NAMES)
    picked = first_rows(both.select(*NAMES)).select(*NAMES, mark.alias("mark"))
    few = both.withColumn("mark", mark).join(F.broadcast(picked.select("mark")), "mark", "left_semi").drop("mark")
    same = reduce(and_, [F.col(f"a.{n}").eqNullSafe(F.col(f"b.{n}")) for n in NAMES])
    return first_rows(few.alias("a").join(picked.alias("b"), same, "left_semi"))


def load_tower(weights: DataFrame, entity_type: str, side: str, step: int) -> Tower:
    """One tower of a weight table; a few hundred thousand numbers."""
    rows = weights.where((F.col("entity_type") == entity_type) & (F.col("side") == side) & (F.col("step") == step)).collect()
    tower = Tower(())
    for r in sorted(rows, key=lambda r: (r.layer, r.kind)):
        v = np.array(r["values"])
        if r.kind == "b":
            tower.b.append(v)
        else:
            tower.w.append(v.reshape(r.rows, r.cols))
    return tower


def partial_gradients(frame: DataFrame, towers: tuple[Tower, Tower], config: Config) -> tuple[float, list[np.ndarray]]:
    """Sum of loss gradients over partitions, each a batch of its own: one step of data-parallel training.

    ``frame`` has r_vec, t_vec, instance_id, one row for a pair.
    """
    shared = frame.sparkSession.sparkContext.broadcast(towers)

    def run(batches):
        pdf = pd.concat(list(batches) or [pd.DataFrame()])
        if not len(pdf):
            return
        gr, gt = shared.value
        inst = pdf.instance_id.to_numpy()
        rng = np.random.default_rng(config.seed)
        x, y = gr.forward(np.stack(pdf.r_vec), rng), gt.forward(np.stack(pdf.t_vec), rng)
        loss, dx, dy = loss_and_gradients(x, y, inst[:, None] == inst[None], config.margin, config.positive)
        flat = np.concatenate([g.ravel() for g in gr.backward(dx) + gt.backward(dy)])
        yield pd.DataFrame({"i": np.arange(len(flat) + 1), "g": np.append(flat, loss)})

    sums = frame.mapInPandas(run, "i long, g double").groupBy("i").agg(F.sum("g").alias("g")).orderBy("i").toPandas().g.to_numpy()
    shapes, at, out = [p.shape for t in towers for p in t.parameters()], 0, []
    for s in shapes:
        n = int(np.prod(s))
        out.append(sums[at : at + n].reshape(s))
        at += n
    return float(sums[-1]), out


def train_distributed(frame: DataFrame, config: Config, steps: int) -> tuple[tuple[Tower, Tower], list[float]]:
    """Synchronous data-parallel training of one large type: the driver holds weights, tasks hold rows."""
    c = replace(config, keep=1.0)
    one = frame.select(F.size("r_vec").alias("r"), F.size("t_vec").alias("t")).first()
    towers = Tower((one.r if one else c.dim, *c.relation), c.seed), Tower((one.t if one else c.dim, *c.text), c.seed + 1)
    opt, losses = Adam(towers[0].parameters() + towers[1].parameters()), []
    n = max(1, frame.count())
    for step in range(steps):
        loss, grads = partial_gradients(frame, towers, c)
        opt.step([g / n for g in grads], learning_rate(step, c.rate, c.decay, c.every))
        losses.append(loss / n)
    return towers, losses
