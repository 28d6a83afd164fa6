"""Descent from private gradients.

Mini-batch descent is one small job per step: the step's users (each takes part once) compute their gradient at
the current weights, report one coordinate of it as a sign, and the signs are summed per coordinate. What returns to the driver is one number per
model and coordinate. Many models (folds, budgets) share a step's pass over the data. Users are stored in ``SLICES`` ranges of their place in the batches, so
that a step reads the ranges of its own users only (``sliced``).

A batch of fewer than ``STREAMED`` users is less work than a job costs. Models of such batches train on one sorted stream of a fold's users, which carries
sums and weights along (``streamed``); ``train`` sends each model to the form that its batch asks for. Both forms take the same steps.

Sequential descent, one user per step, cannot be spread over tasks within a model; it is a baseline. The models of a fold, one per budget, step together through one
sorted stream of all its users, batch by batch, so memory is bounded; the result states the number of users. Users are sorted side by side and
packed before they go to the one task of a stream (``packed``), which only steps. Streams that read one stored table of packed users shuffle nothing.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ldpspark.erm.compiled import walked
from ldpspark.erm.losses import dot, slope
from ldpspark.functions import constants as C
from ldpspark.functions.rng import uniform
from ldpspark.sources.ship import ship
from ldpspark.sources.stored import stored


SLICES = 32
#: Users of a batch below which models train on a stream.
STREAMED = 1_000_000
#: Dimensions up to which a step on plain numbers is cheaper than one on arrays.
PLAIN = 8
#: Bytes of users that a task holds while it packs them.
RANGE = 32 << 20
PACKED = "range int, nth int, first double, rows int, dim int, base binary, draws binary"
_NAMES = ["range", "nth", "first", "rows", "dim", "base", "draws"]
_KINDS = (pa.int32(), pa.int32(), pa.float64(), pa.int32(), pa.int32(), pa.binary(), pa.binary())


def step_size(step: int, gamma0: float = 1.0) -> float:
    """Step size of step 1, 2, ..."""
    return gamma0 / math.sqrt(step)


@dataclass
class Model:
    """One model in training: its users (all but one fold), budget, number of steps and weights."""

    name: str
    dim: int
    eps: float
    steps: int
    fold: int = -1
    weights: list[float] = field(default_factory=list)
    history: list[float] = field(default_factory=list)
    stopped: bool = False

    def __post_init__(self) -> None:
        self.weights = self.weights or [0.0] * self.dim


def steps_for(n: int, dim: int, eps: float, floor_share: int = 1000, g: int | None = None) -> int:
    """Whole batches that n users make; an error if not one."""
    size = g or C.batch_size(dim, eps, n, floor_share)
    if size > n:
        raise ValueError(f"a batch of {size} users is more than the {n} there are")
    return n // size


def prepared(features: DataFrame, folds: int = 0, seed: int = 42, mode: str = "md5") -> DataFrame:
    """Adds what a user draws once and for all: place in the batches ``ub``, coordinate ``uj``, toss ``ut``, and fold."""
    out = features.withColumns({"ub": uniform("ukey", "batch", seed, 0, mode), "uj": uniform("ukey", "step", seed, 0, mode), "ut": uniform("ukey", "grad", seed, 0, mode)})
    fold = F.floor(uniform("ukey", "fold", seed, 0, mode) * folds).cast("int") if folds else F.lit(-2)
    return out.withColumn("fold", fold)


def sliced(users: DataFrame, name: str = "users") -> DataFrame:
    """``users`` of ``prepared``, stored in folders of ``slice``, equal ranges of ``ub``: a step of any training reads the ranges it needs. One shuffle for all trainings."""
    cut = users.withColumn("slice", F.least(F.floor(F.col("ub") * SLICES), F.lit(SLICES - 1)).cast("int"))
    return stored(cut.repartition(F.col("slice"), F.pmod(F.xxhash64("ukey"), F.lit(8))), name, "slice")


def _slices(models: list[Model], step: int) -> list[int]:
    """Ranges of ``ub`` that hold users of a step."""
    out: set[int] = set()
    for m in models:
        # a margin against the rounding of ub * steps
        lo, hi = (step - 1e-9) / m.steps * SLICES, ((step + 1 if step + 1 < m.steps else m.steps) + 1e-9) / m.steps * SLICES
        out.update(range(max(0, math.floor(lo)), min(SLICES, math.floor(hi) + 1)))
    return sorted(out)


def gradient_sums(users: DataFrame, models: list[Model], step: int, kind: str, lam: float) -> DataFrame:
    """(model, j, total, reports) of one step: signs of one clamped gradient coordinate per user and model."""
    spark = users.sparkSession
    live = [m for m in models if step < m.steps and not m.stopped]
    rows = [(m.name, m.fold, m.steps, m.eps, 1 / (2 * C.report_scale(m.eps)), [float(w) for w in m.weights]) for m in live]
    table = F.broadcast(spark.createDataFrame(rows, "model string, mfold int, steps int, eps double, tilt double, w array<double>"))
    batch = F.least(F.floor(F.col("ub") * F.col("steps")), F.col("steps") - 1)
    if "slice" in users.columns:
        users = users.where(F.col("slice").isin(_slices(live, step)))
    at = users.join(table, (F.col("fold") != F.col("mfold")) & (batch == step))
    j = F.floor(F.col("uj") * F.size("w")).cast("int")
    at = at.withColumn("j", j).withColumn("g", slope(kind, dot(F.col("x"), F.col("w")), F.col("y")))
    one = F.col("g") * F.element_at("x", F.col("j") + 1) + lam * F.element_at("w", F.col("j") + 1)
    clamped = F.greatest(F.lit(-1.0), F.least(F.lit(1.0), one))
    sign = F.when(F.col("ut") < F.lit(0.5) + clamped * F.col("tilt"), 1).otherwise(-1)
    return at.groupBy("model", "j").agg(F.sum(sign).cast("long").alias("total"), F.count(F.lit(1)).alias("reports"))


def update(model: Model, sums: dict[int, tuple[int, int]], step: int, gamma0: float, tol: float) -> None:
    """One step of a model from its coordinate sums (driver side: a few numbers)."""
    g = sum(n for _, n in sums.values())
    if not g:
        return
    scale = step_size(step + 1, gamma0) * C.report_scale(model.eps) * model.dim / g
    moved = 0.0
    for j, (total, _) in sums.items():
        model.weights[j] -= scale * total
        moved = max(moved, abs(scale * total))
    if not all(math.isfinite(w) for w in model.weights):
        raise ArithmeticError(f"{model.name}: weights are no longer finite at step {step + 1}")
    model.history.append(moved)
    model.stopped = moved < tol


def minibatch(users: DataFrame, models: list[Model], kind: str, lam: float = 1e-4, gamma0: float = 1.0, tol: float = 0.0, max_steps: int | None = None) -> list[Model]:
    """Trains the models to their number of steps, until a step moves less than ``tol``, or ``max_steps``.

    ``users`` comes from ``prepared`` (x, y, draws and fold) and should be ``sliced``: each step reads its part of it. A model with m participations per user is m
    frames with their own draws and eps/m each; see ``participating``.
    """
    last = max((m.steps for m in models), default=0)
    for step in range(min(last, max_steps) if max_steps else last):
        if all(m.stopped or step >= m.steps for m in models):
            break
        found: dict[str, dict[int, tuple[int, int]]] = {}
        for r in gradient_sums(users, models, step, kind, lam).collect():
            found.setdefault(r["model"], {})[r["j"]] = (r["total"], r["reports"])
        for m in models:
            if m.name in found:
                update(m, found[m.name], step, gamma0, tol)
    return models


def packed(users: DataFrame, n: int | None = None, dim: int | None = None) -> DataFrame:
    """``users`` of ``prepared`` in order of ``ub``, thousands to a row, as compressed columns: what every training on a stream of the same users reads.

    Users are packed by ranges of ``ub`` where they are read, so that the shuffle moves compressed columns; a range is then merged, sorted and packed again. A stream puts the rows in order, which are few.
    Equal places are ordered by the other draws. ``n`` users of ``dim`` numbers (counted if not given) only set how many ranges there are: a task holds one range, of about ``RANGE`` bytes.
    """
    if "base" in users.columns:
        return users
    spark = users.sparkSession
    ship(spark)
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", 4 << 20)
    if n is None or dim is None:
        n, dim = users.agg(F.count(F.lit(1)), F.max(F.size("x"))).first()
    each = 8 * ((dim or 0) + 5)
    tasks = max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    share = max(1, math.ceil(n * each / tasks / RANGE))
    ranges, most, piece = tasks * share, max(1, RANGE // each), max(1, min(10_000, (4 << 20) // each))

    def dealt(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for b in batches:
            if b.num_rows:
                held.append((np.asarray(b["fold"]).astype(np.int32), np.asarray(b["x"].flatten()).reshape(b.num_rows, -1).T, *(np.asarray(b[c]) for c in ("y", "ub", "uj", "ut"))))
                size += b.num_rows
            if size >= most:
                yield from cut(held)
                held, size = [], 0
        if held:
            yield from cut(held)

    def cut(held: list[tuple[np.ndarray, ...]]) -> Iterator[pa.RecordBatch]:
        own = _in_order(held)
        at = np.minimum((own[3] * ranges).astype(np.int64), ranges - 1)
        ends = np.concatenate(([0], np.flatnonzero(np.diff(at)) + 1, [len(at)]))
        yield _packed_rows([(int(at[a]), 0, a, b) for a, b in zip(ends[:-1], ends[1:])], own)

    def merged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, at = [], -1
        for batch in batches:
            for r in batch.to_pylist():
                if held and r["range"] != at:
                    yield whole(at, held)
                    held = []
                at = r["range"]
                fold, y, x = _base(r)
                held.append((fold, x, y, *_draws(r)))
        if held:
            yield whole(at, held)

    def whole(at: int, held: list[tuple[np.ndarray, ...]]) -> pa.RecordBatch:
        own = _in_order(held)
        size = len(own[0])
        return _packed_rows([(at, i, a, min(a + piece, size)) for i, a in enumerate(range(0, size, piece))], own)

    parts = users.select("fold", "x", "y", "ub", "uj", "ut").mapInArrow(dealt, PACKED)
    return parts.repartitionById(tasks, F.floor(F.col("range") / share).cast("int")).sortWithinPartitions("range").mapInArrow(merged, PACKED)


def _in_order(held: list[tuple[np.ndarray, ...]]) -> tuple[np.ndarray, ...]:
    """(fold, x by columns, y, ub, uj, ut) of all parts, in order of ``ub``; equal places by all else, so that the order doesn't depend on the parts."""
    fold, x, y, ub, uj, ut = (np.concatenate(v, axis=-1) for v in zip(*held))
    order = np.argsort(ub, kind="stable")
    if (ub[order[1:]] == ub[order[:-1]]).any():
        order = np.lexsort((*x, y, ut, uj, ub))
    return fold[order], x[:, order], y[order], ub[order], uj[order], ut[order]


def _packed_rows(cuts: list[tuple[int, int, int, int]], own: tuple[np.ndarray, ...]) -> pa.RecordBatch:
    """Rows of ``packed`` for each (range, nth, from, to) of users that are in order."""
    fold, x, y, ub, uj, ut = own
    out = []
    for at, nth, a, b in cuts:
        # places are in order: differences of their bits are small
        near = np.diff(ub[a:b].view(np.int64), prepend=0)
        draws = _squeezed(*(np.ascontiguousarray(v).view(np.uint8).reshape(-1, 8).T for v in (near, uj[a:b], ut[a:b])))
        out.append((at, nth, float(ub[a]), b - a, len(x), _squeezed(fold[a:b], y[a:b], x[:, a:b]), draws))
    return pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(zip(*out), _KINDS)], names=_NAMES)


def _squeezed(*arrays: np.ndarray) -> bytes:
    return pa.compress(b"".join(np.ascontiguousarray(a).tobytes() for a in arrays), codec="zstd", asbytes=True)


def _base(r: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(fold, y, x by columns) of a row of ``packed``."""
    n, d = r["rows"], r["dim"]
    raw = pa.decompress(r["base"], 4 * n + 8 * n * (d + 1), "zstd", asbytes=True)
    rest = np.frombuffer(raw, np.float64, n * (d + 1), 4 * n)
    return np.frombuffer(raw, np.int32, n), rest[:n], rest[n:].reshape(d, n)


def _draws(r: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(ub, uj, ut) of a row of ``packed``, whose bytes are stored by their place in a number."""
    n = r["rows"]
    planes = np.frombuffer(pa.decompress(r["draws"], 24 * n, "zstd", asbytes=True), np.uint8).reshape(3, 8, n)
    near, uj, ut = (np.ascontiguousarray(p.T).view(np.int64).reshape(n) for p in planes)
    return np.cumsum(near).view(np.float64), uj.view(np.float64), ut.view(np.float64)


def _unpacked(batch: pa.RecordBatch, draws: bool, columns: bool = False) -> Iterator[tuple[int, np.ndarray, ...]]:
    """(group, fold, x, y, and the three draws if asked for) of each row of ``packed``; x by users, or by ``columns``."""
    rows = batch.to_pylist()
    if any(r["part"] != rows[0]["part"] for r in rows):
        raise RuntimeError("a task got two streams")
    for r in rows:
        fold, y, x = _base(r)
        yield r["part"], fold, x if columns else np.ascontiguousarray(x.T), y, *(_draws(r) if draws else ())


def _streams(users: DataFrame, parts: int, draws: bool) -> DataFrame:
    """All users in order, as rows of ``packed``, once for each of ``parts`` tasks. Users that come ``packed`` are a stored table: each task reads it, and nothing is shuffled."""
    unread = [] if draws else ["draws"]
    if "base" in users.columns:
        # else a union of single partitions is a single one
        users.sparkSession.conf.set("spark.sql.unionOutputPartitioning", False)
        one = users.drop(*unread).coalesce(1)
        rows = one.withColumn("part", F.lit(0))
        for i in range(1, parts):
            rows = rows.unionAll(one.withColumn("part", F.lit(i)))
        return rows.sortWithinPartitions("range", "nth")
    table = users.sparkSession.createDataFrame([(i,) for i in range(parts)], "part int")
    rows = packed(users).drop(*unread).crossJoin(F.broadcast(table))
    return rows.repartitionById(parts, "part").sortWithinPartitions("part", "range", "nth")


def streamed(users: DataFrame, models: list[Model], kind: str, lam: float = 1e-4, gamma0: float = 1.0, tol: float = 0.0) -> list[Model]:
    """The training of ``minibatch`` on sorted streams of users, ``packed`` or not: for batches too small for a job each. The models of a fold share a stream, those of few numbers share one with other folds."""
    folds: dict[int, list[Model]] = {}
    for m in models:
        folds.setdefault(m.fold, []).append(m)
    parts = min(len(folds), 1 + sum(m.dim for m in models) // 512)
    dealt = [dict(list(folds.items())[i::parts]) for i in range(parts)]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pd.DataFrame]:
        own: dict[int, list[Batches]] = {}
        for batch in batches:
            for part, fold, x, y, ub, uj, ut in _unpacked(batch, True, columns=True):
                own = own or {f: [Batches(m, kind, lam, gamma0, tol) for m in ms] for f, ms in dealt[part].items()}
                asked: dict[int, tuple[np.ndarray, np.ndarray]] = {}
                for f, runs in own.items():
                    out = fold == f
                    for b in runs:
                        d = b.model.dim
                        if d not in asked:
                            j = np.floor(uj * d).astype(np.int64)
                            asked[d] = j, x[j, np.arange(len(j))]
                        b.run(x, y, ub, ut, *asked[d], out)
        if own:
            yield _trained([b for runs in own.values() for b in runs])

    def arrow(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for pdf in work(batches):
            yield pa.RecordBatch.from_pandas(pdf, preserve_index=False)

    rows = {r["model"]: r for r in _streams(users, parts, True).mapInArrow(arrow, "model string, weights array<double>, history array<double>, stopped boolean").collect()}
    for m in models:
        if m.name in rows:
            r = rows[m.name]
            m.weights, m.history, m.stopped = list(r["weights"]), list(r["history"]), r["stopped"]
    return models


def _trained(own: list[Batches]) -> pd.DataFrame:
    for b in own:
        b.close()
    done = [b.model for b in own]
    return pd.DataFrame({"model": [m.name for m in done], "weights": [[float(w) for w in m.weights] for m in done], "history": [[float(h) for h in m.history] for m in done], "stopped": [bool(m.stopped) for m in done]})


class Batches:
    """Mini-batch descent of one model over users that come in order of ``ub``; ``run`` goes on from where the last call ended."""

    def __init__(self, model: Model, kind: str, lam: float, gamma0: float, tol: float) -> None:
        self.model, self.kind, self.lam, self.gamma0, self.tol = model, kind, lam, gamma0, tol
        self.step = 0
        self.tilt = 1 / (2 * C.report_scale(model.eps))
        self.total, self.count = np.zeros(model.dim, np.int64), np.zeros(model.dim, np.int64)

    def close(self) -> None:
        """Takes the step of the users seen since the last one."""
        if self.count.any() and not self.model.stopped:
            update(self.model, {int(j): (int(self.total[j]), int(self.count[j])) for j in np.flatnonzero(self.count)}, self.step, self.gamma0, self.tol)
        self.total[:], self.count[:] = 0, 0

    def run(self, x: np.ndarray, y: np.ndarray, ub: np.ndarray, ut: np.ndarray, j: np.ndarray, xj: np.ndarray, out: np.ndarray) -> None:
        """Users by columns, with the coordinate that each reports and its value there; those who are ``out`` take no part."""
        m = self.model
        if m.stopped or not len(ub):
            return
        first, last = (min(int(ub[i] * m.steps), m.steps - 1) for i in (0, -1))
        cut = np.zeros(0, np.int64)
        if first != last:
            batch = np.minimum((ub * m.steps).astype(np.int64), m.steps - 1)
            cut = np.flatnonzero(np.diff(batch)) + 1
        # two places of a count for each coordinate, the last two for those who are out
        place = np.where(out, 2 * m.dim, 2 * j)
        for a, b in zip([0, *cut.tolist()], [*cut.tolist(), len(ub)]):
            step = first if a == 0 else int(batch[a])
            if step != self.step:
                self.close()
                self.step = step
            if m.stopped:
                return
            w = np.asarray(m.weights)
            g = _slopes(self.kind, w @ x[:, a:b], y[a:b])
            g *= xj[a:b]
            g += self.lam * w[j[a:b]]
            np.maximum(g, -1, out=g)
            np.minimum(g, 1, out=g)
            g *= self.tilt
            g += 0.5
            found = np.bincount(place[a:b] + (ut[a:b] < g), minlength=2 * m.dim + 2)[: 2 * m.dim].reshape(-1, 2)
            self.total += found[:, 1] - found[:, 0]
            self.count += found[:, 1] + found[:, 0]


def train(users: DataFrame, models: list[Model], kind: str, lam: float = 1e-4, gamma0: float = 1.0, tol: float = 0.0, rows: DataFrame | None = None) -> list[Model]:
    """Trains each model by jobs or on a stream, whichever its batch asks for. ``rows``: the users as ``packed``, if that is at hand."""
    n = users.count() if rows is None else rows.agg(F.sum("rows")).first()[0]
    small = [m for m in models if n / m.steps < STREAMED]
    large = [m for m in models if n / m.steps >= STREAMED]
    if small:
        streamed(users if rows is None else rows, small, kind, lam, gamma0, tol)
    if large:
        minibatch(users, large, kind, lam, gamma0, tol)
    return models


def fold_sizes(rows: DataFrame) -> dict[int, int]:
    """Users of each fold of a table of ``packed`` users."""

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                found = np.unique(_base(r)[0], return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(v, pa.int64()) for v in found], names=["fold", "n"])

    return {r["fold"]: r["n"] for r in rows.mapInArrow(counted, "fold long, n long").groupBy("fold").agg(F.sum("n").alias("n")).collect()}


def projected_rows(rows: DataFrame, p: list[list[float]]) -> DataFrame:
    """``packed`` users with P x for x, where they are: what ``projection.projected`` gives, summed in the same order."""
    columns = np.array(p).T

    def mapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                fold, y, x = _base(r)
                out = np.zeros((columns.shape[1], len(y)))
                for signs, v in zip(columns, x):
                    out += signs[:, None] * v
                cells = [r["range"], r["nth"], r["first"], r["rows"], len(out), _squeezed(fold, y, out), r["draws"]]
                yield pa.RecordBatch.from_arrays([pa.array([v], k) for v, k in zip(cells, _KINDS)], names=_NAMES)

    return rows.mapInArrow(mapped, PACKED)


def tested_rows(rows: DataFrame, models: list[tuple[str, int, list[float]]], kind: str) -> DataFrame:
    """(model, users, error) of each model (name, fold, weights) on the ``packed`` users of its fold: what ``losses.evaluate`` says of them."""
    folds: dict[int, tuple[list[str], np.ndarray]] = {}
    for f in {f for _, f, _ in models}:
        folds[f] = [name for name, at, _ in models if at == f], np.array([w for _, at, w in models if at == f], np.float64)

    def tested(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        users, total = dict.fromkeys(folds, 0), {f: np.zeros(len(names)) for f, (names, _) in folds.items()}
        for batch in batches:
            for r in batch.to_pylist():
                fold, y, x = _base(r)
                for f, (_, w) in folds.items():
                    own = fold == f
                    if own.any():
                        score, target = w @ x[:, own], y[own]
                        users[f] += len(target)
                        total[f] += ((score - target) ** 2 if kind == "linear" else (score > 0) != (target > 0)).sum(1)
        for f, (names, _) in folds.items():
            if users[f]:
                yield pa.RecordBatch.from_arrays([pa.array(names), pa.array([users[f]] * len(names)), pa.array(total[f])], names=["model", "n", "total"])

    found = rows.mapInArrow(tested, "model string, n long, total double").groupBy("model")
    return found.agg(F.sum("n").alias("users"), (F.sum("total") / F.sum("n")).alias("error"))


def participating(features: DataFrame, times: int, folds: int = 0, seed: int = 42, mode: str = "md5") -> DataFrame:
    """Each user ``times`` over, with fresh draws each; to be trained with eps / ``times``."""
    again = features.withColumn("turn", F.explode(F.sequence(F.lit(0), F.lit(times - 1))))
    key = again.withColumn("own", F.col("ukey")).withColumn("ukey", F.concat_ws("#", "own", F.col("turn").cast("string")))
    out = prepared(key, 0, seed, mode)
    fold = F.floor(uniform("own", "fold", seed, 0, mode) * folds).cast("int") if folds else F.lit(-2)
    return out.withColumn("fold", fold).drop("own", "turn")


def _slopes(kind: str, s: np.ndarray, y: np.ndarray | float) -> np.ndarray:
    if kind == "linear":
        return 2 * (s - y)
    if kind == "logistic":
        return -y / (1 + np.exp(np.minimum(y * s, 700)))
    return np.where(y * s < 1, -y, 0.0)


class Walk:
    """Descent over users in the given order, one per step, of one model for each budget; ``run`` goes on from where the last call ended.

    A user takes the same draws in all models, in a fixed number, so that the models don't depend on each other or on how users are cut into calls.
    """

    def __init__(self, kind: str, lam: float, gamma0: float, mechanism: str | None = None, eps: list[float] | tuple[float, ...] = (1.0,), seed: int = 42, tol: float = 0.0) -> None:
        if mechanism not in (None, "halfspace", "laplace", "one_coordinate"):
            raise ValueError(f"unknown mechanism {mechanism!r}")
        self.kind, self.lam, self.gamma0, self.mechanism, self.tol = kind, lam, gamma0, mechanism, tol
        self.eps = np.array(eps, np.float64)
        self.rng = np.random.default_rng(seed)
        self.w: np.ndarray | None = None
        self.seen = 0
        self.going = np.ones(len(eps), bool)

    def _noise(self, n: int, d: int):
        """What the reports of ``n`` users need beside their gradients: a function of (user, clamped gradients)."""
        scale = np.array([C.report_scale(e) for e in self.eps])[:, None]
        if self.mechanism == "laplace":
            u = self.rng.random((n, d)) - 0.5
            unit = -np.sign(u) * np.log(np.maximum(1 - 2 * np.abs(u), 1e-300)) * 2 * d
            return lambda k, g: g + unit[k] / self.eps[:, None]
        if self.mechanism == "one_coordinate":
            u = self.rng.random((n, 2))
            at = np.minimum((u[:, 0] * d).astype(np.int64), d - 1)

            def one(k: int, g: np.ndarray) -> np.ndarray:
                out = np.zeros_like(g)
                out[:, at[k]] = np.where(u[k, 1] < 0.5 + g[:, at[k]] / (2 * scale[:, 0]), 1, -1) * scale[:, 0] * d
                return out

            return one
        u = self.rng.random((n, 2 * d + 2))
        rank = _ranks(u[:, d : 2 * d])
        inside, other = (np.searchsorted(np.array(c), u[:, 2 * d], "right") for c in C.halfspace_cdf(d))
        chance = np.array([C.halfspace_prob(d, e) for e in self.eps])
        own = np.where(u[:, 2 * d + 1, None] < chance, inside[:, None], other[:, None])
        size = np.array([C.halfspace_scale(d, e) for e in self.eps])[:, None]
        return lambda k, g: np.where((u[k, :d] < (1 + g) / 2) == (rank[k] < own[k][:, None]), size, -size)

    def run(self, x: np.ndarray, y: np.ndarray) -> None:
        d = x.shape[1]
        if self.w is None:
            self.w = np.zeros((len(self.eps), d))
        if d <= PLAIN and not self.tol:
            self._run_plain(x, y)
            return
        if not self.tol and (self.mechanism == "halfspace" or self.mechanism is None and len(self.eps) == 1):
            self._run_wide(x, y)
            return
        w = self.w
        old = np.seterr(over="ignore", invalid="ignore")  # weights that grow beyond all bounds are told of below
        for a in range(0, len(x), 4096):
            noisy = self._noise(min(4096, len(x) - a), d) if self.mechanism else None
            for k in range(a, min(a + 4096, len(x))):
                if self.tol and not self.going.any():
                    break
                g = _slopes(self.kind, w @ x[k], y[k])[:, None] * x[k] + self.lam * w
                if noisy:
                    g = noisy(k - a, np.minimum(np.maximum(g, -1), 1))
                self.seen += 1
                move = step_size(self.seen, self.gamma0) * g
                if not self.tol:
                    w -= move
                    continue
                w -= move * self.going[:, None]
                self.going &= np.abs(move).max(1) >= self.tol
            if not np.isfinite(w).all():
                raise ArithmeticError("weights are no longer finite; take a smaller gamma0")
        np.seterr(**old)


    def _run_wide(self, x: np.ndarray, y: np.ndarray) -> None:
        """The steps of ``run`` for half-space reports, or one exact model, in few calls: what doesn't depend on the weights is made for a block of users at once."""
        w, d = self.w, x.shape[1]
        slope = _plain_slope(self.kind)
        g, add = np.empty_like(w), np.empty_like(w)
        old = np.seterr(over="ignore", invalid="ignore")
        for a in range(0, len(x), 1024):
            n = min(1024, len(x) - a)
            steps = self.gamma0 / np.sqrt(np.arange(self.seen + 1, self.seen + n + 1))
            self.seen += n
            if not self.mechanism:
                for p, t, step in zip(x[a : a + n], y[a : a + n].tolist(), steps.tolist()):
                    np.multiply(p, slope(float(w[0] @ p), t), out=g[0])
                    np.multiply(w, self.lam, out=add)
                    g += add
                    g *= step
                    w -= g
            else:
                # a sign of the vertex is 1 where the gradient is above 2u - 1; outside of [-1, 1] it needs no clamp for that
                floor, alike, size = self._vertices(n, d)
                far = steps[:, None, None] * size[:, None]
                for p, t, low, same, up, down in zip(x[a : a + n], y[a : a + n], floor, alike, far, -far):
                    np.multiply(_slopes(self.kind, w @ p, t)[:, None], p, out=g)
                    np.multiply(w, self.lam, out=add)
                    g += add
                    w -= np.where((g > low) == same, up, down)
            if not np.isfinite(w).all():
                raise ArithmeticError("weights are no longer finite; take a smaller gamma0")
        np.seterr(**old)

    def _vertices(self, n: int, d: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The half-space draws of ``n`` users: (users, d) least gradients for a 1, (users, budgets, d) whether a place is sent as it is, and the sizes."""
        u = self.rng.random((n, 2 * d + 2))
        inside, other = (np.searchsorted(np.array(c), u[:, 2 * d], "right") for c in C.halfspace_cdf(d))
        own = np.where(u[:, 2 * d + 1, None] < np.array([C.halfspace_prob(d, float(e)) for e in self.eps]), inside[:, None], other[:, None])
        return 2 * u[:, :d] - 1, _ranks(u[:, d : 2 * d])[:, None, :] < own[:, :, None], np.array([C.halfspace_scale(d, float(e)) for e in self.eps])

    def _run_plain(self, x: np.ndarray, y: np.ndarray) -> None:
        """The steps of ``run`` on plain numbers, a model after the other: a few numbers are less work than a call of an array function."""
        d = x.shape[1]
        for a in range(0, len(x), 4096):
            n = min(4096, len(x) - a)
            steps = (self.gamma0 / np.sqrt(np.arange(self.seen + 1, self.seen + n + 1))).tolist()
            users = list(zip(x[a : a + n].tolist(), y[a : a + n].tolist(), steps))
            draws = self._draws(n, d)
            for e in range(len(self.eps)):
                self.w[e] = _plain_steps(self.kind, self.lam, self.mechanism, self.w[e].tolist(), users, draws and draws(e))
            self.seen += n
            if not np.isfinite(self.w).all():
                raise ArithmeticError("weights are no longer finite; take a smaller gamma0")

    def _draws(self, n: int, d: int):
        """The draws of ``_noise`` as lists: a function of the budget's number."""
        if not self.mechanism:
            return None
        scale = [C.report_scale(float(e)) for e in self.eps]
        if self.mechanism == "laplace":
            u = self.rng.random((n, d)) - 0.5
            unit = -np.sign(u) * np.log(np.maximum(1 - 2 * np.abs(u), 1e-300)) * 2 * d
            return lambda e: (unit / self.eps[e]).tolist()
        if self.mechanism == "one_coordinate":
            u = self.rng.random((n, 2))
            at = np.minimum((u[:, 0] * d).astype(np.int64), d - 1).tolist()
            toss = u[:, 1].tolist()
            return lambda e: (at, toss, scale[e], scale[e] * d)
        u = self.rng.random((n, 2 * d + 2))
        rank = _ranks(u[:, d : 2 * d])
        inside, other = (np.searchsorted(np.array(c), u[:, 2 * d], "right") for c in C.halfspace_cdf(d))
        vertex = u[:, :d].tolist()
        return lambda e: (vertex, (rank < np.where(u[:, 2 * d + 1] < C.halfspace_prob(d, float(self.eps[e])), inside, other)[:, None]).tolist(), C.halfspace_scale(d, float(self.eps[e])))


def _plain_slope(kind: str):
    if kind == "linear":
        return lambda s, y: 2 * (s - y)
    if kind == "logistic":
        exp = math.exp
        return lambda s, y: -y / (1 + exp(y * s if y * s < 700 else 700))
    return lambda s, y: -y if y * s < 1 else 0.0


def _plain_steps(kind: str, lam: float, mechanism: str | None, w: list[float], users: list[tuple[list[float], float, float]], draws) -> list[float]:
    """Weights after a step for each of ``users``, (x, y, step size); ``draws`` are those of ``Walk._draws``."""
    slope = _plain_slope(kind)
    if mechanism is None:
        for x, y, step in users:
            s = 0.0
            for v, p in zip(w, x):
                s += v * p
            g = slope(s, y)
            w = [v - step * (g * p + lam * v) for v, p in zip(w, x)]
        return w
    if mechanism == "one_coordinate":
        at, toss, scale, size = draws
        for (x, y, step), j, t in zip(users, at, toss):
            s = 0.0
            for v, p in zip(w, x):
                s += v * p
            g = slope(s, y) * x[j] + lam * w[j]
            g = -1.0 if g < -1.0 else 1.0 if g > 1.0 else g
            w[j] -= step * (size if t < 0.5 + g / (2 * scale) else -size)
        return w
    if mechanism == "laplace":
        for (x, y, step), noise in zip(users, draws):
            s = 0.0
            for v, p in zip(w, x):
                s += v * p
            b = slope(s, y)
            for j, p in enumerate(x):
                g = b * p + lam * w[j]
                w[j] -= step * ((-1.0 if g < -1.0 else 1.0 if g > 1.0 else g) + noise[j])
        return w
    vertex, alike, size = draws
    for (x, y, step), draw, same in zip(users, vertex, alike):
        s = 0.0
        for v, p in zip(w, x):
            s += v * p
        b = slope(s, y)
        far = step * size
        for j, p in enumerate(x):
            g = b * p + lam * w[j]
            g = -1.0 if g < -1.0 else 1.0 if g > 1.0 else g
            w[j] -= far if (draw[j] < (1 + g) / 2) == same[j] else -far
    return w


def _ranks(u: np.ndarray) -> np.ndarray:
    """Rank of each number in its row."""
    out = np.empty(u.shape, np.int64)
    np.put_along_axis(out, u.argsort(1), np.arange(u.shape[1])[None, :], 1)
    return out


def fold_users(x: np.ndarray, y: np.ndarray, kind: str, lam: float, gamma0: float, mechanism: str | None = None, eps: float = 1.0, seed: int = 42, tol: float = 0.0) -> np.ndarray:
    """Descent over users in the given order, one per step; weights of the last step."""
    walk = Walk(kind, lam, gamma0, mechanism, [eps], seed, tol)
    walk.run(x, y)
    return walk.w[0]


def sgd(users: DataFrame, models: list[Model], kind: str, lam: float = 1e-4, gamma0: float | None = None, mechanism: str | None = None, max_users: int | None = None, seed: int = 42) -> DataFrame:
    """(model, users, weights) of sequential descent: each model sees its users in the order of a keyed number, all of them or the first ``max_users``.

    ``gamma0`` defaults to 1, but to 1/(2d) for exact linear regression, which diverges on wide data at 1.
    """
    folds: dict[int, list[tuple[str, float]]] = {}
    for m in models:
        folds.setdefault(m.fold, []).append((m.name, m.eps))
    part = users
    if max_users is not None and "base" not in users.columns:
        n = users.count()
        # what the visiting order can reach, with a margin against its randomness; the exact cut is made per model
        part = users.where(F.col("ub") < min(1.0, 2.0 * max_users / max(1, n) + 50 / max(1, n)))
    numbers = list(folds)
    dim = models[0].dim
    if dim > PLAIN and mechanism in (None, "halfspace"):
        g = gamma0 if gamma0 is not None else (1.0 if mechanism or kind != "linear" else 1 / (2 * dim))
        parts = min(len(folds), 1 + sum(m.dim for m in models) // 512)
        return walked(_streams(part, parts, False), [(numbers.index(m.fold) % parts, m.fold, m.name, m.eps) for m in models], dim, kind, lam, g, mechanism is not None, seed, max_users)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        walk: Walk | None = None
        seen, own = 0, -1
        for batch in batches:
            for own, fold, x, y in _unpacked(batch, False):
                if walk is None:
                    g = gamma0 if gamma0 is not None else (1.0 if mechanism or kind != "linear" else 1 / (2 * x.shape[1]))
                    walk = Walk(kind, lam, g, mechanism, [eps for _, eps in folds[numbers[own]]], seed)
                keep = fold != numbers[own]
                x, y = x[keep], y[keep]
                if max_users is not None:
                    x, y = x[: max_users - seen], y[: max_users - seen]
                if len(x):
                    walk.run(x, y)
                    seen += len(x)
        if seen:
            names = [name for name, _ in folds[numbers[own]]]
            yield pa.RecordBatch.from_arrays([pa.array(names), pa.array([seen] * len(names)), pa.array(walk.w.tolist())], names=["model", "users", "weights"])

    return _streams(part, len(folds), False).mapInArrow(work, "model string, users long, weights array<double>")
