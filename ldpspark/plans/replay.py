"""Many runs of the study's collections, all budgets and methods, in one pass over the users.

A run of the study is one report of every user; its averages take a hundred runs at several budgets. Draws don't depend on the budget, and
all that the collector needs is linear in the reports, so each task draws its own users' reports of every run as arrays, decodes them at once,
and returns sums: a number per method, budget, run and value, whatever the number of users or of matrix rows. The mechanisms are those of ``operators``;
draws come from a mixing hash of the user's key, the run and the draw's place, so that reruns agree.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ldpspark.functions import constants as C
from ldpspark.plans.schema import TupleSpec
from ldpspark.sources.ship import ship

U = np.uint64
#: Users that are drawn for at once; each array of theirs fits a core's cache.
ROWS = 1 << 14
#: Users that a task holds to go through them run by run: the hybrid's signs are summed by matrix row over all of them and decoded once.
HELD = 1 << 18
#: Numbers of a random matrix up to which it is kept as a table.
TABLE = 1 << 23
#: What a sum is of: the sampler's numbers and categories, the hybrid's, and both methods on the numbers alone with the whole budget.
MIXED_NUMBERS, MIXED_CODES, SPLIT_NUMBERS, SPLIT_CODES, ALONE_MIXED, ALONE_SPLIT = range(6)
SUMS = "kind int, e int, run int, at int, total long"


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> U(32))) * U(0xD6E8FEB86659FD93)
    x = (x ^ (x >> U(32))) * U(0xD6E8FEB86659FD93)
    return x ^ (x >> U(32))


def _uniform(base: np.ndarray, first: int, count: int) -> np.ndarray:
    """(count, rows) uniform numbers, places ``first`` and on of each row's own sequence."""
    place = np.arange(first, first + count, dtype=np.uint64) * U(0x9E3779B97F4A7C15)
    return (_mix(base[None, :] + place[:, None]) >> U(11)).astype(np.float64) * 2.0**-53


def _signed(at: np.ndarray, minus: np.ndarray, n: int) -> np.ndarray:
    """Sums of signs by place 0..n-1."""
    both = np.bincount(at + n * minus, minlength=2 * n)
    return both[:n] - both[n:]


def _halfspace(v: np.ndarray, u: np.ndarray, cdfs: tuple[np.ndarray, np.ndarray], p: np.ndarray) -> np.ndarray:
    """(budgets, d) sums of the signs that the half-space sampler sends for columns ``v``; ``u`` holds 2 d + 2 draws a user."""
    d, n = v.shape
    vertex = u[:d] < (1 + v) / 2
    rank = np.zeros((d, n), np.int8 if d < 128 else np.int64)
    for i in range(d):
        for k in range(i):
            less = u[d + k] < u[d + i]
            rank[i] += less
            rank[k] += ~less
    inside, other = (np.searchsorted(c, u[2 * d], "right").astype(rank.dtype) for c in cdfs)
    out = np.empty((len(p), d), np.int64)
    for e, chance in enumerate(p):
        own = np.where(u[2 * d + 1] < chance, inside, other)
        out[e] = [2 * np.count_nonzero((rank[i] < own) == vertex[i]) - n for i in range(d)]
    return out


def replayed(data: DataFrame, spec: TupleSpec, grid: list[float], runs: int, n: int, beta: float, methods: tuple[int, ...], seed: int = 42) -> DataFrame:
    """(kind, e, run, at, total): signed sums by kind, number of the budget, run, and number of the attribute or of the value in ``spec.domain()``."""
    spark = data.sparkSession
    ship(spark)
    dn, d = spec.dn, spec.d
    domain = spec.domain()
    of = np.array([x[0] - dn for x in domain], np.int64)
    code = np.array([x[3] for x in domain], np.int64)
    order = np.array([C.orthogonal_order(c.k) for c in spec.categoricals], np.int64)
    start = np.searchsorted(of, np.arange(len(order)))
    parity = 1 - 2 * (np.bitwise_count(np.arange(order.max() if len(order) else 0)[:, None] & code[None, :]) & 1).astype(np.int64)
    budgets = np.array(grid)
    tilt = 1 / (2 * np.array([C.report_scale(e) for e in grid]))
    keep = np.array([C.keep_probability(e) for e in grid])
    split_keep = np.array([C.keep_probability(e / d) for e in grid])
    rows = np.array([[C.projection_rows(c.k, n, e / d, beta) for c in spec.categoricals] for e in grid], np.int64).reshape(len(grid), len(order))
    cdfs = tuple(np.array(x) for x in C.halfspace_cdf(dn)) if dn else ()
    chance = {k: np.array([C.halfspace_prob(dn, e) for e in b]) for k, b in ((SPLIT_NUMBERS, budgets * dn / d), (ALONE_SPLIT, budgets))} if dn else {}
    salt = _mix(U(seed) + np.arange(len(domain), dtype=np.uint64) * U(0xC2B2AE3D27D4EB4F))
    width = {MIXED_NUMBERS: dn, SPLIT_NUMBERS: dn, ALONE_MIXED: dn, ALONE_SPLIT: dn, MIXED_CODES: len(domain), SPLIT_CODES: len(domain)}

    def one_run(total: dict[int, np.ndarray], run: int, base: np.ndarray, v: np.ndarray, c: np.ndarray) -> None:
        each = np.arange(len(base))
        if MIXED_NUMBERS in total or MIXED_CODES in total:
            u = _uniform(base, 0, 3)
            j = np.minimum((u[0] * d).astype(np.int64), d - 1)
        if MIXED_NUMBERS in total:
            some = np.flatnonzero(j < dn)
            at, toss, value = j[some], u[1, some], v[j[some], some]
            for e in range(len(grid)):
                total[MIXED_NUMBERS][e, run] += _signed(at, toss >= 0.5 + value * tilt[e], dn)
        if MIXED_CODES in total:
            some = np.flatnonzero(j >= dn)
            a, toss = j[some] - dn, u[1, some]
            s = (u[2, some] * order[a]).astype(np.int64)
            cell = a * int(order.max()) + s
            own = (np.bitwise_count(s & c[a, some]) & 1).astype(bool)
            for e in range(len(grid)):
                sums = _signed(cell, own ^ (toss >= keep[e]), len(order) * int(order.max())).reshape(len(order), -1)
                total[MIXED_CODES][e, run] += (sums[of].T * parity).sum(0)
        for kind in (SPLIT_NUMBERS, ALONE_SPLIT):
            if kind in total:
                total[kind][:, run] += _halfspace(v, _uniform(base, 256 * kind, 2 * dn + 2), cdfs, chance[kind])
        if ALONE_MIXED in total:
            u = _uniform(base, 8, 2)
            j = np.minimum((u[0] * dn).astype(np.int64), dn - 1)
            value = v[j, each]
            for e in range(len(grid)):
                total[ALONE_MIXED][e, run] += _signed(j, u[1] >= 0.5 + value * tilt[e], dn)

    def minus(s: np.ndarray, a: int) -> np.ndarray:
        """Where rows ``s`` of a category's random matrix have -1, (rows, values)."""
        column = salt[start[a] : start[a] + spec.categoricals[a].k]
        return (_mix(s.astype(np.uint64)[:, None] * U(0x9E3779B97F4A7C15) + column[None, :]) >> U(63)).astype(bool)

    kept: dict[tuple[int, int], tuple[np.ndarray, np.ndarray]] = {}

    def table(m: int, a: int) -> tuple[np.ndarray, np.ndarray]:
        """The random matrix of m rows, for look-ups and, as signs, for decoding; sums over ``HELD`` users are exact in its type."""
        if (m, a) not in kept:
            found = minus(np.arange(m), a)
            kept[m, a] = found.ravel(), (1 - 2 * found.astype(np.int8)).astype(np.float32)
        return kept[m, a]

    def split_run(total: np.ndarray, run: int, base: np.ndarray, c: np.ndarray) -> None:
        """The hybrid's categories of a run, for the users that a task holds."""
        sums = {(e, a): 0 for e in range(len(grid)) for a in range(len(order))}
        for i in range(0, len(base), ROWS):
            for a, category in enumerate(spec.categoricals):
                row, toss = _uniform(base[i : i + ROWS], 16 + a, 1)[0], _uniform(base[i : i + ROWS], 16 + len(order) + a, 1)[0]
                code = c[a, i : i + ROWS]
                for e in range(len(grid)):
                    m = int(rows[e, a])
                    s = (row * m).astype(np.int64)
                    flip = toss >= split_keep[e]
                    if m * category.k <= TABLE:
                        sums[e, a] = sums[e, a] + _signed(s, table(m, a)[0][s * category.k + code] ^ flip, m)
                    else:
                        phi = minus(s, a)
                        alike = phi == (np.take_along_axis(phi, code[:, None], 1) ^ flip[:, None])
                        total[e, run, start[a] : start[a] + category.k] += 2 * alike.sum(0) - len(s)
        for (e, a), found in sums.items():
            if not np.isscalar(found):
                decoded = found.astype(np.float32) @ table(int(rows[e, a]), a)[1]
                total[e, run, start[a] : start[a] + spec.categoricals[a].k] += np.rint(decoded).astype(np.int64)

    def held(total: dict[int, np.ndarray], parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> None:
        h, v, c = (np.concatenate(x, axis=-1) for x in zip(*parts))
        for run in range(runs):
            base = _mix(h + U(run * 0xA0761D6478BD642F % (1 << 64)))
            if set(total) - {SPLIT_CODES}:
                for i in range(0, len(h), ROWS):
                    one_run(total, run, base[i : i + ROWS], v[:, i : i + ROWS], c[:, i : i + ROWS])
            if SPLIT_CODES in total:
                split_run(total[SPLIT_CODES], run, base, c)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = {k: np.zeros((len(grid), runs, width[k]), np.int64) for k in methods}
        parts, n = [], 0
        for batch in batches:
            for i in range(0, batch.num_rows, HELD // 4):
                part = batch.slice(i, HELD // 4)
                h = np.asarray(part["h"]).view(np.uint64)
                v = np.asarray(part["v"].flatten()).reshape(len(h), dn).T
                c = np.asarray(part["c"].flatten()).astype(np.int64).reshape(len(h), len(order)).T
                if n + len(h) > HELD:
                    held(total, parts)
                    parts, n = [], 0
                parts.append((h, v, c))
                n += len(h)
        if parts:
            held(total, parts)
        for kind, x in total.items():
            e, run, at = np.indices(x.shape)
            columns = [np.full(x.size, kind), e.ravel(), run.ravel(), at.ravel()]
            yield pa.RecordBatch.from_arrays([*[pa.array(y.astype(np.int32)) for y in columns], pa.array(x.ravel())], names=["kind", "e", "run", "at", "total"])

    slim = data.select(F.xxhash64(F.lit(seed), "ukey").alias("h"), F.array(*[F.col(x.name) for x in spec.numerics]).cast("array<double>").alias("v"), F.array(*[F.col(x.name) for x in spec.categoricals]).cast("array<int>").alias("c"))
    sc = spark.sparkContext
    dealt = slim.repartition(max(sc.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions"))), "h")
    return dealt.mapInArrow(work, SUMS).groupBy("kind", "e", "run", "at").agg(F.sum("total").alias("total"))


def run_errors(data: DataFrame, exact: DataFrame, spec: TupleSpec, grid: list[float], runs: int, n: int, beta: float, methods: tuple[int, ...], seed: int = 42) -> DataFrame:
    """(kind, eps, runs, mean_linf): largest error over all attributes or values, averaged over the runs. ``exact``: (codes boolean, at, exact)."""
    dn, d = spec.dn, spec.d
    scale = {
        MIXED_NUMBERS: lambda e: C.report_scale(e) * d,
        MIXED_CODES: lambda e: C.report_scale(e) * d,
        SPLIT_NUMBERS: lambda e: C.halfspace_scale(dn, e * dn / d),
        SPLIT_CODES: lambda e: C.report_scale(e / d),
        ALONE_MIXED: lambda e: C.report_scale(e) * dn,
        ALONE_SPLIT: lambda e: C.halfspace_scale(dn, e),
    }
    table = [(k, i, float(e), scale[k](e) / n, k in (MIXED_CODES, SPLIT_CODES)) for k in methods for i, e in enumerate(grid)]
    scales = data.sparkSession.createDataFrame(table, "kind int, e int, eps double, scale double, codes boolean")
    found = replayed(data, spec, grid, runs, n, beta, methods, seed).join(F.broadcast(scales), ["kind", "e"])
    off = found.join(F.broadcast(exact), ["codes", "at"]).withColumn("off", F.abs(F.col("scale") * F.col("total") - F.col("exact")))
    worst = off.groupBy("kind", "eps", "run").agg(F.max("off").alias("linf"))
    return worst.groupBy("kind", "eps").agg(F.count(F.lit(1)).alias("runs"), F.avg("linf").alias("mean_linf"))
