"""Cross validation of all methods of the study in shared passes."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ldpspark.erm.descent import STREAMED, Model, fold_sizes, packed, prepared, projected_rows, sgd, sliced, tested_rows, train
from ldpspark.erm.losses import evaluate
from ldpspark.erm.projection import matrix, projected
from ldpspark.functions import constants as C
from ldpspark.sources.stored import stored

READER = "spark.sql.parquet.columnarReaderBatchSize"


def tested(users: DataFrame, weights: DataFrame, kind: str) -> DataFrame:
    """(model, users, error) of each model on its held-out fold. ``weights``: (model, mfold, w), one row per model."""
    at = users.join(F.broadcast(weights), F.col("fold") == F.col("mfold"))
    return evaluate(at, F.col("w"), kind, "model")


def _named(eps: float, fold: int) -> str:
    return f"{eps!r}/{fold}"


def cross_validated(features: DataFrame, kind: str, n: int, dim: int, eps_grid: list[float], folds: int = 10, lam: float = 1e-4, r: int = 20, floor_share: int = 1000, methods: tuple[str, ...] = ("sgd_halfspace", "mgd", "mgd_projected", "sgd_exact"), seed: int = 42, mode: str = "xx", max_users: int | None = None, exact_users: int | None = None, gamma0: float = 1.0) -> DataFrame:
    """(method, eps, folds, error, users, trained, steps): error averaged over the folds. Users of a fold never train its models.

    Sequential descent sees all users of its folds, or at most ``max_users`` a model, exact descent ``exact_users``. Projection is for linear regression only and is left out otherwise. The folds and budgets of one method train together.
    ``users`` are those tested, ``trained`` and ``steps`` the mean number of users and of steps behind a model. A budget whose batch asks for more users than there are makes one step of all.
    """
    # only steps by jobs read slices; a margin, as folds differ in size
    by_jobs = any(m.startswith("mgd") for m in methods) and any(n / max(1, n // C.batch_size(size, e, n, floor_share)) > 0.8 * STREAMED for e in eps_grid for size in {dim, *((r,) if kind == "linear" else ())})
    users = prepared(features, folds, seed, mode)
    users = sliced(users) if by_jobs else users
    spark = users.sparkSession

    def found(method: str) -> list[tuple[str, float, int, float, int, int]]:
        data, size, rows = users, dim, plain
        if method == "mgd_projected":
            p = matrix(r, dim, seed)
            size, rows = r, stored(projected_rows(plain, p), "packed")
            data = sliced(projected(users.drop("slice"), p), "projected") if by_jobs else rows
        grid = [0.0] if method == "sgd_exact" else eps_grid
        if method.startswith("mgd"):
            steps = lambda e, f: max(1, trained[f] // C.batch_size(size, e, trained[f], floor_share)) if trained[f] else 1
            models = train(data, [Model(_named(e, f), size, e, steps(e, f), f) for e in grid for f in range(folds)], kind, lam, gamma0, rows=rows)
            made = [(m.name, m.fold, [float(w) for w in m.weights], trained[m.fold], len(m.history)) for m in models]
        else:
            models = [Model(_named(e, f), size, e, 1, f) for e in grid for f in range(folds)]
            mechanism = "halfspace" if method == "sgd_halfspace" else None
            out = sgd(rows, models, kind, lam, None, mechanism, max_users if mechanism else exact_users, seed).collect()
            made = [(w["model"], int(w["model"].rpartition("/")[2]), list(w["weights"]), w["users"], w["users"]) for w in out]
        taken = {name: (count, steps) for name, _, _, count, steps in made}
        errors = tested_rows(rows, [m[:3] for m in made], kind).collect()
        return [(method, float(e["model"].partition("/")[0]), e["users"], e["error"], *taken[e["model"]]) for e in errors]

    # a stream is one task: those of all methods share the cores
    asked = [m for m in methods if m != "mgd_projected" or kind == "linear"]
    # rows of packed users are large: a reader holds few at once
    held = spark.conf.get(READER)
    spark.conf.set(READER, 32)
    try:
        plain = stored(packed(users, n, dim), "packed")
        size_of = fold_sizes(plain)
        trained = {f: sum(size_of.values()) - size_of.get(f, 0) for f in range(folds)}
        with ThreadPoolExecutor(len(asked)) as pool:
            rows = [r for part in pool.map(inheritable_thread_target(spark)(found), asked) for r in part]
    finally:
        spark.conf.set(READER, held)
    every = spark.createDataFrame(rows, "method string, eps double, users long, error double, trained long, steps long")
    return every.groupBy("method", "eps").agg(F.count(F.lit(1)).alias("folds"), F.avg("error").alias("error"), F.sum("users").alias("users"), F.avg("trained").alias("trained"), F.avg("steps").alias("steps"))
