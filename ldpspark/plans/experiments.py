"""The study's experiments on the given tables.

Errors go as 1/(eps sqrt(n)); our tables are smaller than the study's extracts, so each grid can be given as printed or scaled to equal
eps sqrt(n). ``scaled_grid`` says by how much.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ldpspark.functions import constants as C
from ldpspark.operators import categorical as cat
from ldpspark.operators import estimate as est
from ldpspark.operators import numeric as num
from ldpspark.plans import replay
from ldpspark.plans.schema import TupleSpec, features
from ldpspark.plans.views import users
from ldpspark.sources.stored import stored

#: Fixed values of the study.
EPS_GRID = (0.05, 0.1, 0.2, 0.4, 0.8)
STUDY_USERS = {"li23": 9_000_000, "li18": 4_000_000}
REDUCED, LAMBDA, FOLDS, RUNS = 20, 1e-4, 10, 100
BETA = 0.05


def scaled_grid(n: int, study: str = "li23") -> list[float]:
    """The study's budgets times sqrt(study users / n)."""
    return [e * math.sqrt(STUDY_USERS[study] / n) for e in EPS_GRID]


def with_runs(df: DataFrame, runs: int) -> DataFrame:
    """Each user once per run; the run is part of every draw's key."""
    return df.withColumn("run", F.explode(F.sequence(F.lit(0), F.lit(runs - 1))))


def both_grids(n: int, study: str) -> list[tuple[str, float]]:
    """(grid, budget): the study's budgets as printed, and scaled to equal eps sqrt(n)."""
    return [("printed", e) for e in EPS_GRID] + [("scaled", e) for e in scaled_grid(n, study)]


def frequency_errors(spark: SparkSession, sf_dir: str, spec: TupleSpec, grid: list[float], runs: int = RUNS, n: int | None = None) -> DataFrame:
    """(method, eps, runs, mean_linf) of the sampler and of the hybrid's categories, over all values of all categories. The hybrid's matrices have their own rule's rows for ``n`` users."""
    data = stored(users(spark, sf_dir, spec), "users")
    n = n or data.count()
    places = spark.createDataFrame([(x[1], x[3], i) for i, x in enumerate(spec.domain())], "attr string, code int, at int")
    exact = est.exact_histogram(data, [(c.name, c.k) for c in spec.categoricals]).join(F.broadcast(places), ["attr", "code"]).select(F.lit(True).alias("codes"), "at", "exact")
    found = replay.run_errors(data, stored(exact, "exact"), spec, grid, runs, n, BETA, (replay.MIXED_CODES, replay.SPLIT_CODES))
    return found.select(F.when(F.col("kind") == replay.MIXED_CODES, "mixed").otherwise("hybrid").alias("method"), "eps", "runs", "mean_linf")


def mean_errors(spark: SparkSession, sf_dir: str, spec: TupleSpec, grid: list[float], runs: int = RUNS, readings: tuple[str, ...] = ("numeric_only",)) -> DataFrame:
    """(reading, method, eps, runs, mean_linf) of numeric means.

    ``mixed``: the tuple of all attributes, as the text describes; ``numeric_only``: the numbers alone with the whole budget, as the printed figures imply.
    """
    data = stored(users(spark, sf_dir, spec), "users")
    names = [a.name for a in spec.numerics]
    places = spark.createDataFrame([(x, i) for i, x in enumerate(names)], "attr string, at int")
    exact = est.exact_mean(data, names).join(F.broadcast(places), "attr").select(F.lit(False).alias("codes"), "at", "exact")
    kinds = {"mixed": (replay.MIXED_NUMBERS, replay.SPLIT_NUMBERS), "numeric_only": (replay.ALONE_MIXED, replay.ALONE_SPLIT)}
    found = replay.run_errors(data, stored(exact, "exact"), spec, grid, runs, data.count(), BETA, tuple(k for r in readings for k in kinds[r]))
    reading = F.when(F.col("kind").isin(*kinds["mixed"]), "mixed").otherwise("numeric_only")
    method = F.when(F.col("kind").isin(replay.MIXED_NUMBERS, replay.ALONE_MIXED), "mixed").otherwise("hybrid")
    return found.select(reading.alias("reading"), method.alias("method"), "eps", "runs", "mean_linf")


def learning_view(spark: SparkSession, sf_dir: str, spec: TupleSpec, kind: str) -> DataFrame:
    """(ukey, x, y): one-hot features without the target, and the net price, or its sign against the mean."""
    from ldpspark.plans.schema import binarise_at_mean

    data = users(spark, sf_dir, spec).withColumn("x", features(spec, "net_price"))
    if kind == "linear":
        return data.select("ukey", "x", F.col("net_price").alias("y"))
    return binarise_at_mean(data.select("ukey", "x", "net_price"), "net_price").select("ukey", "x", "y")


def dimension_sweep(spark: SparkSession, sf_dir: str, dims: list[int], eps: float, runs: int, mode: str = "xx") -> DataFrame:
    """(method, d, rms): root mean square error of the first d components of the embeddings, by method; half-space up to 16."""
    from ldpspark.sources.tables import load

    raw = load(spark, sf_dir, "embeddings")
    names = [f"e{i}" for i in range(max(dims))]
    flat = raw.select(F.col("vec_id").cast("string").alias("ukey"), *[F.col("embedding")[i].cast("double").alias(n) for i, n in enumerate(names)])
    data = stored(flat, "embeddings")
    exact = stored(est.exact_mean(data, names), "exact")
    many = with_runs(data, runs)
    parts = []
    for d in dims:
        own = names[:d]
        found = {}
        sparse = num.one_coordinate_report(many, own, eps, run=F.col("run"), mode=mode)
        totals = sparse.groupBy("run", "j").agg(F.sum("sign").alias("total"))
        n = many.groupBy("run").agg(F.count(F.lit(1)).alias("n"))
        label = F.element_at(F.array(*[F.lit(x) for x in own]), F.col("j") + 1)
        found["one_coordinate"] = totals.join(F.broadcast(n), "run").select("run", label.alias("attr"), (C.report_scale(eps) * d * F.col("total") / F.col("n")).alias("estimate"))
        lap = num.laplace_report(many, own, eps, run=F.col("run"), mode=mode).groupBy("run").agg(*[F.avg(x).alias(x) for x in own])
        found["laplace"] = lap.select("run", F.explode(F.array(*[F.struct(F.lit(x).alias("attr"), F.col(x).alias("estimate")) for x in own])).alias("x")).select("run", "x.*")
        if d <= 16:
            half = num.halfspace_report(many, own, eps, "repaired", run=F.col("run"), mode=mode)
            b = C.halfspace_scale(d, eps)
            sums = half.groupBy("run").agg(F.count(F.lit(1)).alias("n"), *[F.sum(F.col("signs")[i]).alias(x) for i, x in enumerate(own)])
            found["half_space"] = sums.select("run", F.explode(F.array(*[F.struct(F.lit(x).alias("attr"), (b * F.col(x) / F.col("n")).alias("estimate")) for x in own])).alias("x")).select("run", "x.*")
        for method, e in found.items():
            diff = F.col("estimate") - F.col("exact")
            parts.append(e.join(F.broadcast(exact), "attr").agg(F.sqrt(F.avg(diff * diff)).alias("rms")).select(F.lit(method).alias("method"), F.lit(d).alias("d"), "rms"))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def domain_sweep(data: DataFrame, columns: list[tuple[str, str, int]], eps: float, runs: int, m_override: int | None = None, mode: str = "xx") -> DataFrame:
    """(attr, k, oracle, m, rms) of both oracles on (label, column, k). ``data`` has ukey and the columns, and is stored by the caller."""
    parts = []
    n = data.count()
    many = with_runs(data, runs)
    for label, column, k in columns:
        exact = est.exact_histogram(data, [(column, k)]).select("code", "exact")
        for oracle in ("orthogonal", "projection"):
            m = C.orthogonal_order(k) if oracle == "orthogonal" else (m_override or C.projection_rows(k, n, eps, BETA))
            if oracle == "orthogonal":
                sent = cat.orthogonal_report(many.withColumn("ukey", F.concat_ws("~", "ukey", F.col("run").cast("string"))), column, k, eps, mode=mode, label=label)
                sign = cat.parity_sign
            else:
                sent = cat.random_projection_report(many.withColumn("ukey", F.concat_ws("~", "ukey", F.col("run").cast("string"))), column, m, eps, mode=mode, label=label)
                sign = lambda s, v, at=label: cat.random_sign(s, v, at, 42, mode)
            by_run = sent.withColumn("run", F.substring_index("ukey", "~", -1))
            sums = by_run.groupBy("run", "s").agg(F.sum("sign").alias("total"), F.count(F.lit(1)).alias("reports"))
            codes = F.broadcast(data.sparkSession.range(k).select(F.col("id").cast("int").alias("code")))
            dots = sums.crossJoin(codes).groupBy("run", "code").agg(F.sum(F.col("total") * sign(F.col("s"), F.col("code"))).alias("dot"), F.sum("reports").alias("n"))
            diff = C.report_scale(eps) * F.col("dot") / F.col("n") - F.col("exact")
            parts.append(dots.join(F.broadcast(exact), "code").agg(F.sqrt(F.avg(diff * diff)).alias("rms")).select(F.lit(label).alias("attr"), F.lit(k).alias("k"), F.lit(oracle).alias("oracle"), F.lit(m).alias("m"), "rms"))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out
