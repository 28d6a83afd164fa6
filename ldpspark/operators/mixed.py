"""Many attributes at once: the one-attribute sampler for mixed tuples, and the baselines that split the budget or build a product domain."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ldpspark.functions import constants as C
from ldpspark.functions.rng import choice, uniform
from ldpspark.operators.categorical import parity_sign, random_sign
from ldpspark.operators.numeric import halfspace_report, sign_probability
from ldpspark.plans.schema import TupleSpec


def rows_per_attribute(spec: TupleSpec, oracle: str, n: int, eps: float, beta: float, m_override: int | None = None) -> list[int]:
    """Matrix rows of each category under either oracle."""
    if oracle == "orthogonal":
        return [C.orthogonal_order(c.k) for c in spec.categoricals]
    return [m_override or C.projection_rows(c.k, n, eps, beta) for c in spec.categoricals]


def _matrix(spec: TupleSpec, oracle: str, seed: int, mode: str):
    """sign(row, value) of every category's matrix; all share one random function, with the attribute number in its key."""
    if oracle == "orthogonal":
        return lambda j, s, v: parity_sign(s, v)
    if oracle == "projection":
        return lambda j, s, v: random_sign(F.concat_ws("/", j.cast("string"), s.cast("string")), v, "m", seed, mode)
    raise ValueError(f"unknown oracle {oracle!r}")


def mixed_report(df: DataFrame, spec: TupleSpec, eps: float, seed: int = 42, oracle: str = "orthogonal", n: int = 0, beta: float = 0.05, run: int | Column = 0, mode: str = "md5", m_override: int | None = None) -> DataFrame:
    """One attribute of the tuple, drawn evenly: ``ukey``, ``j``, ``s`` (null for a number), ``sign``. One projection; the whole budget goes to that attribute."""
    d, dn = spec.d, spec.dn
    keep_run = [c for c in ("run",) if c in df.columns]
    drawn = df.withColumn("j", choice("ukey", "attr", d, seed=seed, run=run, mode=mode)).withColumn("u", uniform("ukey", "toss", seed, run, mode))
    number = sign = None
    if dn:
        value = F.element_at(F.array(*[F.col(a.name) for a in spec.numerics]), F.least(F.col("j") + 1, F.lit(dn)))
        number = F.when(F.col("u") < sign_probability(value, eps), 1).otherwise(-1)
    s: Column = F.lit(None).cast("int")
    if spec.categoricals:
        rows = rows_per_attribute(spec, oracle, n, eps, beta, m_override)
        size = F.element_at(F.array(*[F.lit(x) for x in rows]), F.greatest(F.col("j") - dn + 1, F.lit(1)))
        drawn = drawn.withColumn("s", F.when(F.col("j") >= dn, F.floor(uniform("ukey", "row", seed, run, mode) * size).cast("int")))
        s = F.col("s")
        code = F.element_at(F.array(*[F.col(c.name) for c in spec.categoricals]), F.greatest(F.col("j") - dn + 1, F.lit(1)))
        keep = F.when(F.col("u") < C.keep_probability(eps), 1).otherwise(-1)
        sign = _matrix(spec, oracle, seed, mode)(F.col("j"), s, code) * keep
    whole = number if sign is None else sign if number is None else F.when(F.col("j") < dn, number).otherwise(sign)
    return drawn.select("ukey", *keep_run, "j", s.alias("s"), whole.cast("int").alias("sign"))


def sums(reports: DataFrame, *more: str) -> DataFrame:
    """(more, j, s, total, reports, n): all that the collector needs, a few hundred rows."""
    by = Window.partitionBy(*more)
    grouped = reports.groupBy(*more, "j", "s").agg(F.sum("sign").cast("long").alias("total"), F.count(F.lit(1)).alias("reports"))
    return grouped.withColumn("n", F.sum("reports").over(by))


def mixed_means(totals: DataFrame, spec: TupleSpec, eps: float, *more: str) -> DataFrame:
    """(more, attr, estimate) of the numbers."""
    label = F.element_at(F.array(*[F.lit(a.name) for a in spec.numerics]), F.col("j") + 1)
    scale = C.report_scale(eps) * spec.d
    return totals.where(F.col("j") < spec.dn).select(*more, label.alias("attr"), (scale * F.col("total") / F.col("n")).alias("estimate"))


def mixed_frequencies(totals: DataFrame, spec: TupleSpec, eps: float, *more: str, seed: int = 42, oracle: str = "orthogonal", mode: str = "md5", factor: float | None = None) -> DataFrame:
    """(more, attr, code, estimate) of the categories; ``factor`` replaces d where every user reports every attribute."""
    sign = _matrix(spec, oracle, seed, mode)
    domain = totals.sparkSession.createDataFrame(spec.domain(), "dj int, attr string, k int, code int")
    both = totals.where(F.col("j") >= spec.dn).join(F.broadcast(domain), F.col("j") == F.col("dj"))
    part = F.col("total") * sign(F.col("j"), F.col("s"), F.col("code"))
    scale = C.report_scale(eps) * (spec.d if factor is None else factor)
    out = both.groupBy(*more, "attr", "code").agg(F.sum(part).alias("dot"), F.first("n").alias("n"))
    return out.select(*more, "attr", "code", (scale * F.col("dot") / F.col("n")).alias("estimate"))


def split_report(df: DataFrame, spec: TupleSpec, eps: float, seed: int = 42, oracle: str = "projection", n: int = 0, beta: float = 0.05, run: int | Column = 0, mode: str = "md5", share: float | None = None, m_override: int | None = None) -> DataFrame:
    """Every category of the tuple with an equal share of the budget: one row per user and attribute, ``ukey``, ``j``, ``s``, ``sign``."""
    part = eps / spec.d if share is None else share
    rows = rows_per_attribute(spec, oracle, n, part, beta, m_override)
    keep_run = [c for c in ("run",) if c in df.columns]
    pairs = F.array(*[F.struct(F.lit(spec.dn + i).alias("j"), F.lit(rows[i]).alias("m"), F.col(c.name).alias("code")) for i, c in enumerate(spec.categoricals)])
    long = df.select("ukey", *keep_run, F.explode(pairs).alias("x")).select("ukey", *keep_run, "x.*")
    key = F.concat_ws("|", F.col("ukey"), F.col("j").cast("string"))
    long = long.withColumn("s", F.floor(uniform(key, "row", seed, run, mode) * F.col("m")).cast("int"))
    keep = F.when(uniform(key, "flip", seed, run, mode) < C.keep_probability(part), 1).otherwise(-1)
    sign = _matrix(spec, oracle, seed, mode)(F.col("j"), F.col("s"), F.col("code")) * keep
    return long.select("ukey", *keep_run, "j", "s", sign.cast("int").alias("sign"))


def split_sums(reports: DataFrame, *more: str) -> DataFrame:
    """As ``sums``, but n counts users: each reports every attribute."""
    grouped = reports.groupBy(*more, "j", "s").agg(F.sum("sign").cast("long").alias("total"), F.count(F.lit(1)).alias("reports"))
    return grouped.withColumn("n", F.sum("reports").over(Window.partitionBy(*more, "j")))


def composite_code(columns: list[tuple[str, int]]) -> Column:
    """The tuple of categories as one code, mixed radix."""
    code: Column = F.lit(0)
    for name, k in columns:
        code = code * k + F.col(name)
    return code.cast("int")


def marginalise(cells: DataFrame, columns: list[tuple[str, int]]) -> DataFrame:
    """(attr, code, estimate): marginals as sums of estimated cells (code, estimate)."""
    rest = math.prod(k for _, k in columns)
    parts = []
    for name, k in columns:
        rest //= k
        parts.append(F.struct(F.lit(name).alias("attr"), (F.floor(F.col("code") / rest) % k).cast("int").alias("value")))
    long = cells.select("estimate", F.explode(F.array(*parts)).alias("x"))
    return long.groupBy(F.col("x.attr").alias("attr"), F.col("x.value").alias("code")).agg(F.sum("estimate").alias("estimate"))


def hybrid_report(df: DataFrame, spec: TupleSpec, eps: float, seed: int = 42, variant: str = "repaired", n: int = 0, beta: float = 0.05, run: int | Column = 0, mode: str = "md5") -> tuple[DataFrame, DataFrame]:
    """Half-space reports of the numbers with their share of the budget, and split random-projection reports of the categories with theirs."""
    numbers = halfspace_report(df, [a.name for a in spec.numerics], eps * spec.dn / spec.d, variant, seed, run, mode)
    return numbers, split_report(df, spec, eps, seed, "projection", n, beta, run, mode)
