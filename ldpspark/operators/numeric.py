"""Reports of numeric tuples. Each function keeps only the user key and the report, never the value.

Only signs are reported, as integers: their sums are exact and do not depend on the order of rows. The scale is applied to the
sums, once.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ldpspark.functions import constants as C
from ldpspark.functions.rng import choice, uniform


def sign_probability(value: Column, eps: float | Column) -> Column:
    """Probability of +1 for a value on [-1, 1]: affine in the value, with a ratio of e^eps between the two ends."""
    if isinstance(eps, Column):
        t = (F.exp(eps) - 1) / (2 * (F.exp(eps) + 1))
    else:
        t = F.lit(1 / (2 * C.report_scale(eps)))
    return value * t + F.lit(0.5)


def laplace_report(df: DataFrame, names: list[str], eps: float, seed: int = 42, run: int | Column = 0, mode: str = "md5") -> DataFrame:
    """Every attribute plus Laplace noise of scale 2d/eps: ``ukey`` and the noisy attributes (keeps ``run`` if the frame has it)."""
    scale = 2 * len(names) / eps

    def noisy(name: str) -> Column:
        u = uniform("ukey", f"lap:{name}", seed, run, mode) - 0.5
        inner = F.greatest(1 - 2 * F.abs(u), F.lit(2.0**-53))
        return (F.col(name) - F.lit(scale) * F.signum(u) * F.ln(inner)).alias(name)

    return df.select("ukey", *_run(df), *[noisy(n) for n in names])


def _run(df: DataFrame) -> list[str]:
    return [c for c in ("run",) if c in df.columns]


def one_coordinate_report(df: DataFrame, names: list[str], eps: float | None = None, seed: int = 42, run: int | Column = 0, mode: str = "md5", attr_choice: str = "private", eps_col: str | None = None) -> DataFrame:
    """One attribute, drawn evenly, as one sign: ``ukey``, ``j``, ``sign``.

    ``attr_choice='public_hash'`` draws j from a hash of the user key alone, which the collector can repeat, so that the sign is all that is
    sent. ``eps_col`` takes each user's own epsilon, which is public and reported along.
    """
    d = len(names)
    if attr_choice == "public_hash":
        j = choice("ukey", "public", d, seed=0, mode=mode)
    else:
        j = choice("ukey", "attr", d, seed=seed, run=run, mode=mode)
    drawn = df.withColumn("j", j)
    value = F.element_at(F.array(*[F.col(n) for n in names]), F.col("j") + 1)
    p = sign_probability(value, F.col(eps_col) if eps_col else eps)
    sign = F.when(uniform("ukey", "toss", seed, run, mode) < p, 1).otherwise(-1)
    return drawn.select("ukey", *_run(df), "j", sign.alias("sign"), *([F.col(eps_col).alias("eps")] if eps_col else []))


def halfspace_report(df: DataFrame, names: list[str], eps: float, variant: str = "repaired", seed: int = 42, run: int | Column = 0, mode: str = "md5") -> DataFrame:
    """Signs of all attributes at once: ``ukey``, ``signs`` (array of -1 and 1).

    The tuple is first rounded to signs v. A toss picks the half-space of vectors that agree with v in more than half of the places, or the other one. The
    number of agreeing places comes from that side's distribution, and which places they are from the order of one
    more uniform number per place. So no set of 2^d vectors is listed. ``printed`` breaks the guarantee for even d and exists to show it.
    """
    d = len(names)
    inside, other = C.halfspace_cdf(d)
    v = [F.when(uniform("ukey", f"round:{n}", seed, run, mode) < (F.col(n) + 1) / 2, 1).otherwise(-1).alias(f"_v{i}") for i, n in enumerate(names)]
    r = [uniform("ukey", f"subset:{n}", seed, run, mode).alias(f"_r{i}") for i, n in enumerate(names)]
    agree = uniform("ukey", "agree", seed, run, mode).alias("_agree")
    side = (uniform("ukey", "side", seed, run, mode) < C.halfspace_prob(d, eps, variant)).alias("_side")
    drawn = df.select("ukey", *_run(df), *v, *r, agree, side)
    places = lambda cdf: sum((F.when(F.col("_agree") >= x, 1).otherwise(0) for x in cdf[:-1]), F.lit(0))
    a = F.when(F.col("_side"), places(inside)).otherwise(places(other))
    bound = F.element_at(F.array_sort(F.array(*[F.col(f"_r{i}") for i in range(d)])), F.greatest(F.col("_a"), F.lit(1)))
    with_a = drawn.withColumn("_a", a).withColumn("_bound", F.when(F.col("_a") == 0, F.lit(-1.0)).otherwise(bound))
    signs = F.array(*[F.when(F.col(f"_r{i}") <= F.col("_bound"), F.col(f"_v{i}")).otherwise(-F.col(f"_v{i}")) for i in range(d)])
    return with_a.select("ukey", *_run(df), signs.alias("signs"))


def identity(df: DataFrame, names: list[str]) -> DataFrame:
    """No privacy: the values themselves."""
    return df.select("ukey", *names)


def pure_noise(df: DataFrame, names: list[str], seed: int = 42, mode: str = "md5") -> DataFrame:
    """No use: values that do not depend on the user's."""
    return df.select("ukey", *[(2 * uniform("ukey", f"noise:{n}", seed, 0, mode) - 1).alias(n) for n in names])


def bits_per_user(method: str, d: int, k: tuple[int, ...] = (), public_choice: bool = True) -> float:
    """Bits that a user sends: reals count as 64."""
    index = 0 if public_choice else math.ceil(math.log2(max(d, 2)))
    if method == "laplace":
        return 64 * d
    if method == "half_space":
        return d
    if method in ("one_coordinate", "mixed"):
        return 1 + index
    if method == "hybrid":
        return (d - len(k)) + sum(1 + (0 if public_choice else math.ceil(math.log2(max(x, 2)))) for x in k)
    raise ValueError(f"unknown method {method!r}")
