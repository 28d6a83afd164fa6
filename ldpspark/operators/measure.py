"""Accuracy measures over estimates and exact answers."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def linf(estimates: DataFrame, exact: DataFrame, keys: list[str], by: list[str]) -> DataFrame:
    """(by, linf): largest absolute error. The exact answers, one row per attribute or value, are broadcast."""
    both = estimates.join(F.broadcast(exact), keys)
    return both.groupBy(*by).agg(F.max(F.abs(F.col("estimate") - F.col("exact"))).alias("linf"))


def averaged(errors: DataFrame, by: list[str]) -> DataFrame:
    """(by, runs, mean_linf)."""
    return errors.groupBy(*by).agg(F.count(F.lit(1)).alias("runs"), F.avg("linf").alias("mean_linf"))


def bias(estimates: DataFrame, exact: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, runs, bias, rms): mean and root mean square of estimate less exact over the runs."""
    diff = F.col("estimate") - F.col("exact")
    return estimates.join(F.broadcast(exact), keys).groupBy(*keys).agg(F.count(F.lit(1)).alias("runs"), F.avg(diff).alias("bias"), F.sqrt(F.avg(diff * diff)).alias("rms"))


def coverage(errors: DataFrame, radius: float, by: list[str]) -> DataFrame:
    """(by, runs, covered): share of runs whose largest error is within the radius."""
    return errors.groupBy(*by).agg(F.count(F.lit(1)).alias("runs"), F.avg(F.when(F.col("linf") <= radius, 1.0).otherwise(0.0)).alias("covered"))


def projection_distortion(signs: DataFrame, m: int) -> DataFrame:
    """(pairs, max_inner, rms_inner) over the unlike columns of a sign matrix given as (s, code, sign): a floor of the error that more reports do not lower."""
    a = signs.select("s", F.col("code").alias("l"), F.col("sign").alias("x"))
    b = signs.select("s", F.col("code").alias("r"), F.col("sign").alias("y"))
    inner = a.join(b, "s").where("l < r").groupBy("l", "r").agg((F.sum(F.col("x") * F.col("y")) / F.lit(m)).alias("inner"))
    return inner.agg(F.count(F.lit(1)).alias("pairs"), F.max(F.abs("inner")).alias("max_inner"), F.sqrt(F.avg(F.col("inner") * F.col("inner"))).alias("rms_inner"))
