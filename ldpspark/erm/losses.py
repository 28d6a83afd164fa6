"""Losses and gradients as column expressions over a feature array ``x`` and a target ``y``."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

KINDS = ("linear", "logistic", "svm")


def dot(x: Column, w: Column) -> Column:
    return F.aggregate(F.zip_with(x, w, lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)


def loss(kind: str, score: Column, y: Column) -> Column:
    """Squared error, log(1 + e^(-y score)) in a form that does not overflow, or hinge."""
    if kind == "linear":
        return (score - y) * (score - y)
    if kind == "logistic":
        z = -y * score
        return F.greatest(z, F.lit(0.0)) + F.log1p(F.exp(-F.abs(z)))
    if kind == "svm":
        return F.greatest(F.lit(0.0), 1 - y * score)
    raise ValueError(f"unknown loss {kind!r}")


def slope(kind: str, score: Column, y: Column) -> Column:
    """Derivative of the loss by the score; times x it is the gradient. At the hinge's kink: 0."""
    if kind == "linear":
        return 2 * (score - y)
    if kind == "logistic":
        z = y * score
        # 1 / (1 + e^z) without overflow
        e = F.exp(-F.abs(z))
        return -y * F.when(z >= 0, e / (1 + e)).otherwise(1 / (1 + e))
    if kind == "svm":
        return F.when(y * score < 1, -y).otherwise(F.lit(0.0))
    raise ValueError(f"unknown loss {kind!r}")


def gradient(kind: str, x: Column, y: Column, w: Column, lam: float) -> Column:
    """Gradient of the regularised loss at ``w``, an array."""
    g = slope(kind, dot(x, w), y)
    return F.zip_with(x, w, lambda a, b: a * g + lam * b)


def clamp(g: Column) -> Column:
    """Each coordinate on [-1, 1], so that it can be reported."""
    return F.transform(g, lambda v: F.greatest(F.lit(-1.0), F.least(F.lit(1.0), v)))


def weights(values: list[float]) -> Column:
    return F.array(*[F.lit(float(v)) for v in values])


def objective(df: DataFrame, w: list[float], kind: str, lam: float) -> DataFrame:
    """(risk, objective): mean loss, and with half lam |w|^2."""
    score = dot(F.col("x"), weights(w))
    penalty = lam / 2 * sum(v * v for v in w)
    return df.agg(F.avg(loss(kind, score, F.col("y"))).alias("risk")).withColumn("objective", F.col("risk") + F.lit(penalty))


def evaluate(df: DataFrame, w: Column, kind: str, *by: str) -> DataFrame:
    """(by, users, error): mean squared error, or the rate of wrong signs (a score of 0 counts as -1)."""
    score = dot(F.col("x"), w)
    if kind == "linear":
        error = (score - F.col("y")) * (score - F.col("y"))
    else:
        error = F.when((score > 0) == (F.col("y") > 0), 0.0).otherwise(1.0)
    return df.groupBy(*by).agg(F.count(F.lit(1)).alias("users"), F.avg(error).alias("error"))
