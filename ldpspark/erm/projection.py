"""Random sign projection of feature vectors, done once per user."""

from __future__ import annotations

import hashlib
import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ldpspark.functions.rng import SPACE


def _unit(text: str) -> float:
    return int(hashlib.md5(text.encode()).hexdigest()[:13], 16) / SPACE


def matrix(r: int, d: int, seed: int = 42, scale: str = "one_over_d") -> list[list[float]]:
    """r x d signs over d, which keeps [-1, 1]; ``sqrt_r`` takes 1/sqrt(r), for distances, and needs a clamp."""
    step = {"one_over_d": 1 / d, "sqrt_r": 1 / math.sqrt(r)}[scale]
    return [[step if _unit(f"{seed}|0|proj|{i}|{j}") < 0.5 else -step for j in range(d)] for i in range(r)]


def project(x: Column, p: list[list[float]], limit: bool = False) -> Column:
    """P x as an array; the matrix (r d numbers) is part of the expression."""
    rows = F.array(*[F.array(*[F.lit(v) for v in row]) for row in p])
    out = F.transform(rows, lambda row: F.aggregate(F.zip_with(row, x, lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v))
    return F.transform(out, lambda v: F.greatest(F.lit(-1.0), F.least(F.lit(1.0), v))) if limit else out


def projected(df: DataFrame, p: list[list[float]], limit: bool = False) -> DataFrame:
    return df.withColumn("x", project(F.col("x"), p, limit))
