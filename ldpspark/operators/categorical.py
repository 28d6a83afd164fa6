"""Reports of categories: coin flips for two values, sign-matrix oracles for more.

An oracle's matrix is never stored. The random one takes each sign from a keyed hash of (seed, row, value); the orthogonal one is a
Sylvester matrix, whose sign is the parity of the common bits of row and value.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ldpspark.functions import constants as C
from ldpspark.functions.rng import choice, uniform


def survey_report(df: DataFrame, column: str, p_truth: float = 0.5, seed: int = 42, mode: str = "md5") -> DataFrame:
    """The classic survey over -1 and 1: the truth with probability ``p_truth``, a fair coin's answer otherwise."""
    random = F.when(uniform("ukey", "survey:r", seed, 0, mode) < 0.5, 1).otherwise(-1)
    sign = F.when(uniform("ukey", "survey:h", seed, 0, mode) < p_truth, F.col(column)).otherwise(random)
    return df.select("ukey", sign.cast("int").alias("sign"))


def coin_flip_report(df: DataFrame, column: str, eps: float, seed: int = 42, mode: str = "md5") -> DataFrame:
    """The true sign with probability e^eps/(e^eps+1), the other one else."""
    keep = uniform("ukey", "toss", seed, 0, mode) < C.keep_probability(eps)
    return df.select("ukey", F.when(keep, F.col(column)).otherwise(-F.col(column)).cast("int").alias("sign"))


def parity_sign(row: Column, value: Column) -> Column:
    """Sign of the orthogonal matrix at (row, value)."""
    return 1 - 2 * (F.bit_count(row.cast("bigint").bitwiseAND(value.cast("bigint"))) % 2)


def random_sign(row: Column, value: Column, label: str, seed: int, mode: str = "md5") -> Column:
    """Sign of the random matrix of attribute ``label`` at (row, value)."""
    cell = F.concat_ws("|", row.cast("string"), value.cast("string"))
    return F.when(uniform(cell, f"phi:{label}", seed, 0, mode) < 0.5, 1).otherwise(-1)


def orthogonal_report(df: DataFrame, column: str, k: int, eps: float, seed: int = 42, run: int | Column = 0, mode: str = "md5", label: str = "") -> DataFrame:
    """A row s of the orthogonal matrix, drawn evenly, and its sign at the user's value, told by coin flip: ``ukey``, ``s``, ``sign``."""
    s = choice("ukey", f"row{label}", C.orthogonal_order(k), seed=seed, run=run, mode=mode)
    keep = F.when(uniform("ukey", f"flip{label}", seed, run, mode) < C.keep_probability(eps), 1).otherwise(-1)
    drawn = df.withColumn("s", s)
    return drawn.select("ukey", "s", (parity_sign(F.col("s"), F.col(column)) * keep).cast("int").alias("sign"))


def random_projection_report(df: DataFrame, column: str, m: int, eps: float, seed: int = 42, run: int | Column = 0, mode: str = "md5", label: str = "") -> DataFrame:
    """The same with a random matrix of m rows: ``ukey``, ``s``, ``sign``."""
    s = choice("ukey", f"row{label}", m, seed=seed, run=run, mode=mode)
    keep = F.when(uniform("ukey", f"flip{label}", seed, run, mode) < C.keep_probability(eps), 1).otherwise(-1)
    drawn = df.withColumn("s", s)
    return drawn.select("ukey", "s", (random_sign(F.col("s"), F.col(column), label, seed, mode) * keep).cast("int").alias("sign"))
