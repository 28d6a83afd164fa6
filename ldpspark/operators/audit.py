"""Privacy audits: output tables of the mechanisms by enumeration, and their largest log ratio over any two inputs."""

from __future__ import annotations

import itertools
import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ldpspark.functions import constants as C

Table = list[tuple[str, str, float]]


def corners(d: int) -> list[tuple[int, ...]]:
    return list(itertools.product((-1, 1), repeat=d))


def halfspace_outputs(t: tuple[float, ...], eps: float, variant: str) -> dict[tuple[int, ...], float]:
    d = len(t)
    p, size = C.halfspace_prob(d, eps, variant), C.halfspace_size(d)
    out = {y: 0.0 for y in corners(d)}
    for v in corners(d):
        w = math.prod((1 + x * s) / 2 for x, s in zip(t, v))
        if w:
            for y in out:
                agree = sum(a == b for a, b in zip(v, y))
                out[y] += w * (p / size if 2 * agree > d else (1 - p) / (2**d - size))
    return out


def one_coordinate_outputs(t: tuple[float, ...], eps: float) -> dict[tuple[int, int], float]:
    d, slope = len(t), 1 / (2 * C.report_scale(eps))
    return {(j, s): (0.5 + s * t[j] * slope) / d for j in range(d) for s in (-1, 1)}


def coin_flip_outputs(v: int, eps: float) -> dict[int, float]:
    p = C.keep_probability(eps)
    return {v: p, -v: 1 - p}


def oracle_outputs(v: int, rows: int, sign, eps: float) -> dict[tuple[int, int], float]:
    p = C.keep_probability(eps)
    return {(s, x): (p if x == sign(s, v) else 1 - p) / rows for s in range(rows) for x in (-1, 1)}


def output_table(name: str, d: int, eps: float, inputs: list | None = None) -> Table:
    """(input, output, probability) of a mechanism over its extreme inputs, or those of them that are given: sign vectors, or codes."""
    vectors = corners(d) if inputs is None else inputs
    parity = lambda s, v: 1 - 2 * (bin(s & v).count("1") % 2)
    if name.startswith("halfspace_"):
        given = {str(t): halfspace_outputs(t, eps, name.removeprefix("halfspace_")) for t in vectors}
    elif name == "one_coordinate":
        given = {str(t): one_coordinate_outputs(t, eps) for t in vectors}
    elif name == "coin_flip":
        given = {str(v): coin_flip_outputs(v, eps) for v in ((-1, 1) if inputs is None else [t[0] for t in inputs])}
    elif name == "orthogonal":
        given = {str(v): oracle_outputs(v, C.orthogonal_order(d), parity, eps) for v in (range(d) if inputs is None else inputs)}
    else:
        raise ValueError(f"unknown mechanism {name!r}")
    return [(i, str(o), p) for i, row in given.items() for o, p in row.items()]


def exact_epsilon(spark: SparkSession, cases: list[tuple[str, int, float]], inputs: list[list] | None = None) -> DataFrame:
    """(mechanism, d, eps, effective): the largest log ratio of any output's probabilities over two inputs, per case; over all extreme inputs, or each case's of ``inputs``."""
    rows = [(name, d, eps, i, o, p) for at, (name, d, eps) in enumerate(cases) for i, o, p in output_table(name, d, eps, inputs and inputs[at])]
    table = spark.createDataFrame(rows, "mechanism string, d int, eps double, input string, output string, p double")
    ends = table.groupBy("mechanism", "d", "eps", "output").agg(F.max("p").alias("high"), F.min("p").alias("low"))
    return ends.groupBy("mechanism", "d", "eps").agg(F.max(F.ln(F.col("high") / F.col("low"))).alias("effective"))


def empirical_epsilon(reports_a: DataFrame, reports_b: DataFrame, *output: str) -> DataFrame:
    """(outputs, runs, log_ratio): log ratio of how often each output occurs in many reports of two inputs; the largest magnitude estimates epsilon."""
    a = reports_a.groupBy(*output).agg(F.count(F.lit(1)).alias("a"))
    b = reports_b.groupBy(*output).agg(F.count(F.lit(1)).alias("b"))
    return a.join(b, list(output), "full").select(*output, F.coalesce("a", F.lit(0)).alias("a"), F.coalesce("b", F.lit(0)).alias("b"), F.ln(F.greatest("a", F.lit(1)) / F.greatest("b", F.lit(1))).alias("log_ratio"))
