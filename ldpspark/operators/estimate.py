"""Estimators: sums of signs, decoded and scaled once. Every shuffle here carries sums, one row per task and key at most."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ldpspark.functions import constants as C
from ldpspark.operators.categorical import parity_sign, random_sign


def exact_mean(df: DataFrame, names: list[str]) -> DataFrame:
    """(attr, exact)."""
    one = df.agg(*[F.avg(n).alias(n) for n in names])
    return one.select(F.explode(F.array(*[F.struct(F.lit(n).alias("attr"), F.col(n).alias("exact")) for n in names])).alias("x")).select("x.*")


def exact_histogram(df: DataFrame, columns: list[tuple[str, int]]) -> DataFrame:
    """(attr, code, exact): frequencies of all codes of the domain, zeros included."""
    spark = df.sparkSession
    pairs = F.array(*[F.struct(F.lit(n).alias("attr"), F.col(n).cast("int").alias("code")) for n, _ in columns])
    seen = df.select(F.explode(pairs).alias("x")).groupBy("x.attr", "x.code").agg(F.count(F.lit(1)).alias("c"))
    domain = spark.createDataFrame([(n, v) for n, k in columns for v in range(k)], "attr string, code int")
    n = seen.where(F.col("attr") == columns[0][0]).agg(F.sum("c").alias("n"))
    # the domain is public and small; n is one row
    return F.broadcast(domain).join(seen, ["attr", "code"], "left").crossJoin(F.broadcast(n)).select("attr", "code", (F.coalesce("c", F.lit(0)) / F.col("n")).alias("exact"))


def mean_dense(reports: DataFrame, names: list[str]) -> DataFrame:
    """(attr, estimate) of reports that hold every attribute."""
    return exact_mean(reports, names).withColumnRenamed("exact", "estimate")


def sign_sums(reports: DataFrame, *keys: str) -> DataFrame:
    """(keys, total, reports)."""
    return reports.groupBy(*keys).agg(F.sum("sign").cast("long").alias("total"), F.count(F.lit(1)).alias("reports"))


def mean_sparse(reports: DataFrame, names: list[str], eps: float, normalise: str = "all") -> DataFrame:
    """(j, attr, estimate): scaled mean over all users, or with ``normalise='cohort'`` over those who drew the attribute."""
    c, d = C.report_scale(eps), len(names)
    sums = sign_sums(reports, "j").withColumn("n", F.sum("reports").over(Window.partitionBy()))
    if normalise == "cohort":
        value = c * F.col("total") / F.col("reports")
    elif normalise == "all":
        value = c * d * F.col("total") / F.col("n")
    else:
        raise ValueError(f"unknown normalisation {normalise!r}")
    label = F.element_at(F.array(*[F.lit(n) for n in names]), F.col("j") + 1)
    return sums.select("j", label.alias("attr"), value.alias("estimate"))


def mean_halfspace(reports: DataFrame, names: list[str], eps: float) -> DataFrame:
    """(attr, estimate) of half-space reports."""
    b = C.halfspace_scale(len(names), eps)
    sums = reports.agg(F.count(F.lit(1)).alias("n"), *[F.sum(F.col("signs")[i]).alias(f"s{i}") for i in range(len(names))])
    rows = F.array(*[F.struct(F.lit(n).alias("attr"), (F.lit(b) * F.col(f"s{i}") / F.col("n")).alias("estimate")) for i, n in enumerate(names)])
    return sums.select(F.explode(rows).alias("x")).select("x.*")


def proportion(reports: DataFrame, scale: float) -> DataFrame:
    """(n, positive): share of +1 behind randomised signs, (1 + scale * mean) / 2."""
    return reports.agg(F.count(F.lit(1)).alias("n"), ((1 + scale * F.sum("sign") / F.count(F.lit(1))) / 2).alias("positive"))


def decode(sums: DataFrame, k: int, n: Column, eps: float, sign) -> DataFrame:
    """(code, estimate) from sums per matrix row; ``sign(s, code)`` is the matrix. The domain, public and small, is broadcast to the sums."""
    codes = sums.sparkSession.range(k).select(F.col("id").cast("int").alias("code"))
    both = sums.crossJoin(F.broadcast(codes)).withColumn("part", F.col("total") * sign(F.col("s"), F.col("code")))
    return both.groupBy("code").agg(F.sum("part").alias("dot"), F.sum("reports").alias("n")).select("code", (F.lit(C.report_scale(eps)) * F.col("dot") / n).alias("estimate"))


def decode_orthogonal(reports: DataFrame, k: int, eps: float) -> DataFrame:
    return decode(sign_sums(reports, "s"), k, F.col("n"), eps, parity_sign)


def decode_projection(reports: DataFrame, k: int, eps: float, label: str = "", seed: int = 42, mode: str = "md5") -> DataFrame:
    return decode(sign_sums(reports, "s"), k, F.col("n"), eps, lambda s, v: random_sign(s, v, label, seed, mode))


def decode_fast(reports: DataFrame, k: int, eps: float) -> DataFrame:
    """The orthogonal decoder by a butterfly: log2 K rounds, each pairing rows that differ in one bit.

    Each round is a grouping of K rows by the row without that bit, so a domain too large for K^2 products still decodes in K log K.
    """
    order = C.orthogonal_order(k)
    sums = sign_sums(reports, "s")
    n = sums.agg(F.sum("reports").alias("n"))
    level = sums.select(F.col("s").cast("bigint").alias("s"), "total")
    bit = 1
    while bit < order:
        low = F.col("s").bitwiseAND(F.lit(order - 1 - bit))
        up = F.when(F.col("s").bitwiseAND(F.lit(bit)) == 0, 1).otherwise(-1)
        halves = level.groupBy(low.alias("base")).agg(F.sum("total").alias("plus"), F.sum(F.col("total") * up).alias("minus"))
        level = halves.select(F.explode(F.array(F.struct(F.col("base").alias("s"), F.col("plus").alias("total")), F.struct((F.col("base") + bit).alias("s"), F.col("minus").alias("total")))).alias("x")).select("x.*")
        bit *= 2
    return level.where(F.col("s") < k).crossJoin(F.broadcast(n)).select(F.col("s").cast("int").alias("code"), (F.lit(C.report_scale(eps)) * F.col("total") / F.col("n")).alias("estimate"))


def project_simplex(estimates: DataFrame, by: list[str], mode: str = "none") -> DataFrame:
    """Post-processing of frequencies: ``none``, ``clip`` to [0, 1], or ``norm`` (clip, then divide by the sum of the attribute)."""
    if mode == "none":
        return estimates
    clipped = estimates.withColumn("estimate", F.greatest(F.lit(0.0), F.least(F.lit(1.0), F.col("estimate"))))
    if mode == "clip":
        return clipped
    if mode != "norm":
        raise ValueError(f"unknown mode {mode!r}")
    total = F.sum("estimate").over(Window.partitionBy(*by))
    return clipped.withColumn("estimate", F.when(total > 0, F.col("estimate") / total).otherwise(F.lit(0.0)))


def central_laplace(df: DataFrame, names: list[str], eps: float, seed: int = 42) -> DataFrame:
    """(attr, estimate): exact means published with Laplace noise of scale 2d/(n eps), as a trusted collector could; a contrast, not a local method."""
    from ldpspark.functions.rng import uniform

    exact = exact_mean(df, names).crossJoin(F.broadcast(df.agg(F.count(F.lit(1)).alias("n"))))
    u = uniform("attr", "central", seed) - 0.5
    noise = -(2 * len(names) / eps) / F.col("n") * F.signum(u) * F.ln(F.greatest(1 - 2 * F.abs(u), F.lit(2.0**-53)))
    return exact.select("attr", (F.col("exact") + noise).alias("estimate"))
