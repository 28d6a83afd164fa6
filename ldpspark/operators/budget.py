"""Accounting of the privacy budget."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def split(eps: float, weights: list[float]) -> list[float]:
    """Shares that compose to eps."""
    return [eps * w / sum(weights) for w in weights]


def ledger(reports: DataFrame, user: str = "ukey", eps: str = "eps") -> DataFrame:
    """(user, reports, spent): by sequential composition, what a user's reports add up to."""
    return reports.groupBy(user).agg(F.count(F.lit(1)).alias("reports"), F.sum(eps).alias("spent"))


def running(reports: DataFrame, user: str, order: list[str], eps: str = "eps") -> DataFrame:
    """Adds ``spent_so_far`` along each user's reports."""
    return reports.withColumn("spent_so_far", F.sum(eps).over(Window.partitionBy(user).orderBy(*order).rowsBetween(Window.unboundedPreceding, Window.currentRow)))


def snapshot_ledger(events: DataFrame, user: str, ts: str, period: str, eps: float) -> DataFrame:
    """(user, periods, eps_per_period, eps_joint): each snapshot has its own guarantee; over many of them the sum is all that composition gives."""
    each = events.groupBy(user, F.window(ts, period).alias("w")).agg(F.lit(1).alias("one"))
    return each.groupBy(user).agg(F.count(F.lit(1)).alias("periods")).select(user, "periods", F.lit(eps).alias("eps_per_period"), (F.col("periods") * eps).alias("eps_joint"))
