"""Relational operators around a collection that Spark lacks or that need care at scale."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ldpspark.sources.stored import stored


def asof_join(left: DataFrame, right: DataFrame, on: str, by: list[str], values: list[str], bucket: Column | None = None) -> DataFrame:
    """Each left row with the ``values`` of the latest right row of its ``by`` at or before ``on``; null where there is none.

    Both sides are laid along the time line of their key and the last value is carried forward. ``bucket`` (a function of ``on`` that
    never falls as it grows) cuts a long line into pieces; each piece starts with what the ones before it ended with.
    """
    cell = bucket if bucket is not None else F.lit(0)
    carried = F.struct(*[F.col(v) for v in values])
    r = right.select(*by, on, F.lit(0).alias("_side"), carried.alias("_v"), cell.alias("_b"))
    own = [c for c in left.columns if c not in by and c != on]
    row = F.struct(*[F.col(c) for c in own])
    both = left.select(*by, on, F.lit(1).alias("_side"), F.lit(None).cast(r.schema["_v"].dataType).alias("_v"), cell.alias("_b"), row.alias("_row"))
    both = both.unionByName(r.withColumn("_row", F.lit(None).cast(both.schema["_row"].dataType)))
    line = Window.partitionBy(*by, "_b").orderBy(on, "_side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    ends = both.where("_side = 0").groupBy(*by, "_b").agg(F.max_by("_v", on).alias("_end"))
    pieces = both.select(*by, "_b").distinct().join(ends, [*by, "_b"], "left")
    before = Window.partitionBy(*by).orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)
    starts = pieces.select(*by, "_b", F.last("_end", ignorenulls=True).over(before).alias("_start"))
    out = both.withColumn("_last", F.last("_v", ignorenulls=True).over(line)).where("_side = 1").join(starts, [*by, "_b"], "left")
    value = F.coalesce("_last", "_start")
    return out.select(*by, on, *[F.col("_row")[c].alias(c) for c in own], *[value[v].alias(v) for v in values])


def band_join(df: DataFrame, value: str, bands: DataFrame, low: str = "lo", high: str = "hi") -> DataFrame:
    """Rows with the band that holds their value, low <= value < high. The band table is public and small, and broadcast."""
    return df.join(F.broadcast(bands), (F.col(value) >= F.col(low)) & (F.col(value) < F.col(high)))


def first_per_user(df: DataFrame, user: list[str], order: list[str]) -> DataFrame:
    """The first row of each user: bounds what one person contributes. An aggregate, so it combines before the shuffle."""
    rest = [c for c in df.columns if c not in user and c not in order]
    best = F.min(F.struct(*[F.col(c) for c in order], *[F.col(c) for c in rest])).alias("_x")
    return df.groupBy(*user).agg(best).select(*user, *[F.col("_x")[c].alias(c) for c in (*order, *rest)])


def numbered(df: DataFrame, order: list[Column], name: str) -> DataFrame:
    """Adds ``name``: gapless numbers from 0 in the given order. Ranges are sorted each for itself; a range's first number is the sum of the counts before it."""
    keys = [f"_o{i}" for i in range(len(order))]
    ranged = df.withColumns(dict(zip(keys, order))).repartitionByRange(*keys)
    parts = stored(ranged.withColumn("_part", F.spark_partition_id()), "ranges")
    sizes = parts.groupBy("_part").agg(F.count(F.lit(1)).alias("_size"))
    # one row for each range
    before = F.sum("_size").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, Window.currentRow)) - F.col("_size")
    nth = F.row_number().over(Window.partitionBy("_part").orderBy(*keys)) - 1
    return parts.withColumn("_nth", nth).join(F.broadcast(sizes.select("_part", before.alias("_before"))), "_part").withColumn(name, F.col("_before") + F.col("_nth")).select(*df.columns, name)


def batches(df: DataFrame, order: Column, size: int) -> DataFrame:
    """Adds ``batch``: places along a keyed order, cut into groups of ``size``."""
    return numbered(df, [order], "_place").withColumn("batch", F.floor(F.col("_place") / size).cast("int")).drop("_place")


def top_values(estimates: DataFrame, k: int) -> DataFrame:
    """The k values of largest estimate, ties by attribute and code."""
    return estimates.orderBy(F.desc("estimate"), "attr", "code").limit(k)
