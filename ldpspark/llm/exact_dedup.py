"""Exact duplicate removal by a 128-bit content hash, with a comparison of bytes inside each group."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ldpspark.llm.merging import id_filter, only_ids
from ldpspark.llm.staging import small_batches, stage

#: Fixed pattern: the separators 0x20 and 0x09-0x0D.
SPACES = r"[\x20\x09-\x0D]+"


def normalised(text: str = "text") -> Column:
    """Each run of separators as one space; null as the empty text."""
    return F.regexp_replace(F.coalesce(F.col(text).cast("string"), F.lit("")), SPACES, " ")


def hash128(text: Column) -> Column:
    return F.unhex(F.md5(text))


def _grouped(rows: DataFrame, *by: str) -> DataFrame:
    """Of each group the least id (nulls last), the first of its rows, and the number of rows; combined before the shuffle."""
    least = F.min(F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "row"))
    found = rows.groupBy(*by).agg(least.alias("least"), F.count(F.lit(1)).alias("group_size"))
    return found.select(*by, F.col("least.doc_id").alias("keep_id"), F.col("least.row").alias("keep_row"), "group_size")


def exact_groups(docs: DataFrame, digest: Callable[[Column], Column] = hash128) -> DataFrame:
    """Groups of rows with the same normalised text; the row of the least id stays.

    Returns one row per row of ``docs``: ``doc_id``, ``keep_id``, ``group_size``, ``kept``, ``text_sha256``.
    Null text counts as empty. Of rows that repeat the id that stays, one is kept. Null ids come last:
    a group of null ids only has a null ``keep_id`` and keeps one row. Further columns are ignored; an
    empty table gives an empty result. ``digest`` makes the group key; texts that share it without
    being equal are told apart by their bytes.

    No task gets the rows of a large group: least ids and texts are combined before they move, and
    the join back to the rows has one row per key on its other side, so that a hot key may be split.
    """
    small_batches(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), normalised().alias("norm")).withColumn("h", digest(F.col("norm")))
    sha = F.unhex(F.sha2("norm", 256)).alias("sha")
    slim = stage(rows.select("doc_id", "h", sha, F.monotonically_increasing_id().alias("row")), "hashes")
    groups = stage(_grouped(slim, "h"), "groups")

    several = groups.where("group_size > 1").select(F.xxhash64("h").alias("k"))
    inside = only_ids(rows.select("h", "norm", F.xxhash64("h").alias("k")), "k", id_filter(several, "k"))
    # texts of one hash are equal if the least of them is the greatest
    ends = inside.groupBy("h").agg(F.min("norm").alias("low"), F.max("norm").alias("high"))
    unequal = stage(ends.where(F.col("low") != F.col("high")).select("h"), "collisions")

    result = ["doc_id", "keep_id", "group_size", (F.col("row") == F.col("keep_row")).alias("kept"), F.lower(F.hex("sha")).alias("text_sha256")]
    out = slim.join(groups, "h")
    if unequal.isEmpty():
        return out.select(*result)
    mixed = stage(rows.join(unequal, "h", "left_semi").select("doc_id", "h", "norm", sha, F.monotonically_increasing_id().alias("row")), "collided")
    regrouped = mixed.join(_grouped(mixed, "h", "norm"), ["h", "norm"])
    return out.join(unequal, "h", "left_anti").select(*result).unionByName(regrouped.select(*result))


ORACLE = r"""
WITH n AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS t FROM documents)
SELECT doc_id, min(doc_id) OVER (PARTITION BY t) AS keep_id, count(*) OVER (PARTITION BY t) AS group_size,
       (doc_id IS NOT DISTINCT FROM min(doc_id) OVER (PARTITION BY t))
         AND row_number() OVER (PARTITION BY t, doc_id ORDER BY doc_id) = 1 AS kept,
       sha256(t) AS text_sha256
FROM n
"""
