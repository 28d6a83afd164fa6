"""Reproducible shuffle into shards: a Feistel permutation with cycle walking over global row numbers."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ldpspark.llm.staging import lean, small_batches, stage
from ldpspark.llm.textkernel import mix

ROUNDS = 8


class Permutation:
    """A keyed bijection of 0..n-1. ``apply`` gives places, ``invert`` gives back row numbers."""

    def __init__(self, n: int, seed: int):
        self.n = n
        self.half = max(1, ((max(n, 2) - 1).bit_length() + 1) // 2)
        keys = np.random.Generator(np.random.PCG64(seed)).integers(0, 1 << 64, ROUNDS, dtype=np.uint64)
        self.keys = keys

    def _pass(self, x: np.ndarray, keys: np.ndarray, back: bool) -> np.ndarray:
        h, mask = np.uint64(self.half), np.uint64((1 << self.half) - 1)
        a, b = x >> h, x & mask
        for k in keys:
            if back:
                a, b = b ^ (mix(a + k) & mask), a
            else:
                a, b = b, a ^ (mix(b + k) & mask)
        return (a << h) | b

    def _walk(self, rows: np.ndarray, keys: np.ndarray, back: bool) -> np.ndarray:
        x = self._pass(rows.astype(np.uint64), keys, back)
        out = np.flatnonzero(x >= np.uint64(self.n))
        while len(out):
            x[out] = self._pass(x[out], keys, back)
            out = out[x[out] >= np.uint64(self.n)]
        return x.astype(np.int64)

    def apply(self, rows: np.ndarray) -> np.ndarray:
        return self._walk(rows, self.keys, False)

    def invert(self, places: np.ndarray) -> np.ndarray:
        return self._walk(places, self.keys[::-1], True)


def numbered(df: DataFrame, order: list[str | Column]) -> tuple[DataFrame, int]:
    """(row, number): the rows of ``df`` as structs with gapless global numbers from 0 in the given order; and the number of rows.

    Ranges are dealt out by Spark's range partitioning and sorted; a range's offset is the sum of the counts before it.
    Rows equal in ``order`` are interchangeable. Nulls come first.
    """

    def number(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, n = TaskContext.get().partitionId(), 0
        for batch in batches:
            k = batch.num_rows
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.full(k, part, np.int32)), pa.array(np.arange(n, n + k))], names=["row", "part", "nth"])
            n += k

    keys = [f"o{i}" for i in range(len(order))]
    packed = df.select(F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("row"), *[(F.col(f"`{o}`") if isinstance(o, str) else o).alias(k) for o, k in zip(order, keys)])
    schema = T.StructType([packed.schema["row"], T.StructField("part", T.IntegerType()), T.StructField("nth", T.LongType())])
    ranged = packed.repartitionByRange(*keys).sortWithinPartitions(*keys).select("row")
    parts = stage(ranged.mapInArrow(lean(number), schema), "ranges")
    sizes = parts.groupBy("part").agg(F.count(F.lit(1)).alias("size"))
    before = F.sum("size").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, Window.currentRow)) - F.col("size")
    # one row for each partition of the table
    offsets = sizes.select("part", before.alias("before"))
    return parts.join(F.broadcast(offsets), "part").select("row", (F.col("before") + F.col("nth")).alias("number")), parts.count()


def shuffled(df: DataFrame, order: list[str | Column], shards: int = 8, seed: int = 7) -> DataFrame:
    """``df`` with ``shard`` and ``slot``: place p of the permuted row numbers is shard p mod ``shards``, slot p div ``shards``.

    Counts of shards differ by one at most and slots are gapless from 0. Where a row went, and which row is at
    a slot, follow from ``Permutation`` alone. Columns of ``df`` named ``shard`` or ``slot`` give way to the new ones; all others stay as they are.
    Rows equal in ``order`` are interchangeable. An empty table gives an empty result.
    """
    small_batches(df.sparkSession)
    df = df.select(*[F.col(f"`{c}`") for c in df.columns if c.lower() not in ("shard", "slot")])
    rows, n = numbered(df, order)
    permutation = Permutation(n, seed)

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            p = permutation.apply(np.asarray(batch.column(1)))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array((p % shards).astype(np.int32)), pa.array(p // shards)], names=["row", "shard", "slot"])

    schema = T.StructType([rows.schema["row"], T.StructField("shard", T.IntegerType()), T.StructField("slot", T.LongType())])
    return rows.mapInArrow(lean(place), schema).select("row.*", "shard", "slot")


def document_shards(docs: DataFrame, shards: int = 8, seed: int = 7) -> DataFrame:
    """Shard and slot of every document, by the law ``rows``.

    Returns ``doc_id``, ``size`` (UTF-8 bytes plus 1), ``text_crc32``, ``law``, ``shard``, ``slot``, ``grown_shard`` (null: this law moves
    rows when the number of shards changes). Rows are numbered by id, then size, then checksum; null text counts as empty,
    null ids come first, and rows that agree in all three are interchangeable. Further columns are ignored.
    """
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text).alias("text_crc32"))
    out = shuffled(slim, ["doc_id", "size", "text_crc32"], shards, seed)
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
