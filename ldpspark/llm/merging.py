"""Fixed-size summaries of all rows (counters, bit maps), summed over the cluster slice by slice.

A summary has a size set in advance, whatever the data, so it may be sent to the executors.
Partial summaries travel as compressed slices, and each slice is merged by its own task.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ldpspark.llm.staging import lean

SLICES = 16
#: Tasks that merge a slice.
FAN = 2
SLICE_SCHEMA = "slice int, cells binary"


def slices_of(cells: np.ndarray) -> list[tuple[int, bytes]]:
    return [(i, zlib.compress(x.tobytes(), 1)) for i, x in enumerate(np.array_split(cells, SLICES))]


def _merger(dtype: np.dtype, op: np.ufunc) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, np.ndarray] = {}
        for batch in batches:
            for i, blob in zip(batch["slice"].to_pylist(), batch["cells"]):
                x = np.frombuffer(zlib.decompress(blob.as_buffer()), dtype)
                if i in total:
                    op(total[i], x, out=total[i])
                else:
                    total[i] = x.copy()
        for i, x in total.items():
            yield pa.RecordBatch.from_pydict({"slice": pa.array([i], pa.int32()), "cells": pa.array([zlib.compress(x.tobytes(), 1)], pa.binary())})

    return merge


def merged(slices: DataFrame, dtype: np.dtype, op: np.ufunc, size: int) -> np.ndarray:
    """All partial slices merged; the result (``size`` cells, ``FAN`` times) comes to the driver."""
    # the slice's number is the task's: no two slices meet in one, and none is empty
    task = F.col("slice") * FAN + F.pmod(F.crc32("cells"), F.lit(FAN)).cast("int")
    rows = slices.repartitionById(SLICES * FAN, task).mapInArrow(lean(_merger(dtype, op)), SLICE_SCHEMA).collect()
    out = np.zeros(size, dtype)
    bounds = np.cumsum([0] + [len(x) for x in np.array_split(out, SLICES)])
    for r in rows:
        x = np.frombuffer(zlib.decompress(bytes(r["cells"])), dtype)
        a = bounds[r["slice"]]
        out[a : a + len(x)] = op(out[a : a + len(x)], x)
    return out


BITS = 1 << 24


def _places(ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    from ldpspark.llm.textkernel import mix

    h = mix(ids.astype(np.int64).view(np.uint64) + np.uint64(0x9E3779B97F4A7C15))
    return h & np.uint64(BITS - 1), (h >> np.uint64(32)) & np.uint64(BITS - 1)


def id_filter(ids: DataFrame, column: str) -> np.ndarray:
    """A bit map of BITS bits (2 MB at any input) that holds every id of a column; it may hold others."""

    def mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits = None
        for batch in batches:
            if batch.num_rows:
                bits = np.zeros(BITS, bool) if bits is None else bits
                for p in _places(batch.column(0).to_numpy(zero_copy_only=False)):
                    bits[p] = True
        if bits is not None:
            i, blobs = zip(*slices_of(np.packbits(bits)))
            yield pa.RecordBatch.from_pydict({"slice": pa.array(i, pa.int32()), "cells": pa.array(blobs, pa.binary())})

    kept = ids.select(F.col(column).cast("long")).where(F.col(column).isNotNull())
    return merged(kept.mapInArrow(lean(mark), SLICE_SCHEMA), np.dtype(np.uint8), np.bitwise_or, BITS // 8)


def may_hold(packed: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """Whether each id may be in the bit map."""
    known = np.ones(len(ids), bool)
    for p in _places(ids):
        known &= ((packed[(p >> np.uint64(3)).astype(np.int64)] >> (7 - (p & np.uint64(7))).astype(np.uint8)) & 1).astype(bool)
    return known


def only_ids(df: DataFrame, column: str, bits: np.ndarray) -> DataFrame:
    """Rows whose id may be in the bit map: all that are, and few others. Removes them before any shuffle."""
    shared = df.sparkSession.sparkContext.broadcast(bits)
    at = df.columns.index(column)

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packed = shared.value
        for batch in batches:
            ids = batch.column(at)
            known = np.asarray(ids.is_valid())
            x = pd.Series(ids.fill_null(0).to_numpy(zero_copy_only=False)).to_numpy()
            out = batch.filter(pa.array(known & may_hold(packed, x)))
            if out.num_rows:
                yield out

    return df.mapInArrow(lean(keep), df.schema)
