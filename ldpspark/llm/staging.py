"""Tables written to the shared folder, so that lineage is cut and lost executors can be replaced."""

from __future__ import annotations

import ctypes
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from ldpspark.sources.ship import ship
from ldpspark.sources.stored import stored


def lean(work: Callable) -> Callable:
    """``work`` for ``mapInArrow`` and its like, giving the worker's freed memory back to the system at the end: idle workers stay."""

    def run(batches):
        try:
            yield from work(batches)
        finally:
            _release()

    return run


def lean_group(work: Callable) -> Callable:
    """The same for ``applyInPandas``; memory goes back now and then."""
    calls = [0]

    def run(frame):
        out = work(frame)
        calls[0] += 1
        if calls[0] % 64 == 0 or len(frame) > 256:
            del frame
            _release()
        return out

    return run


def _release() -> None:
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc has it
    if trim is not None:
        trim(0)


def small_batches(spark: SparkSession, size: str = "4m") -> None:
    """Makes a session ready for texts in Python steps: the package on the executors, and a bound on the bytes of an Arrow batch, so that long texts don't fill their memory.

    The bound stays set in the session, as plans that are made later need it too.
    """
    ship(spark)
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", size)


#: Rows of a task and file of a stage that is known to be small.
FEW = 20_000


def gathered(df: DataFrame, rows: int, each: int = FEW) -> DataFrame:
    """``df``, of about ``rows`` rows at most, dealt evenly by ``each`` rows where shuffles make far more partitions: tasks and files of a few rows cost more than their work.

    The number of rows only sets the number of partitions. What is dealt by a key is so before.
    """
    parts = max(1, -(-rows // each))
    return df.repartition(parts) if 4 * parts <= int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")) else df


def stage(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as a table in the shared folder and read it back."""
    return stored(df, f"stage-{name}")
