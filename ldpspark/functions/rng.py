"""Keyed randomness: a uniform number is a function of (seed, run, salt, user key) alone.

A retried task draws the same report again, so it spends no budget twice, and another engine can replay every
draw. In a deployment the key is the client's secret; a seed known to the driver is a device of simulation.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SPACE = 1 << 52


def key_text(*parts: str) -> Column:
    """User key as text; integers only, as the text of a double differs between engines."""
    return F.concat_ws("|", *[F.col(p).cast("string") for p in parts])


def uniform(key: str | Column, salt: str, seed: int = 42, run: int | Column = 0, mode: str = "md5") -> Column:
    """A uniform double in [0, 1). ``md5`` can be replayed in SQL, ``xx`` is about five times cheaper."""
    k = F.col(key) if isinstance(key, str) else key
    r = run if isinstance(run, Column) else F.lit(run)
    if mode == "xx":
        return F.shiftrightunsigned(F.xxhash64(F.lit(f"{seed}|{salt}"), r.cast("long"), k), 11).cast("double") / float(1 << 53)
    if mode != "md5":
        raise ValueError(f"unknown mode {mode!r}")
    text = F.concat(F.lit(f"{seed}|"), r.cast("string"), F.lit(f"|{salt}|"), k)
    return F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("bigint").cast("double") / float(SPACE)


def choice(key: str | Column, salt: str, n: int | Column, **how) -> Column:
    """A uniform integer in 0..n-1."""
    size = n if isinstance(n, Column) else F.lit(n)
    return F.floor(uniform(key, salt, **how) * size).cast("int")


def uniform_sql(key: str, salt: str, seed: int = 42, run: str = "0") -> str:
    """The same draw as DuckDB text; ``key`` and ``run`` are SQL expressions."""
    return f"(cast('0x' || substr(md5('{seed}|' || cast({run} as varchar) || '|{salt}|' || {key}), 1, 13) as bigint)::double / 4503599627370496)"
