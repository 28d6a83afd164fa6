"""The mechanisms as SQL functions, for users who write SQL.

They are SQL expressions registered as temporary functions, so the optimiser sees through them; the decoder is a small Python table function
over a few hundred sums.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Row, SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="code: int, dot: bigint")
class DecodeOrthogonal:
    """A table (s, total, k) of one attribute in, (code, dot) out; k is the matrix order."""

    def __init__(self) -> None:
        self.sums: dict[int, int] = {}
        self.order = 0

    def eval(self, row: Row) -> None:
        self.sums[row["s"]] = self.sums.get(row["s"], 0) + row["total"]
        self.order = row["k"]

    def terminate(self) -> Iterator[tuple[int, int]]:
        for code in range(self.order):
            yield code, sum(t * (1 - 2 * (bin(s & code).count("1") % 2)) for s, t in self.sums.items())


def register(spark: SparkSession) -> None:
    """Adds ``ldp_uniform``, ``ldp_one_coordinate``, ``ldp_coin_flip``, ``ldp_orthogonal`` and ``ldp_decode`` to the session."""
    define = lambda text: spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {text}")
    define("ldp_uniform(k STRING, salt STRING, seed INT) RETURNS DOUBLE RETURN cast(cast(conv(substring(md5(concat(seed, '|0|', salt, '|', k)), 1, 13), 16, 10) AS BIGINT) AS DOUBLE) / 4503599627370496D")
    define("ldp_one_coordinate(k STRING, t DOUBLE, eps DOUBLE, seed INT) RETURNS INT RETURN CASE WHEN ldp_uniform(k, 'toss', seed) < t * tanh(eps / 2) / 2 + 0.5D THEN 1 ELSE -1 END")
    define("ldp_coin_flip(k STRING, t INT, eps DOUBLE, seed INT) RETURNS INT RETURN CASE WHEN ldp_uniform(k, 'toss', seed) < 1 / (1 + exp(-eps)) THEN t ELSE -t END")
    define("ldp_orthogonal(k STRING, s INT, v INT, eps DOUBLE, seed INT) RETURNS INT RETURN (1 - 2 * (bit_count(s & v) % 2)) * CASE WHEN ldp_uniform(k, 'flip', seed) < 1 / (1 + exp(-eps)) THEN 1 ELSE -1 END")
    spark.udtf.register("ldp_decode", DecodeOrthogonal)
