"""Private tuples: what each attribute is, its public bounds or domain, and its normalised or coded column.

Bounds and domains are constants that both sides know before the collection. Nothing here looks at the data for them.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Numeric:
    """A number with public bounds; ``expr`` is SQL that Spark and DuckDB read alike."""

    name: str
    expr: str
    low: float
    high: float

    def sql(self) -> str:
        return f"(2 * (least(greatest(cast({self.expr} as double), cast({self.low!r} as double)), cast({self.high!r} as double)) - cast({self.low!r} as double)) / cast({self.high - self.low!r} as double) - 1)"


@dataclass(frozen=True)
class Categorical:
    """A category of a public domain of ``k`` values, coded from 0; ``labels`` in code order, or ``expr`` gives the code itself."""

    name: str
    expr: str
    k: int
    labels: tuple[str, ...] = ()

    def sql(self) -> str:
        if not self.labels:
            return f"cast({self.expr} as int)"
        cases = " ".join(f"when {self.expr} = '{x}' then {i}" for i, x in enumerate(self.labels))
        return f"(case {cases} end)"


@dataclass(frozen=True)
class TupleSpec:
    """Attributes of one user's record; numbers first, then categories, numbered from 0 in that order."""

    name: str
    numerics: tuple[Numeric, ...] = ()
    categoricals: tuple[Categorical, ...] = ()
    key: tuple[str, ...] = field(default=())

    @property
    def d(self) -> int:
        return len(self.numerics) + len(self.categoricals)

    @property
    def dn(self) -> int:
        return len(self.numerics)

    @property
    def one_hot_dimension(self) -> int:
        return self.dn - 1 + sum(c.k - 1 for c in self.categoricals)

    def only(self, numerics: bool = True, categoricals: bool = True) -> TupleSpec:
        return TupleSpec(self.name, self.numerics if numerics else (), self.categoricals if categoricals else (), self.key)

    def domain(self) -> list[tuple[int, str, int, int]]:
        """(j, name, k, value) for all categories."""
        return [(self.dn + i, c.name, c.k, v) for i, c in enumerate(self.categoricals) for v in range(c.k)]


def normalised(df: DataFrame, spec: TupleSpec) -> DataFrame:
    """``ukey`` and one column per attribute: numbers on [-1, 1], clamped to their bounds; categories as codes from 0. One projection, no shuffle."""
    key = F.concat_ws("|", *[F.expr(f"cast({k} as string)") for k in spec.key])
    return df.select(key.alias("ukey"), *[F.expr(a.sql()).alias(a.name) for a in spec.numerics], *[F.expr(c.sql()).alias(c.name) for c in spec.categoricals])


def validate_tuple(df: DataFrame, spec: TupleSpec) -> dict[str, int]:
    """Counts of what would break a collection: rows, null attributes, codes outside the domain, repeated keys."""
    checks = [F.count(F.lit(1)).alias("rows"), (F.count(F.lit(1)) - F.countDistinct("ukey")).alias("repeated_keys")]
    nulls = [F.col(a.name).isNull() for a in (*spec.numerics, *spec.categoricals)]
    outside = [~F.col(c.name).between(0, c.k - 1) for c in spec.categoricals]
    some = lambda parts: F.sum(F.when(F.greatest(*[p.cast("int") for p in parts], F.lit(0), F.lit(0)) > 0, 1).otherwise(0))
    checks += [some(nulls).alias("with_nulls"), some(outside).alias("outside_domain")]
    return df.agg(*checks).first().asDict()


def one_hot(code: str, k: int) -> Column:
    """k-1 values of -1 or 1; the last category is all -1."""
    return F.transform(F.sequence(F.lit(0), F.lit(k - 2)), lambda i: F.when(F.col(code) == i, 1.0).otherwise(-1.0))


def features(spec: TupleSpec, target: str) -> Column:
    """Feature vector of a tuple: numbers but the target, then one-hot categories."""
    numbers = F.array(*[F.col(a.name) for a in spec.numerics if a.name != target])
    return F.concat(numbers, *[one_hot(c.name, c.k) for c in spec.categoricals])


def binarise_at_mean(df: DataFrame, column: str, name: str = "y") -> DataFrame:
    """Adds 1 where the value is at least the column's mean, else -1. The mean is taken from the data: for evaluation only."""
    mean = df.agg(F.avg(column).alias("_mean"))
    return df.crossJoin(F.broadcast(mean)).withColumn(name, F.when(F.col(column) >= F.col("_mean"), 1.0).otherwise(-1.0)).drop("_mean")


def discretised(column: str, edges: list[float]) -> Column:
    """Band number from 0: how many edges are at most the value."""
    return sum((F.when(F.col(column) >= e, 1).otherwise(0) for e in edges), F.lit(0)).cast("int")
