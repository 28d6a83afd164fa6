"""Reading the given tables and other formats; writing reports and models."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table, by its name only; columns and filters are pruned by what is done with it."""
    if name not in TABLES:
        raise ValueError(f"unknown table {name!r}")
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_any(spark: SparkSession, path: str, kind: str, schema: str | None = None) -> DataFrame:
    """Parquet, ORC, CSV (with header) or JSON; text formats need a schema, as types are never guessed from private data."""
    if kind in ("csv", "json") and schema is None:
        raise ValueError("a schema is needed")
    reader = spark.read.schema(schema) if schema else spark.read
    return {"parquet": reader.parquet, "orc": reader.orc, "csv": reader.option("header", True).csv, "json": reader.json}[kind](path)


def write_reports(reports: DataFrame, path: str, by: str | None = None, mode: str = "errorifexists") -> None:
    """Reports as parquet, laid out by a low-cardinality column (batch, day, attribute) so that later scans prune to it.

    Rows are dealt out by that column and a salt, so that a frequent value is written by many tasks.
    """
    if by is None:
        reports.write.mode(mode).parquet(path)
        return
    salted = reports.repartition(F.col(by), F.pmod(F.xxhash64(*reports.columns), F.lit(16)))
    salted.write.mode(mode).partitionBy(by).parquet(path)


def bucketed(reports: DataFrame, table: str, key: str, buckets: int, mode: str = "errorifexists") -> None:
    """Reports as a bucketed table: later joins and groupings on ``key`` need no shuffle."""
    reports.write.mode(mode).bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def save_model(spark: SparkSession, path: str, name: str, step: int, weights: list[float], mode: str = "append") -> None:
    """One row (name, step, weights) of a model table."""
    spark.createDataFrame([(name, step, [float(x) for x in weights])], "name string, step int, weights array<double>").coalesce(1).write.mode(mode).parquet(path)


def load_model(spark: SparkSession, path: str, name: str) -> list[float]:
    """Weights of the latest step."""
    return spark.read.parquet(path).where(F.col("name") == name).agg(F.max_by("weights", "step")).first()[0]
