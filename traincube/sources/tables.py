"""Reading snapshots and keeping trains in files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from traincube.operators.trains import SCHEMA


def read_snapshots(spark: SparkSession, path: str, fmt: str, schema: str) -> DataFrame:
    """Snapshots in parquet, orc, csv or json with an explicit schema; bad rows fail."""
    reader = spark.read.schema(schema)
    if fmt in ("csv", "json"):
        reader = reader.option("mode", "FAILFAST")
    if fmt == "csv":
        reader = reader.option("header", True)
    return reader.format(fmt).load(path)


def checked(cells: DataFrame, columns: tuple[str, ...] = ("c1", "c2", "c3"), on_missing: str = "error") -> DataFrame:
    """Null, NaN and infinite numbers raise an error, or become zero."""
    bad = lambda c: F.col(c).isNull() | F.isnan(c) | (F.abs(F.col(c)) == float("inf"))
    if on_missing == "zero":
        return cells.withColumns({c: F.when(bad(c), 0.0).otherwise(F.col(c)) for c in columns})
    return cells.withColumns({c: F.when(bad(c), F.raise_error(F.lit(f"{c} holds no finite number"))).otherwise(F.col(c)) for c in columns})


def write_trains(trains: DataFrame, path: str) -> None:
    """Parquet by variable and level; a level that is written again replaces the old one."""
    trains.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("variable", "level").parquet(path)


def read_trains(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(SCHEMA).parquet(path)
