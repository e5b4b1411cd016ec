"""Sampled functions as tables of cell midpoints."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

DELTAS = (1e-1, 1e-5, 1e-9)


def cells(spark: SparkSession, sf_dir: str, n: int) -> DataFrame:
    """The cells (i, j) of a grid of n by n in which the parts and suppliers of ``lineitem`` fall."""
    line = spark.read.parquet(f"{sf_dir}/lineitem.parquet")
    return line.select((F.col("l_partkey") % n).alias("i"), (F.col("l_suppkey") % n).alias("j")).distinct()


def places(spark: SparkSession, sf_dir: str, n: int) -> DataFrame:
    """The cells i among n in which the keys of ``orders`` fall."""
    return spark.read.parquet(f"{sf_dir}/orders.parquet").select((F.col("o_orderkey") % n).alias("i")).distinct()


def univariate(i: DataFrame, d: int, deltas: tuple[float, ...] = DELTAS) -> DataFrame:
    """delta, i and -ln(|x - 1/2| + delta) at the midpoints of cells i among 2**d."""
    x = (F.col("i") + 0.5) / float(1 << d)
    base = i.withColumn("delta", F.explode(F.array(*map(F.lit, deltas))))
    return base.select("delta", "i", (-F.log(F.abs(x - 0.5) + F.col("delta"))).alias("val"))


def kernel(ij: DataFrame, d: int, delta: float = 1e-5) -> DataFrame:
    """i, j and -ln(|x - y| + delta) at the midpoints of cells (i, j) among 2**d by 2**d."""
    n = 1 << d
    return ij.select("i", "j", (-F.log(F.abs((F.col("i") + 0.5) / float(n) - (F.col("j") + 0.5) / float(n)) + delta)).alias("val"))
