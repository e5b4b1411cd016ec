"""Tables as dense grids: steps times entities times components.

Rates are sums in a step; levels are their running totals. Step horizons are fixed
parameters and never taken from the data. Grids stay sparse in tables; cells that
no row fills are made where they are needed.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from traincube.functions.shapes import smooth_ceiling

COMPONENTS = ("c1", "c2", "c3")


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def step_of(ts: str, origin: str, minutes: int) -> Column:
    """0-based step of a timestamp without zone."""
    return F.expr(f"timestampdiff(MICROSECOND, timestamp_ntz'{origin}', {ts}) div {minutes * 60_000_000}")


@dataclass(frozen=True)
class ParticleSet:
    """Steps and entities of a particle-like table, and how its segments are compressed."""

    name: str
    steps: int
    segment: int
    entities: int
    padded: int
    order: str  # first: of each segment's first step; every: of each step; none: by id
    fanin: tuple[int, ...]
    whole: int = 1 << 21  # a segment with more cells is cut into blocks of entities, each with a train of its own
    part: int = 1 << 18  # cells of such a block at most

    @property
    def segments(self) -> int:
        return -(-self.steps // self.segment)

    @cached_property  # each task asks for it with each segment
    def block(self) -> int:
        """Entities of a block: all, or the most that have small prime factors only."""
        row = self.segment * len(COMPONENTS)
        n = self.entities if row * self.padded <= self.whole else max(1, self.part // row)
        while n < self.entities and smooth_ceiling(n) > n:
            n -= 1
        return n

    @property
    def blocks(self) -> int:
        return -(-self.entities // self.block)

    def size(self, block: int) -> int:
        """Entities of one block; the last may have fewer."""
        return min(self.block, self.entities - block * self.block)

    def padded_size(self, block: int) -> int:
        """Places of one block: as many as entities if the set has no padding."""
        if self.blocks == 1:
            return self.padded
        return self.size(block) if self.padded == self.entities else smooth_ceiling(self.size(block))


def vehicle(spark: SparkSession, sf_dir: str, minutes: int = 30, steps: int = 1440, drop_first: int = 0, segment: int = 16, order: str = "every") -> tuple[ParticleSet, DataFrame]:
    """Users of ``events``: sums of value, of k and of rows in each step."""
    k = F.get_json_object("props", "$.k").cast("double")
    cells = (
        read(spark, sf_dir, "events")
        .select((step_of("ts", "2024-01-01 00:00:00", minutes) - drop_first).alias("step"), F.col("user_id").alias("entity"), "value", k.alias("k"))
        .where(F.col("step").between(0, steps - 1))
        .groupBy("step", "entity")
        .agg(F.sum("value").alias("c1"), F.sum("k").alias("c2"), F.count("*").cast("double").alias("c3"))
    )
    users = read(spark, sf_dir, "events").agg(F.max("user_id")).first()[0]
    n = int(users) + 1 if users is not None else 1
    return ParticleSet("vehicle", steps, segment, n, smooth_ceiling(n), order, (2, 3, 3, 5)), cells


def sediment(spark: SparkSession, sf_dir: str, steps: int = 2560, segment: int = 32, order: str = "first", fanin: tuple[int, ...] = (2, 2, 2, 2, 5)) -> tuple[ParticleSet, DataFrame]:
    """Parts of ``lineitem`` by day: sums of quantity, price and rows, for all parts and seven years."""
    parts = read(spark, sf_dir, "part").agg(F.max("p_partkey")).first()[0]
    n = int(parts) + 1 if parts is not None else 1
    cells = (
        read(spark, sf_dir, "lineitem")
        .where(F.col("l_partkey") < n)
        .select(step_of("l_shipdate", "1995-01-02 00:00:00", 1440).alias("step"), F.col("l_partkey").alias("entity"), "l_quantity", "l_extendedprice")
        .where(F.col("step").between(0, steps - 1))
        .groupBy("step", "entity")
        .agg(F.sum("l_quantity").alias("c1"), F.sum("l_extendedprice").alias("c2"), F.count("*").cast("double").alias("c3"))
    )
    return ParticleSet("sediment", steps, segment, n, smooth_ceiling(n), order, fanin), cells


def dense(spark: SparkSession, cells: DataFrame, steps: int, entities: int) -> DataFrame:
    """Every (step, entity), zero where no row is: the grid comes from one range of numbers."""
    grid = spark.range(steps * entities).select((F.col("id") % steps).alias("step"), F.floor(F.col("id") / steps).alias("entity"))
    zero = [F.coalesce(F.col(c), F.lit(0.0)).alias(c) for c in COMPONENTS]
    return grid.join(cells, ["step", "entity"], "left").select("step", "entity", *zero)


def running(rates: DataFrame) -> DataFrame:
    """Running totals over steps of each entity, rounded so that sums in any order agree."""
    w = Window.partitionBy("entity").orderBy("step").rowsBetween(Window.unboundedPreceding, 0)
    return rates.select("step", "entity", *(F.round(F.sum(c).over(w), 4).alias(c) for c in COMPONENTS))


def level_box(cells: DataFrame) -> tuple[list[float], list[float]]:
    """Least and greatest levels of each component over all steps and entities; the least is 0 or the first total."""
    w = Window.partitionBy("entity").orderBy("step").rowsBetween(Window.unboundedPreceding, 0)
    totals = cells.select(*(F.sum(c).over(w).alias(c) for c in COMPONENTS))
    row = totals.agg(*(F.least(F.min(c), F.lit(0.0)) for c in COMPONENTS), *(F.greatest(F.max(c), F.lit(0.0)) for c in COMPONENTS)).first()
    return [x or 0.0 for x in row[:3]], [x or 0.0 for x in row[3:]]


def triaxial_cells(spark: SparkSession, sf_dir: str, days: int, steps: int, rves: int = 64) -> DataFrame:
    """status, step, rve and six sums of ``lineitem`` by line status, day bin and part group."""
    x = F.col("l_quantity"), F.col("l_extendedprice"), F.col("l_discount"), F.col("l_tax")
    return (
        read(spark, sf_dir, "lineitem")
        .select((F.col("l_linestatus") == "O").cast("int").alias("status"), step_of("l_shipdate", "1995-01-02 00:00:00", 1440 * days).cast("int").alias("step"), (F.col("l_partkey") % rves).cast("int").alias("rve"), *x)
        .where(F.col("step").between(0, steps - 1))
        .groupBy("status", "step", "rve")
        .agg(F.sum(x[0]).alias("s0"), F.sum(x[1]).alias("s1"), F.sum(x[2]).alias("s2"), F.sum(x[3]).alias("s3"), F.count("*").cast("double").alias("s4"), F.sum(x[0] * x[2]).alias("s5"))
    )


def wheel_cells(spark: SparkSession, sf_dir: str, days: int, steps: int) -> DataFrame:
    """Nine axes from lineitem, orders, customer, nation and part, and six sums."""
    line, orders = read(spark, sf_dir, "lineitem"), read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    customer = read(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    nation = read(spark, sf_dir, "nation").select("n_nationkey", F.col("n_regionkey").alias("patch"))
    part = read(spark, sf_dir, "part").select("p_partkey", "p_type")
    # Six types at most; the window is over them alone.
    kinds = part.select("p_type").distinct().select("p_type", (F.dense_rank().over(Window.orderBy("p_type")) - 1).alias("z"))
    x = F.col("l_quantity"), F.col("l_extendedprice"), F.col("l_discount"), F.col("l_tax")
    axes = ("patch", "step", "x", "y", "z", "g1", "g2", "g3")
    joined = (
        line.select("l_orderkey", "l_partkey", "l_suppkey", "l_linestatus", *x, step_of("l_shipdate", "1995-01-02 00:00:00", 1440 * days).alias("step"))
        .where(F.col("step").between(0, steps - 1))
        .join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
        .join(customer, F.col("o_custkey") == F.col("c_custkey"))
        .join(nation, F.col("c_nationkey") == F.col("n_nationkey"))
        .join(part.join(kinds, "p_type"), F.col("l_partkey") == F.col("p_partkey"))
    )
    cells = joined.select(
        "patch", "step", (F.col("l_partkey") % 10).alias("x"), (F.col("l_suppkey") % 6).alias("y"), "z",
        (F.col("l_linestatus") == "O").cast("int").alias("g1"), (F.col("l_discount") >= 0.05).cast("int").alias("g2"), (F.col("l_quantity") > 25).cast("int").alias("g3"), *x,
    )
    cells = cells.select(*(F.col(a).cast("int").alias(a) for a in axes), *x)
    return cells.groupBy(*axes).agg(F.sum(x[0]).alias("s0"), F.sum(x[1]).alias("s1"), F.sum(x[2]).alias("s2"), F.sum(x[3]).alias("s3"), F.count("*").cast("double").alias("s4"), F.sum(x[0] * x[2]).alias("s5"))
