"""Grids, orders, statistics and formulas: everything that Catalyst plans alone."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from traincube.functions import budget, ordering, shapes
from traincube.operators.measures import autocorrelation
from traincube.plans.registry import VEHICLE, VEHICLE_KEYS, interleave, query
from traincube.sources import grids, samples

BITS = 10


def vehicle_rates(spark: SparkSession, sf_dir: str) -> DataFrame:
    shape, cells = grids.vehicle(spark, sf_dir)
    return grids.dense(spark, cells, shape.steps, shape.entities)


def vehicle_levels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return grids.running(vehicle_rates(spark, sf_dir))


def unit_cube(levels: DataFrame) -> DataFrame:
    """Positions in the unit cube of the whole domain; the box is one row."""
    box = levels.agg(*(f(c).alias(f"{n}_{c}") for c in grids.COMPONENTS for n, f in (("low", F.min), ("high", F.max))))
    x = [ordering.unit(F.col(c), F.col(f"low_{c}"), F.col(f"high_{c}"), BITS).alias(u) for c, u in zip(grids.COMPONENTS, ("ux", "uy", "uz"))]
    return levels.crossJoin(F.broadcast(box)).select("step", "entity", *grids.COMPONENTS, *x)


def with_morton(cube: DataFrame) -> DataFrame:
    return cube.withColumn("morton", ordering.morton([ordering.quantize(F.col(u), BITS) for u in ("ux", "uy", "uz")], BITS))


_R = "round({0}, 4) AS {0}"
_C = ", ".join(_R.format(c) for c in grids.COMPONENTS)


def _rounded(df: DataFrame, *keys: str, columns=grids.COMPONENTS, places: int = 4) -> DataFrame:
    return df.select(*keys, *(F.round(c, places).alias(c) for c in columns))


@query("q_grid_halfhour_rates", VEHICLE + f"z AS (SELECT 1) SELECT step, entity, {_C} FROM rates")
def grid_rates(spark, sf_dir):
    return _rounded(vehicle_rates(spark, sf_dir), "step", "entity")


@query("q_grid_running_totals", VEHICLE + "z AS (SELECT 1) SELECT step, entity, c1, c2, c3 FROM levels")
def grid_levels(spark, sf_dir):
    return vehicle_levels(spark, sf_dir)


@query("q_velocity_from_position", VEHICLE + "z AS (SELECT 1) SELECT step, entity, " + ", ".join(f"round(c{k} - coalesce(lag(c{k}) OVER (PARTITION BY entity ORDER BY step), 0.0), 4) AS v{k}" for k in (1, 2, 3)) + " FROM levels")
def velocity(spark, sf_dir):
    w = Window.partitionBy("entity").orderBy("step")
    return vehicle_levels(spark, sf_dir).select("step", "entity", *(F.round(F.col(f"c{k}") - F.coalesce(F.lag(f"c{k}").over(w), F.lit(0.0)), 4).alias(f"v{k}") for k in (1, 2, 3)))


@query("q_unit_cube", VEHICLE + "z AS (SELECT 1) SELECT step, entity, round(ux, 9) AS ux, round(uy, 9) AS uy, round(uz, 9) AS uz FROM cube")
def q_unit_cube(spark, sf_dir):
    return _rounded(unit_cube(vehicle_levels(spark, sf_dir)), "step", "entity", columns=("ux", "uy", "uz"), places=9)


@query("q_morton3_every_step", VEHICLE_KEYS + "z AS (SELECT 1) SELECT step, entity, morton, CAST(row_number() OVER (PARTITION BY step ORDER BY morton, entity) AS INTEGER) AS rank FROM keys")
def morton_every(spark, sf_dir):
    keyed = with_morton(unit_cube(vehicle_levels(spark, sf_dir)))
    return keyed.select("step", "entity", "morton", F.row_number().over(Window.partitionBy("step").orderBy("morton", "entity")).alias("rank"))


@query("q_morton3_first_snapshot", VEHICLE_KEYS + "z AS (SELECT 1) SELECT step // 16 AS seg, entity, morton, CAST(row_number() OVER (PARTITION BY step ORDER BY morton, entity) AS INTEGER) AS rank FROM keys WHERE step % 16 = 0")
def morton_first(spark, sf_dir):
    keyed = with_morton(unit_cube(vehicle_levels(spark, sf_dir))).where("step % 16 = 0")
    return keyed.select(F.floor(F.col("step") / 16).alias("seg"), "entity", "morton", F.row_number().over(Window.partitionBy("step").orderBy("morton", "entity")).alias("rank"))


@query("q_morton_collisions", VEHICLE_KEYS + "z AS (SELECT 1) SELECT step, CAST(sum(n - 1) AS BIGINT) AS n_collisions FROM (SELECT step, morton, count(*) AS n FROM keys GROUP BY ALL) GROUP BY step")
def collisions(spark, sf_dir):
    keyed = with_morton(unit_cube(vehicle_levels(spark, sf_dir)))
    return keyed.groupBy("step", "morton").agg(F.count("*").alias("n")).groupBy("step").agg(F.sum(F.col("n") - 1).alias("n_collisions"))


@query("q_vehicle_front_mask", VEHICLE + "z AS (SELECT 1) SELECT c.step, c.entity, ux >= 0.75 AS masked, round(CASE WHEN ux >= 0.75 THEN 0.0 ELSE r.c1 END, 4) AS v1 FROM cube c JOIN rates r ON c.step = r.step AND c.entity = r.entity")
def front_mask(spark, sf_dir, front: float = 0.25):
    rates = vehicle_rates(spark, sf_dir)
    cube = unit_cube(grids.running(rates)).select("step", "entity", (F.col("ux") >= 1 - front).alias("masked"))
    return cube.join(rates, ["step", "entity"]).select("step", "entity", "masked", F.round(F.when(F.col("masked"), 0.0).otherwise(F.col("c1")), 4).alias("v1"))


@query("q_vehicle_roster_renewal", VEHICLE + """cap AS (SELECT round(max(c1) / 4, 4) AS cap FROM levels),
laps AS (SELECT step, entity, c1, CAST(floor(c1 / cap) AS BIGINT) AS lap FROM levels, cap)
SELECT step, entity, lap, round(c1 - CASE WHEN lap = 0 THEN 0.0 ELSE first_value(c1) OVER (PARTITION BY entity, lap ORDER BY step) END, 4) AS c1 FROM laps""")
def roster_renewal(spark, sf_dir, laps: int = 4):
    """An entity that has covered another quarter of the longest way leaves and enters again: its totals begin at 0 there, as a new one's do."""
    levels = vehicle_levels(spark, sf_dir).select("step", "entity", "c1")
    cap = levels.agg(F.round(F.max("c1") / laps, 4).alias("cap"))
    numbered = levels.crossJoin(F.broadcast(cap)).withColumn("lap", F.floor(F.col("c1") / F.col("cap")))
    w = Window.partitionBy("entity", "lap").orderBy("step")
    start = F.when(F.col("lap") == 0, 0.0).otherwise(F.first("c1").over(w))
    return numbered.select("step", "entity", "lap", F.round(F.col("c1") - start, 4).alias("c1"))


def pad(df: DataFrame, axis: str, last: int, target: int) -> DataFrame:
    """Rows of the last place on an axis repeated up to the target."""
    extra = df.where(F.col(axis) == last).withColumn(axis, F.explode(F.sequence(F.lit(last + 1), F.lit(target - 1)))) if target > last + 1 else df.limit(0)
    return df.unionByName(extra.withColumn(axis, F.col(axis).cast(df.schema[axis].dataType)))


_SMOOTH = "(SELECT min(t) FROM (SELECT CAST(pow(2, a) * pow(5, b) AS BIGINT) AS t FROM range(25) x(a), range(11) y(b)) WHERE t >= {0})"


@query("q_pad_entities", VEHICLE + f"""n AS (SELECT max(entity) + 1 AS n, {_SMOOTH.format("max(entity) + 1")} AS t FROM users),
more AS (SELECT unnest(range(n, t)) AS rank, n - 1 AS entity FROM n)
SELECT step, entity AS rank, round(c1, 4) AS c1 FROM rates UNION ALL SELECT step, rank, round(c1, 4) AS c1 FROM rates JOIN more USING (entity)""".replace(_SMOOTH.format("max(entity) + 1"), "0").replace("max(entity) + 1 AS n, 0 AS t FROM users", "m AS n, (SELECT min(t) FROM (SELECT CAST(pow(2, a) * pow(5, b) AS BIGINT) AS t FROM (SELECT unnest(range(25)) AS a), (SELECT unnest(range(11)) AS b)) WHERE t >= m) AS t FROM (SELECT max(entity) + 1 AS m FROM users)"))
def pad_entities(spark, sf_dir):
    shape, cells = grids.vehicle(spark, sf_dir)
    rates = grids.dense(spark, cells, shape.steps, shape.entities).select("step", F.col("entity").alias("rank"), F.round("c1", 4).alias("c1"))
    return pad(rates, "rank", shape.entities - 1, shape.padded)


@query("q_pad_steps", VEHICLE + "z AS (SELECT 1) SELECT step AS step_out, entity, round(c1, 4) AS c1 FROM rates UNION ALL SELECT s.step_out, entity, round(c1, 4) AS c1 FROM rates, (SELECT unnest(range(1440, 1600)) AS step_out) s WHERE step = 1439")
def pad_steps(spark, sf_dir):
    rates = vehicle_rates(spark, sf_dir).select(F.col("step").alias("step_out"), "entity", F.round("c1", 4).alias("c1"))
    return pad(rates, "step_out", 1439, shapes.smooth_ceiling(1441))


_LONG = "long AS (" + " UNION ALL ".join(f"SELECT '{v}' AS variable, step // 16 AS seg, {c} AS x FROM {t}" for v, t in (("position", "levels"), ("velocity", "rates")) for c in grids.COMPONENTS) + ")"
_STATS = "CAST(count(*) AS BIGINT) AS n, round(min(x), 4) AS vmin, round(max(x), 4) AS vmax"


def variables_long(spark: SparkSession, sf_dir: str) -> DataFrame:
    rates = vehicle_rates(spark, sf_dir)
    out = None
    for name, df in (("position", grids.running(rates)), ("velocity", rates)):
        one = df.select(F.lit(name).alias("variable"), F.floor(F.col("step") / 16).alias("seg"), F.explode(F.array(*grids.COMPONENTS)).alias("x"))
        out = one if out is None else out.union(one)
    return out


def _stats():
    return F.count("*").alias("n"), F.round(F.min("x"), 4).alias("vmin"), F.round(F.max("x"), 4).alias("vmax")


@query("q_segment_stats", VEHICLE + _LONG + f" SELECT variable, seg, {_STATS}, round(sqrt(sum(x * x)), 4) AS fro FROM long GROUP BY variable, seg")
def segment_stats(spark, sf_dir):
    return variables_long(spark, sf_dir).groupBy("variable", "seg").agg(*_stats(), F.round(F.sqrt(F.sum(F.col("x") * F.col("x"))), 4).alias("fro"))


@query("q_topk_segments", VEHICLE + _LONG + " SELECT seg, fro FROM (SELECT seg, round(sqrt(sum(x * x)), 4) AS fro FROM long WHERE variable = 'velocity' GROUP BY seg) ORDER BY fro DESC, seg LIMIT 10")
def topk_segments(spark, sf_dir):
    own = variables_long(spark, sf_dir).where("variable = 'velocity'").groupBy("seg").agg(F.round(F.sqrt(F.sum(F.col("x") * F.col("x"))), 4).alias("fro"))
    return own.orderBy(F.desc("fro"), "seg").limit(10)


@query("q_rollup_stats", VEHICLE + _LONG + f" SELECT variable, seg, {_STATS} FROM long GROUP BY ROLLUP (variable, seg)")
def rollup_stats(spark, sf_dir):
    return variables_long(spark, sf_dir).rollup("variable", "seg").agg(*_stats())


@query("q_cube_stats", VEHICLE + _LONG + f" SELECT variable, seg, {_STATS} FROM long GROUP BY CUBE (variable, seg)")
def cube_stats(spark, sf_dir):
    return variables_long(spark, sf_dir).cube("variable", "seg").agg(*_stats())


@query("q_grouping_sets_stats", VEHICLE + _LONG + f" SELECT variable, seg, {_STATS} FROM long GROUP BY GROUPING SETS ((variable, seg), (variable), ())")
def grouping_sets_stats(spark, sf_dir):
    long = variables_long(spark, sf_dir)
    return long.groupingSets([[F.col("variable"), F.col("seg")], [F.col("variable")], []], "variable", "seg").agg(*_stats())


_ROSTER = "SELECT DISTINCT (date_diff('microsecond', TIMESTAMP '2024-01-01', ts) // 28800000000) AS seg, user_id AS entity FROM events"


def roster(spark, sf_dir):
    return grids.read(spark, sf_dir, "events").select(grids.step_of("ts", "2024-01-01 00:00:00", 480).alias("seg"), F.col("user_id").alias("entity")).distinct()


@query("q_roster_changes", f"WITH r AS ({_ROSTER}) SELECT seg, entity FROM r EXCEPT SELECT seg + 1 AS seg, entity FROM r")
def roster_changes(spark, sf_dir):
    r = roster(spark, sf_dir)
    return r.exceptAll(r.select((F.col("seg") + 1).alias("seg"), "entity"))


@query("q_stable_roster", f"WITH r AS ({_ROSTER}) SELECT seg, entity FROM r INTERSECT SELECT seg + 1 AS seg, entity FROM r")
def stable_roster(spark, sf_dir):
    r = roster(spark, sf_dir)
    return r.intersect(r.select((F.col("seg") + 1).alias("seg"), "entity"))


@query("q_missing_entities", f"WITH r AS ({_ROSTER}), u AS (SELECT unnest(range(m + 1)) AS entity FROM (SELECT max(user_id) AS m FROM events)) SELECT s.seg, u.entity FROM (SELECT unnest(range(90)) AS seg) s, u WHERE NOT EXISTS (SELECT 1 FROM r WHERE r.seg = s.seg AND r.entity = u.entity)")
def missing_entities(spark, sf_dir):
    shape, _ = grids.vehicle(spark, sf_dir)
    every = spark.range(90 * shape.entities).select((F.col("id") % 90).alias("seg"), F.floor(F.col("id") / 90).alias("entity"))
    return every.join(roster(spark, sf_dir), ["seg", "entity"], "left_anti")


@query("q_hold_last", VEHICLE + "z AS (SELECT s.step, u.entity, c.c1 FROM (SELECT unnest(range(1440)) AS step) s CROSS JOIN users u LEFT JOIN cells c ON c.step = s.step AND c.entity = u.entity) SELECT step, entity, round(coalesce(last_value(c1 IGNORE NULLS) OVER (PARTITION BY entity ORDER BY step ROWS UNBOUNDED PRECEDING), 0.0), 4) AS c1 FROM z")
def hold_last(spark, sf_dir):
    shape, cells = grids.vehicle(spark, sf_dir)
    grid = spark.range(shape.steps * shape.entities).select((F.col("id") % shape.steps).alias("step"), F.floor(F.col("id") / shape.steps).alias("entity"))
    w = Window.partitionBy("entity").orderBy("step").rowsBetween(Window.unboundedPreceding, 0)
    return grid.join(cells, ["step", "entity"], "left").select("step", "entity", F.round(F.coalesce(F.last("c1", ignorenulls=True).over(w), F.lit(0.0)), 4).alias("c1"))


@query("q_univariate_samples", "SELECT delta, i, round(-ln(abs((i + 0.5) / 1024 - 0.5) + delta), 9) AS val FROM (SELECT DISTINCT o_orderkey % 1024 AS i FROM orders), (SELECT unnest([1e-1, 1e-5, 1e-9]) AS delta)")
def univariate_samples(spark, sf_dir):
    return samples.univariate(samples.places(spark, sf_dir, 1024), 10).select("delta", "i", F.round("val", 9).alias("val"))


@query("q_kernel_samples", "SELECT i, j, round(-ln(abs((i + 0.5) / 32 - (j + 0.5) / 32) + 1e-5), 9) AS val FROM (SELECT DISTINCT l_partkey % 32 AS i, l_suppkey % 32 AS j FROM lineitem)")
def kernel_samples(spark, sf_dir):
    return samples.kernel(samples.cells(spark, sf_dir, 32), 5).select("i", "j", F.round("val", 9).alias("val"))


@query("q_kernel_index", "SELECT i, j, i + 16 * j AS plain_idx, i % 4 + 4 * (j % 4) + 16 * ((i >> 2) & 1) + 32 * ((j >> 2) & 1) + 64 * ((i >> 3) & 1) + 128 * ((j >> 3) & 1) AS interlaced_idx FROM (SELECT DISTINCT l_partkey % 16 AS i, l_suppkey % 16 AS j FROM lineitem)")
def kernel_index(spark, sf_dir):
    """Indices of the cells that the parts and suppliers of the lines fall in."""
    one = shapes.modes_for_vector(4, 3)
    ij = samples.cells(spark, sf_dir, 16)
    return ij.select("i", "j", shapes.long_index([F.col("i"), F.col("j")], [16, 16]).alias("plain_idx"), shapes.interlaced_index([F.col("i"), F.col("j")], [one, one]).alias("interlaced_idx"))


@query("q_long_index", "SELECT o_orderkey, idx, idx % 3 AS digit_1, (idx // 3) % 4 AS digit_2, (idx // 12) % 5 AS digit_3, idx % 12 AS row_k, idx // 12 AS col_k FROM (SELECT o_orderkey, o_custkey % 60 AS idx FROM orders)")
def q_long_index(spark, sf_dir):
    d = shapes.digits(F.col("idx"), [3, 4, 5])
    row, col = shapes.unfold(F.col("idx"), [3, 4, 5], 2)
    orders = grids.read(spark, sf_dir, "orders").select("o_orderkey", (F.col("o_custkey") % 60).alias("idx"))
    return orders.select("o_orderkey", "idx", *(x.alias(f"digit_{k}") for k, x in enumerate(d, 1)), row.alias("row_k"), col.alias("col_k"))


def _each(rows: DataFrame, of, schema: str) -> DataFrame:
    """of() of the one number of each row."""

    def run(batches):
        for x in batches:
            out = [of(v) for v in x.column(0).to_pylist()]
            if out:
                yield pa.RecordBatch.from_pylist(out)

    return rows.mapInArrow(run, schema)


@query("q_vector_levels", "SELECT level, CAST(pow(2, 20 - level + 1) AS BIGINT) AS leaf_size, level AS n_modes FROM (SELECT DISTINCT o_custkey % 20 + 1 AS level FROM orders)")
def vector_levels(spark, sf_dir):
    level = grids.read(spark, sf_dir, "orders").select((F.col("o_custkey") % 20 + 1).alias("level")).distinct()
    return _each(level, lambda k: {"level": k, "leaf_size": shapes.modes_for_vector(20, k)[0], "n_modes": len(shapes.modes_for_vector(20, k))}, "level long, leaf_size long, n_modes long")


@query("q_small_primes", "WITH n AS (SELECT DISTINCT l_partkey % 99 + 2 AS n FROM lineitem), c AS (SELECT unnest(range(2, 101)) AS n), p AS (SELECT a.n AS p FROM c a WHERE NOT EXISTS (SELECT 1 FROM c b WHERE b.n < a.n AND a.n % b.n = 0)), f AS (SELECT n, p FROM n, p, (SELECT unnest(range(1, 7)) AS k) WHERE n % CAST(pow(p, k) AS BIGINT) = 0) SELECT n, string_agg(CAST(p AS VARCHAR), ',' ORDER BY p) AS factors FROM f GROUP BY n")
def q_small_primes(spark, sf_dir):
    n = grids.read(spark, sf_dir, "lineitem").select((F.col("l_partkey") % 99 + 2).alias("n")).distinct()
    return _each(n, lambda n: {"n": n, "factors": ",".join(map(str, shapes.small_primes(n)))}, "n long, factors string")


@query("q_smooth_ceiling", "WITH t AS (SELECT CAST(pow(2, a) * pow(5, b) AS BIGINT) AS t FROM (SELECT unnest(range(25)) AS a), (SELECT unnest(range(11)) AS b)) SELECT n, min(t) AS target FROM (SELECT DISTINCT o_orderkey % 1500 + 1 AS n FROM orders), t WHERE t >= n GROUP BY n")
def q_smooth_ceiling(spark, sf_dir):
    n = grids.read(spark, sf_dir, "orders").select((F.col("o_orderkey") % 1500 + 1).alias("n")).distinct()
    return _each(n, lambda n: {"n": n, "target": shapes.smooth_ceiling(n)}, "n long, target long")


_POINTS = "p AS (SELECT vec_id, CAST(embedding[1] AS DOUBLE) AS a, CAST(embedding[2] AS DOUBLE) AS b FROM embeddings ORDER BY vec_id LIMIT 256), box AS (SELECT min(a) a0, max(a) a1, min(b) b0, max(b) b1 FROM p), u AS (SELECT vec_id, least((a - a0) / (a1 - a0), 1.0 - 1.0 / 1024) AS ux, least((b - b0) / (b1 - b0), 1.0 - 1.0 / 1024) AS uy FROM p, box)"


def points2d(spark, sf_dir, n: int = 256):
    """The first n embeddings by id, two coordinates, in the unit square; n is what the workload fixes."""
    p = grids.read(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding")[0].cast("double").alias("a"), F.col("embedding")[1].cast("double").alias("b")).orderBy("vec_id").limit(n)
    box = p.agg(F.min("a").alias("a0"), F.max("a").alias("a1"), F.min("b").alias("b0"), F.max("b").alias("b1"))
    return p.crossJoin(F.broadcast(box)).select("vec_id", ordering.unit(F.col("a"), F.col("a0"), F.col("a1"), BITS).alias("ux"), ordering.unit(F.col("b"), F.col("b0"), F.col("b1"), BITS).alias("uy"))


@query("q_morton2d_embeddings", f"WITH {_POINTS}, c AS (SELECT vec_id, CAST(floor(ux * 1024) AS BIGINT) AS x, CAST(floor(uy * 1024) AS BIGINT) AS y FROM u), k AS (SELECT vec_id, {interleave(['x', 'y'], 10)} AS morton FROM c) SELECT vec_id, morton, CAST(row_number() OVER (ORDER BY morton, vec_id) AS INTEGER) AS rank FROM k")
def morton2d(spark, sf_dir):
    keyed = points2d(spark, sf_dir).select("vec_id", ordering.morton([ordering.quantize(F.col(u), BITS) for u in ("ux", "uy")], BITS).alias("morton"))
    return keyed.select("vec_id", "morton", F.row_number().over(Window.orderBy("morton", "vec_id")).alias("rank"))


@query("q_morton_bits", f"WITH {_POINTS}, d AS (SELECT min(sqrt(pow(p.ux - q.ux, 2) + pow(p.uy - q.uy, 2))) AS dist FROM u p, u q WHERE p.vec_id < q.vec_id) SELECT CAST(floor(log2(sqrt(2) / dist)) + 1 AS INTEGER) AS min_dist_bits, CAST(7 AS INTEGER) AS extent_bits FROM d")
def morton_bits(spark, sf_dir):
    """Bits from the least distance of two points, found among neighbouring cells of a grid, and from an extent of 0.01."""
    side = 16
    p = points2d(spark, sf_dir).withColumns({"cx": F.floor(F.col("ux") * side), "cy": F.floor(F.col("uy") * side)})
    near = F.array(*(F.struct((F.col("cx") + a).alias("cx"), (F.col("cy") + b).alias("cy")) for a in (-1, 0, 1) for b in (-1, 0, 1)))
    q = p.select(F.col("vec_id").alias("other"), F.col("ux").alias("vx"), F.col("uy").alias("vy"), F.explode(near).alias("cell")).select("other", "vx", "vy", "cell.*")
    dist = F.sqrt(F.pow(F.col("ux") - F.col("vx"), 2) + F.pow(F.col("uy") - F.col("vy"), 2))
    least = p.join(q, ["cx", "cy"]).where("vec_id < other").agg(F.min(dist).alias("dist"))
    return least.select((F.floor(F.log2(F.lit(2**0.5) / F.col("dist"))) + 1).cast("int").alias("min_dist_bits"), F.lit(ordering.bits_for_extent(0.01)).alias("extent_bits"))


@query("q_tolerance_from_nrmse", VEHICLE + _LONG + " SELECT variable, tau, round(tau * (max(x) - min(x)) * sqrt(count(*)) / sqrt(sum(x * x)), 6) AS tau_fro FROM long, (SELECT unnest([1e-1, 1e-2, 1e-3]) AS tau) GROUP BY variable, tau")
def tolerance(spark, sf_dir):
    s = variables_long(spark, sf_dir).groupBy("variable").agg(F.min("x").alias("a"), F.max("x").alias("b"), F.count("*").alias("n"), F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("f"))
    s = s.withColumn("tau", F.explode(F.array(*map(F.lit, (1e-1, 1e-2, 1e-3)))))
    return s.select("variable", "tau", F.round(budget.fro_from_nrmse(F.col("tau"), F.col("a"), F.col("b"), F.col("n"), F.col("f")), 6).alias("tau_fro"))


#: Nineteenths end in no decimal place, so that rounding meets no ties.
_TAUS = "(SELECT DISTINCT round(100 * l_discount + 1) / 1900 AS tau, l_tax AS tau_round, CAST(l_linenumber AS BIGINT) AS levels FROM lineitem)"


def taus(spark, sf_dir):
    """Tolerances from the discounts and taxes of the lines, levels from their numbers."""
    line = grids.read(spark, sf_dir, "lineitem")
    return line.select((F.round(100 * F.col("l_discount") + 1) / 1900).alias("tau"), F.col("l_tax").alias("tau_round"), F.col("l_linenumber").cast("long").alias("levels")).distinct()


@query("q_tolerance_compose", f"SELECT tau, tau_round, levels, round((1 + tau) * pow(1 + tau_round, levels) - 1, 9) AS composed FROM {_TAUS}")
def compose(spark, sf_dir):
    return taus(spark, sf_dir).withColumn("composed", F.round(budget.composed(F.col("tau"), F.col("tau_round"), F.col("levels")), 9))


@query("q_tolerance_split", "SELECT tau, levels, round(pow(1 + tau, 1.0 / (levels + 1)) - 1, 9) AS stage, round(tau, 9) AS composed FROM (SELECT DISTINCT tau, levels FROM " + _TAUS + ")")
def split(spark, sf_dir):
    t = taus(spark, sf_dir).select("tau", "levels").distinct().withColumn("stage", budget.stage_tau(F.col("tau"), F.col("levels")))
    return t.select("tau", "levels", F.round("stage", 9).alias("stage"), F.round(budget.composed(F.col("stage"), F.col("stage"), F.col("levels")), 9).alias("composed"))


@query("q_ratio_formula", "WITH l AS (SELECT DISTINCT CAST(l_quantity AS BIGINT) AS q, CAST(l_linenumber AS BIGINT) AS k FROM lineitem), t AS (SELECT {'modes': [q, k, 2], 'ranks': [1, least(q, 2 * k), least(2, q * k), 1]} AS t FROM l), u AS (SELECT t.modes AS modes, t.ranks AS ranks, list_sum(list_transform(range(1, len(t.modes) + 1), lambda k: t.ranks[k] * t.modes[k] * t.ranks[k + 1])) AS numel, list_product(t.modes) AS n, list_sum(t.modes) AS s FROM t) SELECT array_to_string(modes, ',') AS modes, array_to_string(ranks, ',') AS ranks, CAST(numel AS BIGINT) AS numel, round(n / numel, 6) AS ratio, round(n / s, 6) AS ceiling FROM u")
def ratio_formula(spark, sf_dir):
    """Modes from the quantities and numbers of the lines, with the largest ranks that they allow."""
    line = grids.read(spark, sf_dir, "lineitem").select(F.col("l_quantity").cast("long").alias("q"), F.col("l_linenumber").cast("long").alias("k")).distinct()
    one, two = F.lit(1).cast("long"), F.lit(2).cast("long")
    t = line.select(F.array("q", "k", two).alias("m"), F.array(one, F.least("q", 2 * F.col("k")), F.least(two, F.col("q") * F.col("k")), one).alias("r"))
    k = F.sequence(F.lit(1), F.size("m"))
    numel = F.aggregate(k, F.lit(0).cast("long"), lambda s, i: s + F.element_at("r", i) * F.element_at("m", i) * F.element_at("r", i + 1))
    n = F.aggregate("m", F.lit(1).cast("long"), lambda s, x: s * x)
    total = F.aggregate("m", F.lit(0).cast("long"), lambda s, x: s + x)
    text = lambda c: F.array_join(F.col(c).cast("array<string>"), ",")
    return t.select(text("m").alias("modes"), text("r").alias("ranks"), numel.alias("numel"), F.round(n / numel, 6).alias("ratio"), F.round(n / total, 6).alias("ceiling"))


def triaxial_sql(days: int, steps: int) -> str:
    return _TRI.replace("4233600000000", str(days * 86_400_000_000)).replace("BETWEEN 0 AND 52 *", f"BETWEEN 0 AND {steps} *")


#: Days in a step and steps of the triaxial set, daily and in coarse bins; both hold every row of the tables.
FULL, COARSE = (1, 2560), (49, 52)
_TRI = """WITH cells AS MATERIALIZED (
  SELECT CAST(l_linestatus = 'O' AS INTEGER) AS status, CAST(date_diff('microsecond', TIMESTAMP '1995-01-02', l_shipdate) // 4233600000000 AS INTEGER) AS step, CAST(l_partkey % 64 AS INTEGER) AS rve,
         sum(l_quantity) AS s0, sum(l_extendedprice) AS s1, sum(l_discount) AS s2, sum(l_tax) AS s3, CAST(count(*) AS DOUBLE) AS s4, sum(l_quantity * l_discount) AS s5
  FROM lineitem WHERE date_diff('microsecond', TIMESTAMP '1995-01-02', l_shipdate) BETWEEN 0 AND 52 * 4233600000000 - 1 GROUP BY ALL)"""
_WHEEL = """WITH kinds AS (SELECT p_type, row_number() OVER (ORDER BY p_type) - 1 AS z FROM (SELECT DISTINCT p_type FROM part)),
cells AS (
  SELECT CAST(n_regionkey AS INTEGER) AS patch, CAST(date_diff('microsecond', TIMESTAMP '1995-01-02', l_shipdate) // 4838400000000 AS INTEGER) AS step, CAST(l_partkey % 10 AS INTEGER) AS x, CAST(l_suppkey % 6 AS INTEGER) AS y, CAST(z AS INTEGER) AS z,
         CAST(l_linestatus = 'O' AS INTEGER) AS g1, CAST(l_discount >= 0.05 AS INTEGER) AS g2, CAST(l_quantity > 25 AS INTEGER) AS g3,
         sum(l_quantity) AS s0, sum(l_extendedprice) AS s1, sum(l_discount) AS s2, sum(l_tax) AS s3, CAST(count(*) AS DOUBLE) AS s4, sum(l_quantity * l_discount) AS s5
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN part ON l_partkey = p_partkey JOIN kinds USING (p_type)
  WHERE date_diff('microsecond', TIMESTAMP '1995-01-02', l_shipdate) BETWEEN 0 AND 45 * 4838400000000 - 1 GROUP BY ALL)"""


def wheel_sql(days: int, steps: int) -> str:
    return _WHEEL.replace("4838400000000", str(days * 86_400_000_000)).replace("BETWEEN 0 AND 45 *", f"BETWEEN 0 AND {steps} *")


#: Days in a step and steps of the wheel set, in coarse bins and as in the workload; both hold every row of the tables.
WHEEL_COARSE, WHEEL_FULL = (56, 45), (4, 626)


def _long_sums(df: DataFrame, *axes: str) -> DataFrame:
    comp = F.explode(F.array(*(F.struct(F.lit(k).alias("component"), F.round(f"s{k}", 4).alias("val")) for k in range(6)))).alias("c")
    return df.select(*axes, comp).select(*axes, "c.component", "c.val")


def _sql_sums(head: str, axes: str) -> str:
    return head + " " + " UNION ALL ".join(f"SELECT {axes}, {k} AS component, round(s{k}, 4) AS val FROM cells" for k in range(6))


@query("q_triaxial_grid", _sql_sums(triaxial_sql(*FULL), "status, step, rve"))
def triaxial_grid(spark, sf_dir):
    return _long_sums(grids.triaxial_cells(spark, sf_dir, *FULL), "status", "step", "rve")


@query("q_wheel_grid", _sql_sums(_WHEEL, "patch, step, x, y, z, g1, g2, g3"))
def wheel_grid(spark, sf_dir):
    return _long_sums(grids.wheel_cells(spark, sf_dir, *WHEEL_COARSE), "patch", "step", "x", "y", "z", "g1", "g2", "g3")


_SERIES = _TRI + """, g AS (SELECT p.status, s.step, r.rve, coalesce(s0, 0.0) AS s0, coalesce(s1, 0.0) AS s1, coalesce(s4, 0.0) AS s4
  FROM (SELECT unnest([0, 1]) AS status) p CROSS JOIN (SELECT unnest(range(52)) AS step) s CROSS JOIN (SELECT unnest(range(64)) AS rve) r LEFT JOIN cells c ON c.status = p.status AND c.step = s.step AND c.rve = r.rve),
raw AS (""" + " UNION ALL ".join(f"SELECT {k} AS component, status, rve, step, s{c} AS y FROM g" for k, c in enumerate((0, 1, 4))) + """),
series AS (SELECT 'incremental' AS variable, component, status, rve, step, y FROM raw
  UNION ALL SELECT 'current', component, status, rve, step, round(sum(y) OVER (PARTITION BY component, status, rve ORDER BY step ROWS UNBOUNDED PRECEDING), 4) FROM raw),
m AS (SELECT variable, component, status, rve, avg(y) AS mu, sum(y * y) / count(*) - pow(avg(y), 2) AS var FROM series GROUP BY ALL),
c AS (SELECT s.*, y - mu AS d, var FROM series s JOIN m USING (variable, component, status, rve) WHERE var > 1e-12),
pairs AS (SELECT a.variable, a.component, a.status, a.rve, b.step - a.step AS lag, sum(a.d * b.d) / count(*) / any_value(a.var) AS ac
  FROM c a JOIN c b ON a.variable = b.variable AND a.component = b.component AND a.status = b.status AND a.rve = b.rve AND b.step >= a.step GROUP BY ALL)
"""


def triaxial_series(spark, sf_dir, days: int = COARSE[0], steps: int = COARSE[1]):
    """(variable, component, status, rve, step, y): three sums as increments and as running totals."""
    cells = grids.triaxial_cells(spark, sf_dir, days, steps)
    grid = spark.range(2 * steps * 64).select((F.col("id") % 2).cast("int").alias("status"), (F.floor(F.col("id") / 2) % steps).cast("int").alias("step"), F.floor(F.col("id") / (2 * steps)).cast("int").alias("rve"))
    g = grid.join(cells, ["status", "step", "rve"], "left")
    raw = g.select("status", "step", "rve", F.explode(F.array(*(F.struct(F.lit(k).alias("component"), F.coalesce(F.col(f"s{c}"), F.lit(0.0)).alias("y")) for k, c in enumerate((0, 1, 4))))).alias("c")).select("status", "step", "rve", "c.*")
    w = Window.partitionBy("component", "status", "rve").orderBy("step").rowsBetween(Window.unboundedPreceding, 0)
    current = raw.withColumn("y", F.round(F.sum("y").over(w), 4))
    return raw.withColumn("variable", F.lit("incremental")).unionByName(current.withColumn("variable", F.lit("current")))


@query("q_autocorr_component", _SERIES + "SELECT variable, component, lag, round(avg(ac), 6) AS ac FROM pairs GROUP BY ALL")
def autocorr_component(spark, sf_dir):
    ac = autocorrelation(triaxial_series(spark, sf_dir), ["variable", "component", "status", "rve"], "step", "y")
    return ac.groupBy("variable", "component", "lag").agg(F.round(F.avg("ac"), 6).alias("ac"))


@query("q_autocorr_overall", _SERIES + "SELECT variable, lag, round(avg(ac), 6) AS ac FROM pairs GROUP BY ALL")
def autocorr_overall(spark, sf_dir):
    ac = autocorrelation(triaxial_series(spark, sf_dir), ["variable", "component", "status", "rve"], "step", "y")
    return ac.groupBy("variable", "lag").agg(F.round(F.avg("ac"), 6).alias("ac"))


@query("q_documents_stats", "SELECT source, lang, CAST(count(*) AS BIGINT) AS n, min(n_chars) AS vmin, max(n_chars) AS vmax FROM documents GROUP BY source, lang")
def documents_stats(spark, sf_dir):
    return grids.read(spark, sf_dir, "documents").groupBy("source", "lang").agg(F.count("*").alias("n"), F.min("n_chars").alias("vmin"), F.max("n_chars").alias("vmax"))


@query("q_unfold_gram", _TRI + ", x AS (SELECT status + 2 * (step % 4) AS row_, (step // 4) * 64 + rve AS col_, s0 AS v FROM cells) SELECT CAST(a.row_ AS BIGINT) AS row1, CAST(b.row_ AS BIGINT) AS row2, round(sum(a.v * b.v), 2) AS g FROM x a JOIN x b ON a.col_ = b.col_ GROUP BY ALL")
def unfold_gram(spark, sf_dir):
    """Products of the rows of an unfolding, by a join on its columns: what a relational factorization starts from."""
    cells = grids.triaxial_cells(spark, sf_dir, *COARSE)
    idx = shapes.long_index([F.col("status"), F.col("step"), F.col("rve")], [2, 52, 64])
    row, col = shapes.unfold(idx, [2, 4, 13, 64], 2)
    x = cells.select(row.alias("row1"), col.alias("col"), F.col("s0").alias("v"))
    y = x.select(F.col("row1").alias("row2"), "col", F.col("v").alias("w"))
    return x.join(y, "col").groupBy("row1", "row2").agg(F.round(F.sum(F.col("v") * F.col("w")), 2).alias("g"))


