"""Compression of arrays in tables, one task for each segment or tensor."""

from __future__ import annotations

from collections.abc import Iterator
from math import prod

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from traincube.functions import kernels as K
from traincube.functions.budget import Budget
from traincube.functions.ordering import hilbert_array, morton_array, unit_array
from traincube.functions.shapes import modes_for_particles
from traincube.operators import panels
from traincube.operators.trains import ARROW, SCHEMA, compressed, pack, rows_of, table, unpack
from traincube.sources.grids import COMPONENTS, ParticleSet, level_box

#: An array and its working copies must fit a task.
MOST_CELLS = 1 << 28
BITS = 10


def running_sums(own: DataFrame, first: int = 0, base: DataFrame | None = None) -> DataFrame:
    """Totals of each entity up to the end of each segment in which it has cells (seg, entity, c1, c2, c3), added in the order of segments.

    base: totals (entity, c1, c2, c3) before the first segment, which stand as those of the one before it.
    """
    sums = own.groupBy("seg", "entity").agg(*(F.sum(c).alias(c) for c in COMPONENTS))
    if base is not None:
        sums = sums.unionByName(base.select(F.lit(first - 1).cast("long").alias("seg"), F.col("entity").cast("int").alias("entity"), *COMPONENTS))
    w = Window.partitionBy("entity").orderBy("seg").rowsBetween(Window.unboundedPreceding, 0)
    return sums.select("seg", "entity", *(F.sum(c).over(w).alias(c) for c in COMPONENTS))


def sparse(cells: DataFrame, shape: ParticleSet, only: tuple[int, int] | None = None, base: DataFrame | None = None, run: int = 1) -> DataFrame:
    """What each task needs of sparse cells (step, entity, c1, c2, c3) of rates: (seg, block, at, entity, c1, c2, c3).

    A task has one block of entities and ``run`` neighbouring segments, which seg numbers.
    at is the step in them, -1 for totals before them, and -2 for a row that every task
    has. only (for single segments): first segment, and the one after the last; base: totals
    (entity, c1, c2, c3) before the first one, if cells hold nothing earlier.
    """
    count = -(-shape.segments // run)
    span, first, last = shape.segment * run, *(only or (0, count))
    seg = F.floor(F.col("step") / span).cast("long")
    own = cells.select(seg.alias("seg"), F.pmod(F.col("step"), F.lit(span)).cast("int").alias("at"), F.col("entity").cast("int").alias("entity"), *COMPONENTS)
    block = F.floor(F.col("entity") / shape.block).cast("int").alias("block")
    rows = own.where(F.col("seg").between(first, last - 1))
    if count > 1 or base is not None:
        w = Window.partitionBy("entity").orderBy("seg")
        # Totals up to a run's end are the totals before every later one until the entity moves again.
        totals = running_sums(own, first, base).select("entity", (F.col("seg") + 1).alias("first"), F.coalesce(F.lead("seg").over(w), F.lit(count - 1)).alias("last"), *COMPONENTS)
        totals = totals.withColumns({"first": F.greatest("first", F.lit(first)), "last": F.least("last", F.lit(last - 1))})
        rows = rows.unionByName(totals.where("first <= last").select(F.explode(F.sequence("first", "last")).alias("seg"), F.lit(-1).alias("at"), "entity", *COMPONENTS))
    each = F.explode(F.sequence(F.lit(0), F.lit((shape.blocks - 1) * shape.block), F.lit(shape.block))) if shape.blocks > 1 else F.lit(0)
    every = cells.sparkSession.range(first, last).select(F.col("id").alias("seg"), F.lit(-2).alias("at"), each.alias("entity"), *(F.lit(0.0).alias(c) for c in COMPONENTS))
    return rows.unionByName(every).select("seg", block, "at", "entity", *COMPONENTS)


def dense(t: pa.Table, shape: ParticleSet, run: int = 1):
    """For each segment of a task in turn: its number, levels and rates [step, entity, component] by entity, and how many of its steps are not padding."""
    first, block = t.column("seg")[0].as_py() * run, t.column("block")[0].as_py()
    at, entity = t.column("at").to_numpy(), t.column("entity").to_numpy() - block * shape.block
    value = np.stack([t.column(c).to_numpy() for c in COMPONENTS], -1)
    level, base = np.zeros((shape.size(block), len(COMPONENTS))), at == -1
    level[entity[base]] += value[base]
    order = np.argsort(at, kind="stable")
    cuts = np.searchsorted(at[order], np.arange(run + 1) * shape.segment)
    for k in range(min(run, shape.segments - first)):
        inside = order[cuts[k] : cuts[k + 1]]
        rates = np.zeros((shape.segment, *level.shape))
        rates[at[inside] - k * shape.segment, entity[inside]] = value[inside]
        levels = np.empty_like(rates)
        for j in range(shape.segment):  # far faster than cumsum along the first axis, and the same sums
            levels[j] = levels[j - 1] + rates[j] if j else rates[0]
        levels += level
        used = min(shape.segment, shape.steps - (first + k) * shape.segment)
        levels[used:], rates[used:] = levels[used - 1], rates[used - 1]
        level = levels[-1].copy()
        yield first + k, levels, rates, used


def dealt(rows: DataFrame, shape: ParticleSet, run: int, each: int = 4, most: int = 512) -> DataFrame:
    """Rows of sparse() by task; of blocks, about ``each`` tasks' rows in a partition, so that few trains travel together, or more where there would be over ``most`` partitions."""
    if shape.blocks == 1:
        return rows.groupBy("seg", "block")
    count = -(-shape.segments // run)
    parts = min(most, -(-shape.blocks * count // each))
    keys = _even_keys(rows.sparkSession, parts)
    # Hashes of seg and block themselves would leave a third of the partitions empty and give others several tasks' rows.
    deal = F.element_at(F.array(*map(F.lit, keys)), (F.pmod(F.col("block").cast("long") * count + F.col("seg"), F.lit(parts)) + 1).cast("int"))
    return rows.withColumn("deal", deal).repartition(parts, "deal").groupBy("deal", "seg", "block")


def _hashes(spark: SparkSession, parts: int, count: int) -> list[int]:
    return [r[0] for r in spark.range(count).select(F.pmod(F.hash(F.col("id").cast("int")), F.lit(parts))).collect()]


def _even_keys(spark: SparkSession, parts: int) -> list[int]:
    """For each of ``parts`` partitions a number that a hash puts there."""
    count = 4 * parts
    while True:
        found = {p: k for k, p in reversed(list(enumerate(_hashes(spark, parts, count))))}
        if len(found) == parts:
            return [found[p] for p in range(parts)]
        count *= 2


def run_of(shape: ParticleSet, tasks: int = 96) -> int:
    """Segments that a task takes in turn: one, or of many blocks so many that tasks are about ``tasks``; totals before each run travel only."""
    return min(shape.segments, max(1, shape.blocks * shape.segments // tasks)) if shape.blocks > 1 else 1


def placed(x: np.ndarray, place: np.ndarray | None) -> np.ndarray:
    """Entities in the order of each step."""
    if place is None:
        return x
    return x[:, place[0]] if len(place) == 1 else np.take_along_axis(x, place[:, :, None], 1)


def filled(x: np.ndarray, padded: int) -> np.ndarray:
    """An array with its last entity repeated up to ``padded`` places."""
    return np.concatenate((x, np.repeat(x[:, -1:], padded - x.shape[1], 1)), 1) if padded > x.shape[1] else x


def segments(
    cells: DataFrame,
    shape: ParticleSet,
    budget: Budget,
    tensorize: bool = True,
    share: float = 1.0,
    box: tuple[list[float], list[float]] | None = None,
    variables: tuple[str, ...] = ("position", "velocity"),
    only: tuple[int, int] | None = None,
    base: DataFrame | None = None,
    keep_order: bool = False,
    max_rank: int | None = None,
    then=None,
    run: int = 1,
    emit=None,
    along=None,
) -> DataFrame:
    """Trains of all segments from sparse cells (step, entity, c1, c2, c3) of rates; see sparse() for only and base.

    A task gets the cells of a segment, or of a run of them, and, for each entity with
    earlier rows, one row of totals before them; dense arrays exist in that task only, one
    segment at a time. A segment that is too large is cut into blocks of entities, which
    are compressed, ordered and padded each by itself. Steps after
    the last and entities after the last repeat the last ones. keep_order: the first
    variable's rows also have ``places``, the entity at each place, for each step of the
    segment, or once if all steps have the same order; see orders(). then: what the rows of
    ``run`` segments become before they leave the task. emit: a function of a train's row
    that gives record batches, and their columns; these leave the task and no train
    travels, such as trains.light or trains.expanded. along: as then, but a function of the
    iterator of all rows of a task, which are made as it takes them.
    """
    rows = compressor(shape, budget, tensorize, share, (box or level_box(cells)) if shape.order != "none" else None, variables, keep_order, max_rank)
    schema = ARROW.append(_PLACES) if keep_order else ARROW
    leave, columns = emit or (lambda r: [pa.RecordBatch.from_pylist([r], schema)], SCHEMA + (", places array<array<int>>" if keep_order else ""))
    # Only whole groups of ``run`` segments meet in a task.
    task = run if only else run * max(1, run_of(shape) // run)

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(list(batches))
        block = t.column("block")[0].as_py()

        def made() -> Iterator[dict]:
            kept = []
            for s, levels, rates, used in dense(t, shape, task):
                kept += rows(s, block, levels, rates, used)
                if (s + 1) % (1 if along else run) == 0 or s + 1 == shape.segments:
                    yield from then(kept) if then else kept
                    kept = []

        for r in along(made()) if along else made():
            yield from leave(r)

    return dealt(sparse(cells, shape, only, base, task), shape, task, 1 if emit else 4).applyInArrow(build, columns)


def compressor(shape: ParticleSet, budget: Budget, tensorize: bool = True, share: float = 1.0, box: tuple[list[float], list[float]] | None = None, variables: tuple[str, ...] = ("position", "velocity"), keep_order: bool = False, max_rank: int | None = None, keep_array: bool = False):
    """The function that turns one segment of dense() into its train rows; arrays are checked to fit a task. keep_array: rows have the ``array`` without padding too."""
    span, order = shape.segment, shape.order
    places = max(shape.padded_size(b) for b in (0, shape.blocks - 1))
    if span * places * len(COMPONENTS) > MOST_CELLS:
        raise ValueError(f"a segment of {span} x {places} x {len(COMPONENTS)} cells does not fit a task; take fewer steps, or operators.panels")

    def rows(s: int, block: int, levels: np.ndarray, rates: np.ndarray, used: int) -> list[dict]:
        padded = shape.padded_size(block)
        modes = modes_for_particles(span, padded, len(COMPONENTS)) if tensorize else [span, padded, len(COMPONENTS)]
        place = _order(levels, order, *(box or (None, None)))
        out = []
        for name, x in (("position", levels), ("velocity", rates)):
            if name in variables:
                x = placed(x, place)
                row = compressed(filled(x, padded).ravel(order="F"), modes, budget, share, x[:used].ravel(), max_rank, variable=name, level=0, seg=s, steps=span, block=block)
                if keep_array:
                    row["array"] = x[:used]
                out.append(row | ({"places": None if out or place is None else list(place.astype(np.int32))} if keep_order else {}))
        return out

    return rows


_PLACES = pa.field("places", pa.list_(pa.list_(pa.int32())))


def orders(trains: DataFrame) -> DataFrame:
    """seg, block and places of trains that were made with keep_order; a stored table reads these columns only."""
    return trains.where("places is not null").select("seg", "block", "places")


def restore_identity(cells: DataFrame, orders: DataFrame, segment: int) -> DataFrame:
    """Cells (step, place, ...) of ordered trains with the entity at each place: an equi-join with the order table."""
    rank = orders.select("seg", F.posexplode("places").alias("_at", "own"), F.size("places").alias("_n"))
    rank = rank.select("seg", F.when(F.col("_n") == 1, F.lit(-1)).otherwise(F.col("_at")).alias("_at"), F.posexplode("own").alias("place", "entity"))
    at = F.pmod(F.col("step"), F.lit(segment)).cast("int")
    seg = F.floor(F.col("step") / segment).cast("long")
    each_step = rank.where("_at < 0").isEmpty()
    own = cells.withColumns({"_seg": seg, "_at": at if each_step else F.lit(-1)})
    return own.join(rank.withColumnRenamed("seg", "_seg"), ["_seg", "_at", "place"]).drop("_seg", "_at", "place")


def expand_ordered(trains: DataFrame, shape: ParticleSet) -> DataFrame:
    """seg, step, entity, comp and val of trains with their places, put back by entity where they are expanded; one row of places stands for all steps."""
    span = shape.segment

    def run(batches):
        for x in batches:
            for r, places in zip(rows_of(x.drop_columns(["places"])), x.column("places")):
                n = shape.size(r["block"])
                y = K.expand(unpack(r)).reshape(span, -1, len(COMPONENTS), order="F")[:, :n]
                place = np.array(places.as_py()) if places.as_py() is not None else np.arange(n)[None]
                step, _, comp = np.indices(y.shape)
                entity = np.broadcast_to(place[:, :, None], y.shape) + r["block"] * shape.block
                yield pa.RecordBatch.from_pydict({"seg": np.full(y.size, r["seg"], np.int64), "step": r["seg"] * span + step.ravel(), "entity": entity.ravel().astype(np.int64), "comp": comp.ravel(), "val": y.ravel()})

    return trains.select("seg", "block", "cores", "places").mapInArrow(run, "seg long, step long, entity long, comp long, val double")


def _order(levels: np.ndarray, order: str, low: list[float], high: list[float]) -> np.ndarray | None:
    """Entity at each place, for each step or, in one row, for all; ties by entity."""
    if order == "none":
        return None
    key = hilbert_array if order.startswith("hilbert") else morton_array
    if order.endswith("every"):
        return np.argsort(key(unit_array(levels, low, high, BITS), BITS), axis=1, kind="stable")
    return np.argsort(key(unit_array(levels[0], low, high, BITS), BITS), kind="stable")[None]


def arrays(cells: DataFrame, build, *keys: str) -> DataFrame:
    """Trains for each combination of keys, "variable" by default; build turns these and their cells into train rows (see trains.compressed)."""
    keys = keys or ("variable",)

    def run(t):
        return table(build(*(t.column(k)[0].as_py() for k in keys), t))

    return cells.groupBy(*keys).applyInArrow(run, SCHEMA)


def per_row(jobs: DataFrame, build) -> DataFrame:
    """One list of train rows for each row of small jobs: sampled functions and sweeps."""

    def run(batches):
        for x in batches:
            for row in x.to_pylist():
                yield pa.RecordBatch.from_pylist(build(row), ARROW)

    return jobs.mapInArrow(run, SCHEMA)


def factorized(cells: DataFrame, modes: list[int], tau: float, memory: int, inside: int | None = None) -> tuple[K.Train, float]:
    """The train of one array of cells (idx, val) and its squared error, in one task if the array and its copies fit ``memory`` bytes, else by panels."""
    if strategy(prod(modes), memory) == "task":

        def run(t):
            x = np.zeros(prod(modes))
            np.add.at(x, t.column("idx").to_numpy(), t.column("val").to_numpy())
            cores, lost = K.decompose(x, modes, tau)
            return table([pack(cores, variable="", level=0, seg=0, err_abs=lost)])

        row = cells.select(F.lit(0).alias("_one"), "idx", F.col("val").cast("double").alias("val")).groupBy("_one").applyInArrow(run, SCHEMA).collect()
        return (unpack(row[0].asDict(True)), row[0]["err_abs"]) if row else K.decompose(np.zeros(prod(modes)), modes, tau)
    # As many leading modes as one panel holds in a task.
    fit = next(k for k in range(len(modes) - 1, 0, -1) if k == 1 or strategy(prod(modes[:k]), memory) == "task")
    return panels.decompose(cells, modes, tau, inside or fit)


def strategy(cells: int, memory: int, copies: int = 6) -> str:
    """Where an array is factorized: in one task if it and its working copies fit, else by panels."""
    return "task" if 8 * cells * copies <= memory else "panels"
