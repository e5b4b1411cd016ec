"""Errors of compressed tables, measured against their cells."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from traincube.functions import kernels as K
from traincube.functions.budget import Budget
from traincube.operators import compress, merge
from traincube.operators.trains import ARROW, SCHEMA, rows_of, unpack
from traincube.sources.grids import COMPONENTS, ParticleSet
from traincube.sources.scratch import stored

_SUMS = "variable string, level int, seg long, e2 double, x2 double, n long, vmin double, vmax double"
_ARROW = pa.schema([("variable", pa.string()), ("level", pa.int32()), ("seg", pa.int64()), ("e2", pa.float64()), ("x2", pa.float64()), ("n", pa.int64()), ("vmin", pa.float64()), ("vmax", pa.float64())])


def measured(trains: DataFrame, cells: DataFrame, shape: ParticleSet, orders: DataFrame | None = None, how: str = "stack") -> DataFrame:
    """variable, level, seg, n, vmin, vmax, fro, nrmse and rel_fro of each train of a tree, from its entries and the cells; blocks of a segment are taken together.

    Trains are cut into segments of level 0; the parts that belong to a segment meet its
    sparse cells in one task, which makes the dense array once for all levels and returns
    sums only. orders: the order table of trains whose entities are ordered.
    """
    parts = merge.parts(trains, shape.fanin, shape.segment, how).withColumn("places", F.lit(None).cast("array<array<int>>"))
    if orders is not None:
        parts = parts.unionByName(_order_rows(orders, parts))
    rows = compress.sparse(cells, shape)

    def run(t: pa.Table, own: pa.Table) -> pa.Table:
        _, levels, rates, used = next(compress.dense(t, shape))
        place, found = None, []
        for r in own.select(["places"]).to_pylist():
            if r["places"] is not None:
                place = np.array(r["places"])
        array = {"position": compress.placed(levels, place)[:used], "velocity": compress.placed(rates, place)[:used]}
        for r in rows_of(own.select(["variable", "level", "seg", "block", "cores"])):
            if r["variable"] is not None:
                x = array[r["variable"]]
                found.append({c: r[c] for c in ("variable", "level", "seg")} | _statistics(x) | {"e2": _missed(x, K.expand(unpack(r)), shape, r["block"])})
        return pa.Table.from_pylist(found, _ARROW)

    own = parts.withColumnRenamed("seg", "top").withColumnRenamed("part", "_part")
    sums = rows.groupBy("seg", "block").cogroup(own.groupBy("_part", "block")).applyInArrow(lambda a, b: run(a, b.rename_columns(["seg" if c == "top" else c for c in b.column_names])), _SUMS)
    return _errors(sums)


def _statistics(x: np.ndarray) -> dict:
    """Squares and range of an array."""
    return {"x2": float((x**2).sum()), "n": x.size, "vmin": float(x.min()), "vmax": float(x.max())}


def _missed(x: np.ndarray, y: np.ndarray, shape: ParticleSet, block: int) -> float:
    """Squares of what a train's entries y miss of an array [step, entity, component]; fastest if that is column-major too."""
    off = (x - y.reshape(shape.segment, shape.padded_size(block), len(COMPONENTS), order="F")[: x.shape[0], : x.shape[1]]).ravel(order="K")
    return float(off @ off)


def _errors(sums: DataFrame) -> DataFrame:
    span, e = F.max("vmax") - F.min("vmin"), F.sqrt(F.sum("e2"))
    return sums.groupBy("variable", "level", "seg").agg(
        F.sum("n").alias("n"), F.min("vmin").alias("vmin"), F.max("vmax").alias("vmax"), F.sqrt(F.sum("x2")).alias("fro"),
        F.when(span > 0, e / F.sqrt(F.sum("n")) / span).when(e == 0, 0.0).alias("nrmse"), F.when(F.sum("x2") > 0, e / F.sqrt(F.sum("x2"))).otherwise(0.0).alias("rel_fro"),
    )


def tree_in_tasks(cells: DataFrame, shape: ParticleSet, budget: Budget, share: float = 1.0, fanin: tuple[int, ...] | None = None) -> tuple[DataFrame, DataFrame]:
    """The trees of a set with blocks, and their measured errors: trains without cores, and measured().

    A task has all segments of a block, or a run of them without levels to merge. Level 0 is
    measured where it is made and its cores go once they are merged; the levels above are
    measured against the arrays, which are made anew one segment at a time. So nothing but
    statistics leaves it.
    """
    fanin = shape.fanin if fanin is None else fanin
    run = shape.segments if fanin else compress.run_of(shape)
    rows = compress.compressor(shape, budget, share=share, box=compress.level_box(cells) if shape.order != "none" else None, keep_order=True, keep_array=True)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t, tree = pa.Table.from_batches(list(batches)), []
        block, place, found, now = t.column("block")[0].as_py(), {}, {}, {}

        def note(r: dict, known: dict, x: np.ndarray, y: np.ndarray) -> None:
            at = r["variable"], r["level"], r["seg"]
            new, old = {"e2": _missed(x, y, shape, block)} | known, found.get(at)
            found[at] = new if old is None else {c: (min if c == "vmin" else max if c == "vmax" else float.__add__ if c != "n" else int.__add__)(old[c], new[c]) for c in new}

        def first() -> Iterator[dict]:
            for s, levels, rates, used in compress.dense(t, shape, run):
                for r in rows(s, block, levels, rates, used):
                    places, x = r.pop("places"), r.pop("array")
                    if places is not None and fanin:
                        place[s] = np.array(places)
                    note(r, _statistics(x), np.asfortranarray(x), K.expand(unpack(r)))
                    yield r

        for r in merge.merge_along(first(), fanin, budget):
            tree.append(r if r["level"] else r | {"cores": None})
        above = [(r, range(r["seg"] * step, (r["seg"] + 1) * step)) for r in tree if r["level"] for step in [int(np.prod(fanin[: r["level"]], dtype=int))]]
        for s, levels, rates, used in compress.dense(t, shape, run) if above else ():
            array = {"position": compress.placed(levels, place.get(s))[:used], "velocity": compress.placed(rates, place.get(s))[:used]}
            known = {name: _statistics(x) for name, x in array.items()}
            array = {name: np.asfortranarray(x) for name, x in array.items()}
            for r, own in above:
                if s in own:
                    name, at = r["variable"], (r["variable"], r["level"])
                    if s == own[0]:
                        now[at] = merge.expander(r, fanin)
                    note(r, known[name], array[name], now[at](s))
        yield pa.RecordBatch.from_pylist([r | {"cores": None} | {f"m_{c}": v for c, v in found[r["variable"], r["level"], r["seg"]].items()} for r in tree], _TREE)

    out = stored(compress.dealt(compress.sparse(cells, shape, run=run), shape, run, 1).applyInArrow(work, SCHEMA + ", " + _SUMS.partition("seg long, ")[2].replace("e2", "m_e2").replace("x2", "m_x2").replace("n long", "m_n long").replace("vmin", "m_vmin").replace("vmax", "m_vmax")))
    return out.select(ARROW.names), _errors(out.select("variable", "level", "seg", *(F.col(f"m_{c}").alias(c) for c in ("e2", "x2", "n", "vmin", "vmax"))))


_TREE = pa.schema([*ARROW, *(pa.field(f"m_{f.name}", f.type) for f in list(_ARROW)[3:])])


def _order_rows(orders: DataFrame, like: DataFrame) -> DataFrame:
    """Order tables as rows that go with the parts."""
    known = {"part": F.col("seg"), "block": F.col("block"), "places": F.col("places"), "level": F.lit(-1), "seg": F.lit(-1).cast("long")}
    return orders.select(*(known.get(f.name, F.lit(None).cast(f.dataType)).alias(f.name) for f in like.schema))

