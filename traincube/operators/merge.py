"""Joining trains of neighbouring segments, level by level."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from math import prod, sqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from traincube.functions import kernels as K
from traincube.functions.budget import Budget
from traincube.operators.trains import ARROW, SCHEMA, pack, rows_of, table, unpack
from traincube.sources.scratch import stored


def merged(rows: list[dict], budget: Budget, share: float, how: str, axis: int = 0) -> dict:
    """The train of neighbouring segments in order.

    Squared errors of the parts add, as they stand side by side. Of what the target
    then leaves, rounding takes ``share``; its error adds by the triangle inequality.
    """
    rows = sorted(rows, key=lambda r: r["seg"])
    trains = [unpack(r) for r in rows]
    n, original, fro2 = (sum(r[c] for r in rows) for c in ("n", "n_original", "fro2"))
    vmin, vmax = min(r["vmin"] for r in rows), max(r["vmax"] for r in rows)
    so_far = sqrt(sum(r["err_abs"] ** 2 for r in rows))
    norm = sqrt(fro2)
    left = max(0.0, budget.absolute(original, vmin, vmax, norm) - so_far)
    tau = max(left * share / norm if norm else 0.0, 1e-14)
    if how == "stack":
        cores, lost = K.stack_rounded(trains, tau)
    elif axis == 0:
        cores, lost = K.concat_rounded(trains, tau)
    else:
        cores, lost = K.recompress(K.concat(trains, axis), tau)
    return pack(cores, variable=rows[0]["variable"], level=rows[0]["level"] + 1, seg=0, block=rows[0]["block"], n=n, n_original=original, vmin=vmin, vmax=vmax, fro2=fro2, err_abs=so_far + sqrt(lost), steps=sum(r["steps"] for r in rows))


def merge_level(trains: DataFrame, fanin: int, budget: Budget, share: float = 1.0, how: str = "stack", axis: int = 0) -> DataFrame:
    """One level up: ``fanin`` neighbours become one. A last group that is short is merged as it is."""

    def run(key, t):
        rows = list(rows_of(t.select([f for f in t.column_names if f != "parent"])))
        return table([merged(rows, budget, share, how, axis) | {"seg": key[2].as_py()}])

    parent = trains.withColumn("parent", F.floor(F.col("seg") / fanin).cast("long"))
    return parent.groupBy("variable", "block", "parent").applyInArrow(run, SCHEMA)


def merge_tree(trains: DataFrame, fanin: tuple[int, ...], budget: Budget, how: str = "stack", axis: int = 0) -> DataFrame:
    """All levels, from level 0 on; each is stored before the next is made from it."""
    now = stored(trains)
    out = now
    for k, f in enumerate(fanin):
        now = stored(merge_level(now, f, budget, 1.0 / (len(fanin) - k), how, axis))
        out = out.unionByName(now)
    return out


def merge_rows(rows: list[dict], fanin: tuple[int, ...], budget: Budget, how: str = "stack", axis: int = 0) -> list[dict]:
    """merge_tree() of rows that are in one task: all levels."""
    now, out = rows, list(rows)
    for k, f in enumerate(fanin):
        groups: dict[tuple, list[dict]] = {}
        for r in now:
            groups.setdefault((r["variable"], r["block"], r["seg"] // f), []).append(r)
        now = [merged(g, budget, 1.0 / (len(fanin) - k), how, axis) | {"seg": at[2]} for at, g in groups.items()]
        out += now
    return out


def merge_along(rows: Iterable[dict], fanin: tuple[int, ...], budget: Budget, how: str = "stack", axis: int = 0) -> Iterator[dict]:
    """merge_rows() of rows that come one after another, each once it is in the row above it, so that few cores are held at a time."""
    waiting: list[dict[tuple, list[dict]]] = [{} for _ in fanin]

    def add(k: int, r: dict) -> Iterator[dict]:
        if k == len(fanin):
            yield r
            return
        at = r["variable"], r["block"], r["seg"] // fanin[k]
        waiting[k].setdefault(at, []).append(r)
        if len(waiting[k][at]) == fanin[k]:
            yield from close(k, at)

    def close(k: int, at: tuple) -> Iterator[dict]:
        group = waiting[k].pop(at)
        above = merged(group, budget, 1.0 / (len(fanin) - k), how, axis) | {"seg": at[2]}
        while group:
            yield group.pop(0)
        yield from add(k + 1, above)

    for r in rows:
        yield from add(0, r)
    for k in range(len(fanin)):  # what is left are last groups, which are short
        for at in list(waiting[k]):
            yield from close(k, at)


def pieces(r: dict, fanin: tuple[int, ...], span: int, how: str = "stack"):
    """The segments of level 0 that a train row holds, and the train of each."""
    cores, level = unpack(r), r["level"]
    if how == "stack":
        sizes = [c.shape[1] for c in cores[len(cores) - level :]]
        for digits in np.ndindex(*sizes):
            part = r["seg"]
            for f, d in zip(reversed(fanin[:level]), reversed(digits)):
                part = part * f + d
            at = {len(cores) - level + k: d for k, d in enumerate(digits)}
            yield part, K.fix(cores, at) if at else cores
    else:
        first = r["seg"] * int(np.prod(fanin[:level], dtype=int))
        for k in range(cores[0].shape[1] // span):
            yield first + k, [cores[0][:, k * span : (k + 1) * span], *cores[1:]]


def piece(r: dict, s: int, fanin: tuple[int, ...]) -> K.Train:
    """The train of segment s of level 0 in a stacked one that holds it."""
    cores = unpack(r)
    at = {len(cores) - r["level"] + k: d for k, d in enumerate(_digits(r, s, fanin))}
    return K.fix(cores, at) if at else cores


def _digits(r: dict, s: int, fanin: tuple[int, ...]) -> list[int]:
    """The indices of segment s in the modes that stacking added."""
    step, out = 1, []
    for f in fanin[: r["level"]]:
        out.append(s // step % f)
        step *= f
    return out


#: Numbers that are kept of a train whose segments are expanded one after another.
_KEPT = 1 << 21


def expander(r: dict, fanin: tuple[int, ...], most: int = _KEPT):
    """A function of a segment s of level 0 that gives its entries in a stacked train that holds it.

    What the segments share, the entries for each rank before the modes that stacking
    added, is made once, unless it is more than ``most`` numbers.
    """
    cores = unpack(r)
    own = len(cores) - r["level"]
    if not r["level"] or prod(c.shape[1] for c in cores[:own]) * cores[own].shape[0] > most:
        return lambda s: K.expand(piece(r, s, fanin))
    shared, rest = K.rows(cores[:own]), cores[own:]

    def entries(s: int) -> np.ndarray:
        weight = np.ones(1)
        for c, d in zip(reversed(rest), reversed(_digits(r, s, fanin))):
            weight = c[:, d] @ weight
        return weight @ shared

    return entries


def parts(trains: DataFrame, fanin: tuple[int, ...], span: int, how: str = "stack") -> DataFrame:
    """Trains of a tree cut into its segments of level 0: variable, level, seg, block, part (the segment) and cores.

    Cutting fixes the modes that stacking added, or takes a range of the joined one; nothing is expanded.
    """

    def run(batches):
        for x in batches:
            for r in rows_of(x):
                for part, cores in pieces(r, fanin, span, how):
                    yield pa.RecordBatch.from_pylist([{c: r[c] for c in ("variable", "level", "seg", "block")} | {"part": part, "cores": pack(cores)["cores"]}], _PARTS)

    return trains.mapInArrow(run, "variable string, level int, seg long, block int, part long, cores array<struct<k: int, r_left: int, n: int, r_right: int, core: array<double>>>")


_PARTS = pa.schema([ARROW.field(c) if c != "part" else pa.field("part", pa.int64()) for c in ("variable", "level", "seg", "block", "part", "cores")])
