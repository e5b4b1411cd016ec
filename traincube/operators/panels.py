"""Factorization of one array that no task can hold.

The array lies as column panels of its current matrix. For each mode the left
factor comes from a tree of QR factors of transposed panels, whose last one, a
square of the row count, is all that the driver sees; then every panel is
projected where it lies. Panels hold whole numbers of the later modes, so the next
reshape needs no shuffle.
"""

from __future__ import annotations

from math import prod, sqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from traincube.functions import kernels as K
from traincube.sources.scratch import stored

_PANEL = "panel long, cells array<double>"
#: Numbers that may come to the driver at once.
MOST_ON_DRIVER = 1 << 24
#: Below this tolerance sums of products lose the digits that decide.
GRAM_LEAST = 1e-6


def panels(cells: DataFrame, modes: list[int], inside: int) -> DataFrame:
    """Cells (idx, val), missing ones zero, as panels over the first ``inside`` modes."""
    size = prod(modes[:inside])

    def run(key, t):
        x = np.zeros(size)
        x[t.column("at").to_numpy()] = t.column("val").to_numpy()
        return pa.Table.from_pydict({"panel": [key[0].as_py()], "cells": pa.array([x], pa.list_(pa.float64()))})

    own = cells.select(F.floor(F.col("idx") / size).cast("long").alias("panel"), F.pmod(F.col("idx"), F.lit(size)).cast("long").alias("at"), F.col("val").cast("double").alias("val"))
    every = cells.sparkSession.range(prod(modes[inside:])).select(F.col("id").alias("panel"), F.lit(0).cast("long").alias("at"), F.lit(0.0).alias("val"))
    summed = own.unionByName(every).groupBy("panel", "at").agg(F.sum("val").alias("val"))
    return summed.groupBy("panel").applyInArrow(run, _PANEL)


def _tree(frame: DataFrame, rows: int, fanin: int = 16) -> np.ndarray:
    """The triangular factor of the transposed matrix, by levels of QR."""

    def first(batches):
        for x in batches:
            r = np.zeros((0, rows))
            for c in x.column("cells"):
                r = np.linalg.qr(np.concatenate((r, c.values.to_numpy().reshape(rows, -1, order="F").T)), mode="r")
            yield pa.RecordBatch.from_pydict({"node": pa.array([x.column("panel")[0].as_py()]), "r": pa.array([r.ravel()], pa.list_(pa.float64()))})

    def join(key, t):
        parts = [np.asarray(v.values.to_numpy()).reshape(-1, rows) for v in t.column("r")]
        return pa.Table.from_pydict({"node": pa.array([key[0].as_py()]), "r": pa.array([np.linalg.qr(np.concatenate(parts), mode="r").ravel()], pa.list_(pa.float64()))})

    now = stored(frame.mapInArrow(first, "node long, r array<double>"))
    count = now.count()
    while count > fanin:
        now = stored(now.withColumn("node", F.floor(F.xxhash64("node") % (count // fanin)).cast("long")).groupBy("node").applyInArrow(join, "node long, r array<double>"))
        count = now.count()
    parts = [np.array(r["r"]).reshape(-1, rows) for r in now.collect()]
    return np.linalg.qr(np.concatenate(parts), mode="r")


def _gram(frame: DataFrame, rows: int) -> np.ndarray:
    """The product of the matrix with its transpose: each task adds up those of its panels, and rows of these are summed by number."""

    def part(batches):
        g = np.zeros((rows, rows))
        for x in batches:
            for c in x.column("cells"):
                m = c.values.to_numpy().reshape(rows, -1, order="F")
                g += m @ m.T
        yield pa.RecordBatch.from_pydict({"i": pa.array(np.arange(rows)), "g": pa.array(list(g), pa.list_(pa.float64()))})

    def add(key, t):
        return pa.Table.from_pydict({"i": pa.array([key[0].as_py()]), "g": pa.array([sum(np.asarray(v.values.to_numpy()) for v in t.column("g"))], pa.list_(pa.float64()))})

    _checked(rows * rows, "a product of the matrix with its transpose")
    done = frame.mapInArrow(part, "i long, g array<double>").groupBy("i").applyInArrow(add, "i long, g array<double>").orderBy("i").toArrow()
    return np.stack([v.values.to_numpy() for v in done.column("g")])


def _checked(numbers: int, what: str) -> None:
    if numbers > MOST_ON_DRIVER:
        raise ValueError(f"{what} has {numbers} numbers, more than the {MOST_ON_DRIVER} that the driver takes; use another number of leading modes or a larger tolerance")


def _left(frame: DataFrame, rows: int, method: str) -> tuple[np.ndarray, np.ndarray]:
    """Left singular vectors and singular values of the matrix that the panels make up."""
    if method == "gram":
        value, u = np.linalg.eigh(_gram(frame, rows))
        return u[:, ::-1], np.sqrt(np.maximum(value[::-1], 0))
    u, sigma, _ = np.linalg.svd(_tree(frame, rows).T)
    return u, sigma


def unfolding_rank(cells: DataFrame, modes: list[int], k: int, delta: float) -> int:
    """The least rank of a matrix within relative error delta of the unfolding over the first k modes; no train within delta has a smaller rank there."""
    frame = stored(panels(cells, modes, k))
    _, sigma = _left(frame, prod(modes[:k]), "qr")
    norm = float(np.linalg.norm(sigma))
    return K.cut_rank(sigma, delta * norm) if norm else 1


def decompose(cells: DataFrame, modes: list[int], tau: float, inside: int, method: str = "qr") -> tuple[K.Train, float]:
    """As kernels.decompose, over panels of the first ``inside`` modes; the last modes are done on what is left, when it is small.

    method: qr, or gram, which moves less but squares the condition number and so is for tolerances from GRAM_LEAST on.
    """
    if method == "gram" and tau < GRAM_LEAST:
        raise ValueError(f"gram needs a tolerance of {GRAM_LEAST} or more")
    frame = stored(panels(cells, modes, inside))
    norm2 = frame.select(F.aggregate("cells", F.lit(0.0), lambda s, x: s + x * x).alias("s")).agg(F.sum("s")).first()[0]
    norm = sqrt(norm2 or 0.0)
    if norm == 0:
        return [np.zeros((1, n, 1)) for n in modes], 0.0
    threshold, lost, cores, rank = tau * norm / sqrt(max(1, len(modes) - 1)), 0.0, [], 1
    for n in modes[:inside]:
        rows = rank * n
        u, sigma = _left(frame, rows, method)
        r = K.cut_rank(sigma, threshold)
        lost += float((sigma[r:] ** 2).sum())
        u = u[:, :r] * np.where(u[np.abs(u[:, :r]).argmax(0), np.arange(r)] < 0, -1.0, 1.0)
        cores.append(u.reshape(rank, n, r, order="F"))

        def project(batches, u=u, rows=rows):
            for x in batches:
                done = [(u.T @ c.values.to_numpy().reshape(rows, -1, order="F")).ravel(order="F") for c in x.column("cells")]
                yield pa.RecordBatch.from_arrays([x.column("panel"), pa.array(done, pa.list_(pa.float64()))], ["panel", "cells"])

        frame, rank = stored(frame.mapInArrow(project, _PANEL)), r
    # One column of ``rank`` numbers is left of each panel.
    _checked(rank * prod(modes[inside:]), "what is left for the last modes")
    rest = np.concatenate([np.array(r["cells"]) for r in frame.orderBy("panel").collect()])
    tail = modes[inside:]
    if not tail:
        cores[-1] = np.tensordot(cores[-1], rest.reshape(rank, 1), (2, 0))
        return cores, lost
    own, more = K.decompose(rest, [rank, *tail], 0.0) if len(tail) == 1 else K.decompose(rest, [rank * tail[0], *tail[1:]], threshold * sqrt(max(1, len(tail) - 1)) / float(np.linalg.norm(rest)))
    if len(tail) == 1:
        return [*cores, rest.reshape(rank, tail[0], 1, order="F")], lost
    head = own[0].reshape(rank, tail[0], -1, order="F")
    return [*cores, head, *own[1:]], lost + more
