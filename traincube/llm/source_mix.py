"""Mixing sources to target weights by minimum-cost flow.

Documents may belong to several sources. They are aggregated by membership
pattern; a flow network routes each pattern's words to the quotas of its sources,
where every further pass over the same documents costs more than the one before.
The flow into a pattern fixes how many whole copies all its documents get and how
many words of one more copy are drawn; those documents are drawn in the order of
a seeded hash.

Size is the number of words; null text has none. A null source is a source of its
own, after the others. Rows are drawn by id, size and text; rows equal in all of
these are told apart by place only where the drawing ends between them. Empty tables
give an empty result; other columns aren't read.
"""

from __future__ import annotations

from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from traincube.llm.scratch import materialize
from traincube.llm.words import Words, blocks, documents

WEIGHTS = (3, 1, 2)
_BUCKETS = 4096
#: Up to so many membership patterns their plan is broadcast; more of them are joined.
_MOST_PATTERNS = 20_000


def targets(sizes: list[int], weights: list[float], share: float = 1.5, most: float = 2.0) -> list[float]:
    """Shares of ``share`` times all sizes by weight; what exceeds ``most`` times a size goes to the others by weight."""
    out, open_ = [0.0] * len(sizes), set(range(len(sizes)))
    left = share * sum(sizes)
    while open_:
        unit = left / sum(weights[i] for i in open_)
        above = [i for i in open_ if unit * weights[i] > most * sizes[i]]
        if not above:
            for i in open_:
                out[i] = unit * weights[i]
            break
        for i in above:
            out[i] = float(most * sizes[i])
            left -= out[i]
            open_.remove(i)
    return out


def route(capacity: list[int], members: list[tuple[int, ...]], quota: list[int], passes: int) -> np.ndarray:
    """Minimum-cost maximum flow [pattern, source] by successive shortest paths.

    Pass k over a pattern's words costs k a word, so the cost is convex in the
    number of repetitions.
    """
    n_p, n_s = len(capacity), len(quota)
    source, sink = n_p + n_s, n_p + n_s + 1
    to: list[int] = []
    room: list[int] = []
    cost: list[int] = []
    out: list[list[int]] = [[] for _ in range(sink + 1)]

    def edge(a, b, c, w):
        for x, y, r, v in ((a, b, c, w), (b, a, 0, -w)):
            out[x].append(len(to))
            to.append(y)
            room.append(r)
            cost.append(v)

    for p, c in enumerate(capacity):
        for k in range(passes):
            edge(source, p, c, k)
    first = len(to)
    for p, own in enumerate(members):
        for s in own:
            edge(p, n_p + s, passes * capacity[p], 0)
    last = len(to)
    for s, q in enumerate(quota):
        edge(n_p + s, sink, q, 0)
    while True:
        dist, via, inside = {source: 0}, {}, {source}
        line = deque([source])
        while line:
            x = line.popleft()
            inside.discard(x)
            for e in out[x]:
                if room[e] and dist[x] + cost[e] < dist.get(to[e], 1 << 60):
                    dist[to[e]], via[to[e]] = dist[x] + cost[e], e
                    if to[e] not in inside:
                        inside.add(to[e])
                        line.append(to[e])
        if sink not in dist:
            break
        path, x = [], sink
        while x != source:
            path.append(via[x])
            x = to[via[x] ^ 1]
        amount = min(room[e] for e in path)
        for e in path:
            room[e] -= amount
            room[e ^ 1] += amount
    flow = np.zeros((n_p, n_s), np.int64)
    e = first
    for p, own in enumerate(members):
        for s in own:
            flow[p, s] = room[e ^ 1]
            e += 2
    assert e == last
    return flow


def _sizes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for block in blocks(batches):
        n = Words(block, hashed=False).counts()
        names = ["id", "sources", "place", "print"]
        yield pa.RecordBatch.from_arrays([*(block.rows.column(c) for c in names), pa.array(n, pa.int64())], [*names, "size"])


def measure(docs: DataFrame, sources: Column, id_col: str = "doc_id", text_col: str = "text", place: Column | None = None) -> DataFrame:
    """id, sources (array of string), place, print (of the text) and size of each document.

    place: a number that tells equal rows apart, by default the row's in this scan; pass a
    stored column where the result is joined to the documents again.
    """
    rows = documents(docs, text_col, id=F.col(id_col).cast("long"), sources=sources, place=F.monotonically_increasing_id() if place is None else place).withColumn("print", F.xxhash64("body"))
    return rows.mapInArrow(_sizes, "id long, sources array<string>, place long, print long, size long")


def mix(sized: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = 1.5, most: int = 2, seed: int = 0) -> DataFrame:
    """``sized`` (see measure; a stored table) with source_size, target and copies.

    Weights repeat over the sources in code-point order. Source sizes and targets
    of a document are those of its first source. The driver holds one row for each
    membership pattern that occurs.
    """
    spark = sized.sparkSession
    patterns = sized.groupBy("sources").agg(F.sum("size").alias("size")).collect()
    names = sorted({s for r in patterns for s in r["sources"]}, key=lambda s: (s is None, (s or "").encode()))
    at = {s: k for k, s in enumerate(names)}
    patterns.sort(key=lambda r: [at[s] for s in r["sources"]])
    sizes = [sum(r["size"] for r in patterns if s in r["sources"]) for s in names]
    target = targets(sizes, [weights[k % len(weights)] for k in range(len(names))], share, most)
    capacity = [r["size"] for r in patterns]
    members = [tuple(sorted({at[s] for s in r["sources"]})) for r in patterns]
    flow = route(capacity, members, [round(t) for t in target], most)
    plan = []
    for r, c, own, f in zip(patterns, capacity, members, flow.sum(1).tolist()):
        passes = min(f // c, most) if c else 0
        plan.append((r["sources"], sizes[own[0]], target[own[0]], passes, f - passes * c))
    plan = spark.createDataFrame(plan, "sources array<string>, source_size long, target double, passes long, rest long")
    # The plan has a row for each pattern, and its size is known here.
    rows = sized.join(F.broadcast(plan) if len(patterns) <= _MOST_PATTERNS else plan, sized["sources"].eqNullSafe(plan["sources"])).drop(plan["sources"])
    rows = rows.withColumn("draw", F.xxhash64(F.lit(seed), "id", "size", "print")).withColumn("bucket", F.shiftrightunsigned("draw", 64 - _BUCKETS.bit_length() + 1).cast("int"))
    by = Window.partitionBy("sources").orderBy("bucket")
    before = F.sum("size").over(by) - F.col("size")
    filled = rows.groupBy("sources", "bucket", "rest").agg(F.sum("size").alias("size")).withColumn("before", before)
    edge = filled.where((F.col("before") <= F.col("rest")) & (F.col("before") + F.col("size") > F.col("rest"))).select(F.col("sources").alias("edge_sources"), F.col("bucket").alias("edge"), "before")
    rows = rows.join(F.broadcast(edge) if len(patterns) <= _MOST_PATTERNS else edge, rows["sources"].eqNullSafe(edge["edge_sources"]), "left").drop("edge_sources")
    # Only the bucket in which the drawing ends, one of _BUCKETS, is put in order.
    order = Window.partitionBy("sources").orderBy("draw", "id", "place")
    ends = rows.where("bucket = edge").select("place", (F.col("before") + F.sum("size").over(order)).alias("reach"))
    rows = rows.join(ends, "place", "left")
    drawn = F.col("edge").isNull() | (F.col("bucket") < F.col("edge")) | F.coalesce(F.col("reach") <= F.col("rest"), F.lit(False))
    rows = rows.withColumn("drawn", (F.col("rest") > 0) & drawn)
    rows = materialize(rows.select("id", "sources", "place", "size", "source_size", "target", "passes", "rest", "draw", "drawn"))
    for _ in range(2):
        rows = _fit(rows)
    return rows.withColumn("copies", F.col("passes") + F.col("drawn").cast("long"))


def _fit(rows: DataFrame) -> DataFrame:
    """Draw for each pattern the one document more that brings its words nearest to what is left, if any does."""
    gap = rows.groupBy("sources").agg((F.max("rest") - F.sum(F.when(F.col("drawn"), F.col("size")).otherwise(0))).alias("gap")).where("gap > 0").withColumnRenamed("sources", "gap_sources")
    open_ = rows.where("not drawn and size > 0").join(F.broadcast(gap), rows["sources"].eqNullSafe(F.col("gap_sources"))).where("size < 2 * gap")
    pick = open_.groupBy("sources").agg(F.min(F.struct(F.abs(F.col("size") - F.col("gap")).alias("off"), "draw", "id", "place")).alias("p")).select(F.col("sources").alias("pick_sources"), F.col("p.place").alias("pick"))
    rows = rows.join(F.broadcast(pick), rows["sources"].eqNullSafe(F.col("pick_sources")), "left")
    return rows.withColumn("drawn", F.col("drawn") | F.coalesce(F.col("place") == F.col("pick"), F.lit(False))).drop("pick_sources", "pick")
