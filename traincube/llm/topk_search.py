"""Exact top-k by inner product, term at a time.

Vectors are rows of integer weights. For a block of candidates each dimension is a
posting list of the candidates with a weight there; a query scatters its weight
times the postings into a dense score array, dimension by dimension. Of each array
the k best are selected by partition, and those of all blocks are merged.

Candidates are dealt over partitions of bounded size. Each task holds its candidates
as integers and streams past them the blocks of queries, which go to every partition:
the stated query set against all rows, in blocks. Only the k best of each query leave
a task, and these are merged.

A vector that is null, or holds a null or non-finite component, takes no part; nor does
one with a null id. Vectors may differ in length; missing dimensions weigh nothing. A
row is never a candidate of itself; another row that repeats its id is, and if both are
queries each has its own k rows. Ties go to the smaller id. Fewer candidates than k give
fewer rows. An empty table gives an empty result, and other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from traincube.llm.scratch import materialize

QUERY_BLOCK = 256
CANDIDATE_BLOCK = 4096
#: Candidates of a partition, which a task holds.
MOST_CANDIDATES = 1 << 18


def weights(vectors: DataFrame, id_col: str, vector_col: str, scale: float = 256.0) -> DataFrame:
    """id, query and w, floor(scale * component), of the rows that take part; vectors: with ``_query``."""
    x = F.transform(F.col(vector_col), lambda v: v.cast("double"))
    fine = F.forall(x, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf")))
    return vectors.where(F.col(id_col).isNotNull() & F.col(vector_col).isNotNull()).where(fine).select(
        F.col(id_col).cast("long").alias("id"), F.col("_query").alias("query"), F.transform(x, lambda v: F.floor(v * F.lit(scale))).alias("w"))


_BLOCK = "ids binary, places binary, terms binary"


def _dense(part: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """ids, places and [dimension, row] weights of rows, by id."""
    part = part.take(pa.array(np.lexsort((part.column("place").to_numpy(), part.column("id").to_numpy()))))
    w = part.column("w")
    offsets = w.offsets.to_numpy()
    n = np.diff(offsets)
    flat = w.values.to_numpy(zero_copy_only=False)[offsets[0] : offsets[-1]].astype(np.int64)
    dense = np.zeros((len(n), int(n.max(initial=0))), np.int64)
    dense[np.repeat(np.arange(len(n)), n), np.arange(len(flat)) - np.repeat(offsets[:-1] - offsets[0], n)] = flat
    return part.column("id").to_numpy(), part.column("place").to_numpy(), np.ascontiguousarray(dense.T)


def _pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows of queries into blocks."""
    for batch in batches:
        for at in range(0, batch.num_rows, QUERY_BLOCK):
            yield pa.RecordBatch.from_arrays([pa.array([x.tobytes()]) for x in _dense(batch.slice(at, QUERY_BLOCK))], ["ids", "places", "terms"])


def accumulate(queries: np.ndarray, candidates: np.ndarray) -> np.ndarray:
    """Scores [query, candidate] from [dimension, row] weights, one dimension after the other."""
    dims = min(len(queries), len(candidates))
    most = int(np.abs(queries).max(initial=0)) * int(np.abs(candidates).max(initial=0)) * max(1, dims)
    kind = np.int32 if most < 2**31 else np.int64
    scores = np.zeros((queries.shape[1], candidates.shape[1]), kind)
    for q, c in zip(queries[:dims].astype(kind), candidates[:dims].astype(kind)):
        post = np.flatnonzero(c)
        rows = np.flatnonzero(q)
        if len(post) == len(c):
            scores[rows] += q[rows, None] * c
        elif len(post) and len(rows):
            scores[np.ix_(rows, post)] += q[rows, None] * c[post]
    return scores


def best(scores: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Places of the k highest scores, ties to smaller ids; ids ascend."""
    if len(scores) <= k:
        return np.arange(len(scores))
    least = np.partition(scores, len(scores) - k)[len(scores) - k]
    # Of those equal to the k-th the smallest ids, which stand first.
    over = np.flatnonzero(scores > least)
    return np.concatenate((over, np.flatnonzero(scores == least)[: k - len(over)]))


def _search(k: int):
    """Rows of a partition, candidates before blocks of queries: to the k best candidates of each query here."""

    def answer(query: dict, held: list[tuple]) -> pa.RecordBatch:
        q_ids, q_places = (np.frombuffer(query[c], np.int64) for c in ("ids", "places"))
        q = np.frombuffer(query["terms"], np.int64).reshape(-1, len(q_ids))
        found: list[list] = [[] for _ in q_ids]
        for c_ids, c_places, c in held:
            for i, (place, s) in enumerate(zip(q_places, accumulate(q, c))):
                pick = best(s, c_ids, k + 1)
                pick = pick[c_places[pick] != place]
                found[i].append((c_ids[pick], s[pick].astype(np.int64)))
        out = []
        for i, parts in enumerate(found):
            ids, s = (np.concatenate(x) for x in zip(*parts))
            order = np.lexsort((ids, -s))[:k]
            out.append((np.full(len(order), q_ids[i]), np.full(len(order), q_places[i]), ids[order], s[order]))
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*out)], ["query_id", "place", "vec_id", "score"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        for batch in batches:
            n = int(np.searchsorted(batch.column("query").to_numpy(zero_copy_only=False), True))
            held += [_dense(batch.slice(at, min(CANDIDATE_BLOCK, n - at))) for at in range(0, n, CANDIDATE_BLOCK)]
            if held:
                for row in batch.slice(n).select(["ids", "places", "terms"]).to_pylist():
                    yield answer(row, held)

    return run


def top_k(vectors: DataFrame, is_query: Column, k: int = 5, id_col: str = "vec_id", vector_col: str = "embedding", scale: float = 256.0) -> DataFrame:
    """query_id, rank, vec_id and score of each query's k best candidates among all rows."""
    marked = vectors.withColumn("_query", F.coalesce(is_query, F.lit(False)))
    # Stored, so that a row has the same place as a query and as a candidate.
    rows = materialize(weights(marked, id_col, vector_col, scale).withColumn("place", F.monotonically_increasing_id()))
    n = rows.count()
    slots = max(int(vectors.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-n // MOST_CANDIDATES))
    none = [F.lit(None).cast("binary").alias(c) for c in ("ids", "places", "terms")]
    # Partitions are asked for by number, so that no hash leaves one empty or fills another twice.
    candidates = rows.select(F.lit(False).alias("query"), F.pmod(F.xxhash64("place"), F.lit(slots)).cast("int").alias("slot"), "id", "place", "w", *none)
    queries = rows.where("query").select("id", "place", "w").mapInArrow(_pack, _BLOCK)
    queries = queries.select(F.lit(True).alias("query"), F.explode(F.sequence(F.lit(0), F.lit(slots - 1))).alias("slot"), *(F.lit(None).cast(f.dataType).alias(f.name) for f in candidates.schema if f.name in ("id", "place", "w")), "ids", "places", "terms")
    dealt = candidates.union(queries).repartitionById(slots, F.col("slot")).sortWithinPartitions("query")
    found = dealt.drop("slot").mapInArrow(_search(k), "query_id long, place long, vec_id long, score long")
    ranked = Window.partitionBy("place").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(ranked)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
