"""Passages that repeat across documents, by seeds and extension.

Winnowing picks anchors, hashes of five words, such that every window of 13 words
holds one that depends on the window's words alone. An anchor that only one
document has seeds nothing. Around the others a match is extended both ways over
the windows that chose the anchor: the hash of each such window meets the equal
ones of all documents, and the smallest document id keeps the passage. Windows
found to repeat are joined into maximal repeats, and their words go.

Anchors and windows travel as packed arrays, one row for a bucket of hashes and a
few megabytes of text. What repeats within those megabytes is settled there, so a
passage in a third of all documents sends one entry from each such piece.

A row is known by a hash of its id and text, never by its position in a scan, as
every scan may number rows otherwise. Rows equal in both get the same answers, and
each of them is a row of the result.

Null and empty texts have no words. A null id counts as larger than any other.
Rows with equal ids do not remove each other's words. Empty tables give an empty
result. Other columns are not read, whatever their names.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from traincube.llm.words import Words, blocks, documents

LENGTH = 13
SEED = 5
#: Bits of an anchor that travel. Windows are compared by 96 bits, so equal anchors of different words only cost work.
_ANCHOR = np.uint64((1 << 48) - 1)
_NO_ID = np.iinfo(np.int64).max
_PIECE = 16 << 20

_PACKED = "bucket long, settled boolean, hashes binary, more binary, docs binary, places binary, ids binary"


def _sliding(x: np.ndarray, width: int, least: bool) -> np.ndarray:
    """Minimum or maximum of every ``width`` neighbours, by doubling."""
    f = np.minimum if least else np.maximum
    have, out = 1, x
    while have * 2 <= width:
        out = f(out[:-have], out[have:])
        have *= 2
    rest = width - have
    return f(out[: len(out) - rest], out[rest:]) if rest else out


def anchors(words: Words, length: int, seed: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of seeds by word, of the anchor chosen by the window from each word on (0: no window), and which words begin an anchor."""
    wide = length - seed + 1
    grams, _ = words.grams(seed)
    n = max(0, len(words.hash) - length + 1)
    if not n:
        return grams, np.zeros(0, np.uint64), np.zeros(len(grams), bool)
    last = np.repeat(words.edge[1:], words.counts())[:n]
    chosen = np.where(np.arange(n) + length <= last, _sliding(grams, wide, True), np.uint64(0))
    padded = np.concatenate((np.zeros(wide - 1, np.uint64), chosen, np.zeros(wide - 1, np.uint64)))
    return grams, chosen, (grams == _sliding(padded, wide, False)) & (grams > 0)


def _planes(x: np.ndarray) -> bytes:
    """Numbers byte by byte, all first bytes and so on: bytes that are all zero, or sorted, then take next to nothing on the way."""
    return x.view(np.uint8).reshape(-1, x.itemsize).T.tobytes()


def _from_planes(raw: bytes, kind) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8).reshape(np.dtype(kind).itemsize, -1).T).view(kind).ravel()


class _Pack:
    """Entries (hash, more of the hash, document) of a few megabytes of text, sent out by bucket."""

    def __init__(self, buckets: int, settle: Callable, with_ids: bool):
        self.buckets, self.settle, self.with_ids = buckets, settle, with_ids
        self.clear()

    def clear(self):
        self.parts: list[tuple] = []
        self.places: list[np.ndarray] = []
        self.ids: list[np.ndarray] = []
        self.docs = self.bytes = 0

    def add(self, block, hashes: np.ndarray, more: np.ndarray, doc: np.ndarray):
        self.parts.append((hashes, more, (doc + self.docs).astype(np.uint32)))
        self.places.append(block.column("place"))
        self.ids.append(block.column("id"))
        self.docs += len(block)
        self.bytes += len(block.data)

    def rows(self) -> Iterator[pa.RecordBatch]:
        if self.parts:
            hashes, more, doc = (np.concatenate(x) for x in zip(*self.parts))
            places, ids = np.concatenate(self.places), np.concatenate(self.ids)
            order = np.lexsort((doc, more, hashes))
            hashes, more, doc = hashes[order], more[order], doc[order]
            fresh = np.ones(len(hashes), bool)
            fresh[1:] = (hashes[1:] != hashes[:-1]) | (more[1:] != more[:-1]) | (doc[1:] != doc[:-1])
            hashes, more, doc = hashes[fresh], more[fresh], doc[fresh]
            found, ask = self.settle(hashes, more, ids[doc], places[doc])
            # What is settled goes on to its document by place, not to the bucket of its hash.
            for settled, keep, key in ((False, ask, hashes % np.uint64(self.buckets)), (True, found, places[doc].astype(np.uint64) % np.uint64(self.buckets))):
                at = np.flatnonzero(keep)
                at = at[np.argsort(key[at], kind="stable")]
                cuts = np.flatnonzero(np.diff(key[at])) + 1
                for part in np.split(at, cuts):
                    if len(part):
                        own, local = np.unique(doc[part], return_inverse=True)
                        narrow = np.uint16 if len(own) <= 1 << 16 else np.uint32
                        known = ids[own].tobytes() if self.with_ids and not settled else b""
                        row = [int(key[part[0]]), settled, _planes(hashes[part]), _planes(more[part]), local.astype(narrow).tobytes(), places[own].tobytes(), known]
                        yield pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip(row, (pa.int64(), pa.bool_(), *[pa.binary()] * 5))], [c.split()[0] for c in _PACKED.split(", ")])
        self.clear()


def _groups(hashes: np.ndarray, more: np.ndarray) -> np.ndarray:
    """Where runs of equal hashes begin."""
    new = np.ones(len(hashes), bool)
    new[1:] = (hashes[1:] != hashes[:-1]) | (more[1:] != more[:-1])
    return np.flatnonzero(new)


def _shared(hashes, more, ids, places):
    """For anchors: those of two documents or more are found; one entry of each hash asks further."""
    at = _groups(hashes, more)
    size = np.diff(np.append(at, len(hashes)))
    ask = np.zeros(len(hashes), bool)
    ask[at] = True
    return np.repeat(size > 1, size), ask


def _later(hashes, more, ids, places):
    """For windows: those that a smaller id has too are found; those of the smallest id ask further."""
    at = _groups(hashes, more)
    size = np.diff(np.append(at, len(hashes)))
    first = np.repeat(np.minimum.reduceat(ids, at), size) if len(at) else ids
    return ids > first, ids == first


def _meet(settle: Callable):
    """Entries of each bucket together; what is found goes back as (place, hashes)."""

    def answer(parts: list[dict], settled: list[dict]) -> Iterator[pa.RecordBatch]:
        hashes, places = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)]
        for groups, ask in ((parts, True), (settled, False)):
            if not groups:
                continue
            h, m = (np.concatenate([_from_planes(x[c], t) for x in groups]) for c, t in (("hashes", np.uint64), ("more", np.uint32)))
            local = [np.frombuffer(x["docs"], np.uint16 if 4 * len(x["docs"]) == len(x["hashes"]) else np.uint32) for x in groups]
            place = np.concatenate([np.frombuffer(x["places"], np.int64)[d] for x, d in zip(groups, local)])
            ids = np.concatenate([np.frombuffer(x["ids"], np.int64)[d] for x, d in zip(groups, local) if x["ids"]] or [place])
            if ask:
                order = np.lexsort((place, m, h))
                h, m, place, ids = h[order], m[order], place[order], ids[order]
                found, _ = settle(h, m, ids, place)
                h, place = h[found], place[found]
            hashes.append(h)
            places.append(place)
        h, place = np.concatenate(hashes), np.concatenate(places)
        order = np.lexsort((h, place))
        h, place = h[order], place[order]
        fresh = np.ones(len(h), bool)
        fresh[1:] = (h[1:] != h[:-1]) | (place[1:] != place[:-1])
        h, place = h[fresh], place[fresh]
        own, at = np.unique(place, return_index=True)
        if len(own):
            yield pa.RecordBatch.from_arrays([pa.array(own), pa.array([x.tobytes() for x in np.split(h, at[1:])], pa.binary())], ["place", "hashes"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bucket, parts, settled = None, [], []
        for batch in batches:
            for row in batch.to_pylist():
                if row["bucket"] != bucket:
                    yield from answer(parts, settled)
                    bucket, parts, settled = row["bucket"], [], []
                (settled if row["settled"] else parts).append(row)
        yield from answer(parts, settled)

    return run


def _hits(packed: DataFrame, settle: Callable) -> DataFrame:
    met = packed.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(_meet(settle), "place long, hashes binary")
    return met.groupBy("place").agg(F.collect_list("hashes").alias("hits"))


def _hit_set(block) -> np.ndarray:
    raw = block.rows.column("hits")
    return np.unique(np.frombuffer(b"".join(h for x in raw.to_pylist() if x for h in x), np.uint64))


def _among(x: np.ndarray, found: np.ndarray) -> np.ndarray:
    """Membership in a sorted array."""
    if not len(found):
        return np.zeros(len(x), bool)
    return found[np.minimum(np.searchsorted(found, x), len(found) - 1)] == x


def _buckets(docs: DataFrame) -> int:
    """A bucket is put in order in memory, so their number follows the size of the files read: one for each 256 MB at least.

    Answers are a row for each bucket and text, so small inputs get no fewer than 256.
    """
    leaves = docs._jdf.queryExecution().optimizedPlan().collectLeaves()
    sizes = [int(str(leaves.apply(k).stats().sizeInBytes())) for k in range(leaves.size())]
    # A leaf of unknown size counts as endless in Spark, and for nothing here.
    files = sum(x for x in sizes if x < 1 << 55)
    return max(256, 4 * int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), files >> 28)


def repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = LENGTH, seed: int = SEED) -> DataFrame:
    """id, place (of the row's id and text), n_words, n_removed, repeats (maximal, in words, end exclusive) and kept, the words left, joined by a space.

    A word goes if a window of ``length`` words over it also stands in a document
    of smaller id; windows are judged on the input.
    """
    buckets = _buckets(docs)
    rows = documents(docs, text_col, id=F.coalesce(F.col(id_col).cast("long"), F.lit(int(_NO_ID)))).select("id", F.xxhash64("id", "body").alias("place"), "body")

    def seeds_of(batches):
        pack = _Pack(buckets, _shared, False)
        for block in blocks(batches):
            words = Words(block)
            grams, _, begins = anchors(words, length, seed)
            at = np.flatnonzero(begins)
            pack.add(block, grams[at] & _ANCHOR, np.zeros(len(at), np.uint32), np.searchsorted(words.edge, at, "right") - 1)
            if pack.bytes >= _PIECE:
                yield from pack.rows()
        yield from pack.rows()

    def windows_of(batches):
        pack = _Pack(buckets, _later, True)
        for block in blocks(batches):
            words = Words(block)
            _, chosen, _ = anchors(words, length, seed)
            at = np.flatnonzero((chosen > 0) & _among(chosen & _ANCHOR, _hit_set(block)))
            h = words.grams(length)[0][at]
            m = (words.grams(length, 1)[0][at] >> np.uint64(32)).astype(np.uint32)
            pack.add(block, h, m, np.searchsorted(words.edge, at, "right") - 1)
            if pack.bytes >= _PIECE:
                yield from pack.rows()
        yield from pack.rows()

    span = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))

    def cut(batches):
        for block in blocks(batches):
            hits = block.rows.column("hits").to_pylist()
            words = Words(block) if any(hits) else None
            if words is not None:
                grams, _ = words.grams(length)
                edge = words.edge.tolist()
            n, gone, spans, kept = [], [], [], []
            for d, body in enumerate(block.bodies()):
                own = body.split()
                n.append(len(own))
                runs = []
                if hits[d] and len(own) >= length:
                    found = np.unique(np.frombuffer(b"".join(hits[d]), np.uint64))
                    at = np.flatnonzero(_among(grams[edge[d] : edge[d] + len(own) - length + 1], found))
                    if len(at):
                        new = np.flatnonzero(np.diff(at) > length)
                        runs = list(zip(at[np.concatenate(([0], new + 1))].tolist(), (at[np.append(new, len(at) - 1)] + length).tolist()))
                for a, b in reversed(runs):
                    del own[a:b]
                gone.append(sum(b - a for a, b in runs))
                spans.append([{"start": a, "end": b} for a, b in runs])
                kept.append(b" ".join(own))
            yield pa.RecordBatch.from_arrays([block.rows.column("id"), block.rows.column("place"), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(spans, span), pa.array(kept, pa.binary())], ["id", "place", "n_words", "n_removed", "repeats", "kept"])

    # The exchange of the texts by place is the same in both joins, and Spark runs it once.
    seeded = rows.join(_hits(rows.mapInArrow(seeds_of, _PACKED), _shared), "place")
    found = _hits(seeded.mapInArrow(windows_of, _PACKED), _later)
    out = rows.join(found, "place", "left").mapInArrow(cut, "id long, place long, n_words long, n_removed long, repeats array<struct<start: long, end: long>>, kept binary")
    return out.withColumn("id", F.when(F.col("id") != F.lit(int(_NO_ID)), F.col("id"))).withColumn("kept", F.decode("kept", "UTF-8"))
