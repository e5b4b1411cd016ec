"""Near-duplicate documents by min-max hashing.

Each permutation of the shingles' hashes gives two signature values, its minimum
and its maximum, so 64 permutations give 128 values. Bands of four values make
documents candidates; at a similarity of 0.75 a pair of large sets shares no band
with a probability of about 5e-6, and of 2e-5 at 6 shared of 8 shingles. Minimum and
maximum of a small set depend on each other, and 3 shared of 4 would be missed with
1e-4, so sets of at most SMALL shingles also meet by a prefix of their ordered
shingles, of which two linked sets always share one. Candidates whose signatures agree
in less than LEAST_AGREEMENT of their values are left out, which at 0.75 loses about
3e-7 of the pairs. A link counts only if the full sets confirm it.

Texts with the same set are one class from the start. In a bucket no pairs are
formed at first: every class meets the leads of its buckets. What may still link
classes of different components is looked for in blocks of bounded size: first, inside the
buckets, which classes have a mate of another component with a near enough signature;
then, for these and with their full sets, the sizes of all intersections of a block
as a product of incidence matrices. Only links that join components leave a block.
So no link between different components is lost, and no bucket becomes its pairs:
of a bucket's largest component each chunk meets the chunks of all other rows only.
Rows of a hot bucket are dealt over many tasks before they meet anything (graphs.meet).

Null and empty texts, and texts without words, have an empty set and link with
nothing. A null id has no part in the smallest id of a component. Repeated rows
are copies of one another. An empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from traincube.llm.graphs import components, meet
from traincube.llm.scratch import discard, materialize
from traincube.llm.words import Words, blocks, documents, mix, seeds

WIDTH = 5
PERMUTATIONS = 64
ROWS = 4
#: Similarity as a ratio of whole numbers.
THRESHOLD = (75, 100)
#: Pairs whose signatures agree in a smaller share of values are not confirmed: five standard deviations below the threshold.
LEAST_AGREEMENT = 0.56
#: Sets of at most this size also meet by a prefix of their ordered shingles.
SMALL = 10
#: Rows of a chunk where signatures are compared, and where full sets are.
CHUNKS = (512, 256)

_KEYS = seeds(2, 21)
_FACTORS = (seeds(PERMUTATIONS, 22) >> np.uint64(32)).astype(np.uint32) | np.uint32(1)
_MASKS = (seeds(PERMUTATIONS, 23) >> np.uint64(32)).astype(np.uint32)
_BANDS = seeds(2 * PERMUTATIONS, 24)
_N_BANDS = 2 * PERMUTATIONS // ROWS


def shingle_sets(words: Words) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each text; the whole sequence where words are fewer than WIDTH."""
    grams, _ = words.grams(WIDTH)
    edge = words.edge.tolist()
    out = []
    for a, b in zip(edge, edge[1:]):
        if b - a >= WIDTH:
            x = np.sort(grams[a : b - WIDTH + 1])
            out.append(x[np.concatenate(([True], x[1:] != x[:-1]))])
        elif b > a:
            whole = np.uint64(b - a)
            for h in words.hash[a:b]:
                whole = mix(np.array([whole]) * _KEYS[:1] + h)[0]
            out.append(np.array([whole], np.uint64))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def signatures(sets: list[np.ndarray]) -> np.ndarray:
    """[set, value] minima of all permutations, then maxima; the sets are not empty."""
    flat = np.concatenate(sets)
    flat = (flat >> np.uint64(32)).astype(np.uint32)
    at = np.cumsum([0, *(len(s) for s in sets[:-1])])
    out = np.empty((2 * PERMUTATIONS, len(sets)), np.uint32)
    value = np.empty_like(flat)
    for k in range(PERMUTATIONS):
        np.bitwise_xor(flat, _MASKS[k], out=value)
        np.multiply(value, _FACTORS[k], out=value)
        out[k] = np.minimum.reduceat(value, at)
        out[PERMUTATIONS + k] = np.maximum.reduceat(value, at)
    return out.T


def prefix(ordered: np.ndarray) -> np.ndarray:
    """The shingles of a sorted set of which any linked set has one among its own; none of sets above SMALL."""
    n = len(ordered)
    return ordered[: n + (-THRESHOLD[0] * n) // THRESHOLD[1] + 1].astype(np.int64) if n <= SMALL else np.zeros(0, np.int64)


def bands(signature: np.ndarray) -> np.ndarray:
    """[set, band] hashes; a band takes as many minima as maxima, of the same permutations."""
    half = ROWS // 2
    n = PERMUTATIONS // half
    wide = signature.astype(np.uint64) + np.uint64(1)
    low, high = wide[:, :PERMUTATIONS].reshape(-1, n, half), wide[:, PERMUTATIONS:].reshape(-1, n, half)
    c = _BANDS[:PERMUTATIONS].reshape(n, half), _BANDS[PERMUTATIONS:].reshape(n, half)
    return mix((low * c[0]).sum(2) + (high * c[1]).sum(2)).astype(np.int64)


_SKETCH = "id long, place long, print long, n_shingles long, key1 long, key2 long, bands array<long>, signature binary"


def _sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for block in blocks(batches):
        sets = shingle_sets(Words(block, lower=True))
        n = np.array([len(s) for s in sets])
        full = np.flatnonzero(n)
        keys = np.zeros((2, len(sets)), np.int64)
        band, sig = [None] * len(sets), [None] * len(sets)
        if len(full):
            own = [sets[i] for i in full.tolist()]
            at = np.cumsum([0, *(len(s) for s in own[:-1])])
            flat = np.concatenate(own)
            for k in range(2):
                keys[k, full] = np.add.reduceat(mix(flat ^ _KEYS[k]), at).astype(np.int64)
            signed = signatures(own)
            low = (signed * np.uint32(2654435761) >> np.uint32(24)).astype(np.uint8)
            for i, b, s in zip(full.tolist(), bands(signed), low):
                band[i], sig[i] = np.concatenate((b, prefix(sets[i]))), s.tobytes()
        yield pa.RecordBatch.from_arrays(
            [block.rows.column("id"), block.rows.column("place"), block.rows.column("print"), pa.array(n, pa.int64()), pa.array(keys[0]), pa.array(keys[1]), pa.array(band, pa.list_(pa.int64())), pa.array(sig, pa.binary())],
            ["id", "place", "print", "n_shingles", "key1", "key2", "bands", "signature"],
        )


def _rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """id, place in this scan, fingerprint of the text, and the text."""
    return documents(docs, text_col, id=F.col(id_col).cast("long"), place=F.monotonically_increasing_id()).withColumn("print", F.xxhash64("body"))


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for block in blocks(batches):
        sets = [s.tobytes() for s in shingle_sets(Words(block, lower=True))]
        yield pa.RecordBatch.from_arrays([block.rows.column("node"), pa.array(sets, pa.binary())], ["node", "shingles"])


def _agree(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Pairs whose signatures allow the threshold."""
    for x in batches:
        if not x.num_rows:
            continue
        a, b = (np.frombuffer(b"".join(x.column(c).to_pylist()), np.uint8).reshape(x.num_rows, -1) for c in ("signature_a", "signature_b"))
        near = (a == b).mean(1) >= LEAST_AGREEMENT
        yield pa.RecordBatch.from_arrays([x.column(c).filter(pa.array(near)) for c in ("a", "b")], ["a", "b"])


def _with_mates(own: dict[str, np.ndarray]) -> np.ndarray:
    """Nodes of a block that have a near enough signature in another component."""
    sig, label, node = own["signature"], own["label"], own["node"]
    _, at, n_of = np.unique(label, return_inverse=True, return_counts=True)
    order = np.argsort(n_of[at], kind="stable")
    found, done, most = np.zeros(len(label), bool), np.zeros(len(label), bool), label[order[-1]]
    for i in order.tolist():
        if label[i] == most:  # rows of the largest component meet all others as these are gone through
            continue
        done[i] = True
        at = np.flatnonzero(~done & (label != label[i]))
        at = at[(sig[at] == sig[i]).mean(1) >= LEAST_AGREEMENT]
        found[at] = True
        found[i] |= len(at) > 0
    return np.unique(node[found])


def _joining(own: dict[str, np.ndarray], sets: list[np.ndarray]) -> list[tuple[int, int]]:
    """Links of a block, as few as join the components that it can."""
    label, node, side = own["label"], own["node"], own["side"]
    size = np.array([len(x) for x in sets])
    two = side.min() != side.max()
    rows, cols = (np.flatnonzero(side == side.min()), np.flatnonzero(side == side.max())) if two else (np.arange(len(node)),) * 2
    _, word, times = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    owner = np.repeat(np.arange(len(sets)), size)
    common = times[word] > 1
    column = (np.cumsum(times > 1) - 1)[word[common]]
    owner = owner[common]
    order = np.argsort(column, kind="stable")
    column, owner = column[order], owner[order]
    both = np.zeros((len(rows), len(cols)), np.float32)
    width = 8192
    for first in range(0, int(column[-1]) + 1 if len(column) else 0, width):
        i, j = np.searchsorted(column, (first, first + width))
        held = np.zeros((len(sets), width), np.float32)
        held[owner[i:j], column[i:j] - first] = 1
        both += held[rows] @ held[cols].T
    near = THRESHOLD[1] * both >= THRESHOLD[0] * (size[rows][:, None] + size[cols][None, :] - both)
    a, b = np.nonzero(near & (label[rows][:, None] != label[cols][None, :]))
    a, b = rows[a], cols[b]
    low, high = np.minimum(label[a], label[b]), np.maximum(label[a], label[b])
    _, at = np.unique(np.stack((low, high)), axis=1, return_index=True)
    root: dict[int, int] = {}

    def find(x: int) -> int:
        while root.get(x, x) != x:
            x = root[x]
        return x

    out = []
    for k in at.tolist():
        x, y = find(int(low[k])), find(int(high[k]))
        if x != y:
            root[max(x, y)] = min(x, y)
            out.append((int(node[a[k]]), int(node[b[k]])))
    return out


def _in_blocks(exact: bool):
    """Rows sorted by (bucket, part): to the links of each block (exact), or to its nodes with mates."""

    def emit(parts: list[pa.RecordBatch]) -> pa.RecordBatch:
        table = pa.Table.from_batches(parts)
        own = {c: table.column(c).to_numpy() for c in ("node", "label", "side")}
        if exact:
            several = len(table) > 1 and own["label"].min() != own["label"].max()
            links = _joining(own, [np.frombuffer(x, np.uint64) for x in table.column("shingles").to_pylist()]) if several else []
            return pa.RecordBatch.from_arrays([pa.array([x[k] for x in links], pa.int64()) for k in (0, 1)], ["a", "b"])
        own["signature"] = np.frombuffer(b"".join(table.column("signature").to_pylist()), np.uint8).reshape(table.num_rows, -1)
        return pa.RecordBatch.from_arrays([pa.array(_with_mates(own))], ["node"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, parts = None, []
        for x in batches:
            bucket, part = x.column("bucket").to_numpy(), x.column("part").to_numpy()
            cuts = [0, *(np.flatnonzero((np.diff(bucket) != 0) | (np.diff(part) != 0)) + 1).tolist(), x.num_rows]
            for i, j in zip(cuts, cuts[1:]):
                if j > i:
                    if (bucket[i], part[i]) != key and parts:
                        yield emit(parts)
                        parts = []
                    key = (bucket[i], part[i])
                    parts.append(x.slice(i, j - i))
        if parts:
            yield emit(parts)

    return run


def _blocks_of(rows: DataFrame, chunk: int) -> DataFrame:
    """Rows (bucket, node, label, ...; a stored table) of each bucket dealt into blocks of about two chunks, so that any two rows of a bucket with different labels meet in one block.

    The rows of the bucket's most frequent label need not meet one another, so their
    chunks, numbered from ``others`` on, only meet those of all other rows. A bucket of
    one label needs no block, and one of at most ``chunk`` rows is a block.
    """
    labels = rows.groupBy("bucket", "label").agg(F.count("*").alias("n"))
    size = labels.groupBy("bucket").agg(F.max_by("label", F.struct("n", "label")).alias("main"), F.max("n").alias("most"), F.sum("n").alias("n")).where("most < n")
    one = F.col("n") <= chunk
    size = size.select("bucket", "main", "n", F.when(one, 1).otherwise(F.ceil((F.col("n") - F.col("most")) / chunk)).cast("int").alias("others"), F.when(one, 0).otherwise(F.ceil(F.col("most") / chunk)).cast("int").alias("mains"))
    met = meet(rows, size, "bucket", "node", rows.count())
    main, all_ = (F.col("label") == F.col("main")) & (F.col("mains") > 0), F.col("others") + F.col("mains")
    met = met.withColumn("side", F.when(main, F.col("others") + F.pmod(F.xxhash64("node"), F.col("mains"))).otherwise(F.pmod(F.xxhash64("node"), F.col("others"))).cast("int"))
    met = met.withColumn("other", F.explode(F.sequence(F.lit(0), F.when(main, F.col("others")).otherwise(all_) - 1)))
    part = F.least("side", "other").cast("long") * all_ + F.greatest("side", "other")
    return met.withColumn("part", part).drop("other", "others", "mains", "main").repartition("bucket", "part").sortWithinPartitions("bucket", "part")


def _confirm(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Pairs whose full sets reach the threshold."""
    for x in batches:
        keep = []
        for s, t in zip(x.column("set_a"), x.column("set_b")):
            a, b = (np.frombuffer(v.as_buffer(), np.uint64) for v in (s, t))
            both = len(np.intersect1d(a, b, assume_unique=True))
            keep.append(THRESHOLD[1] * both >= THRESHOLD[0] * (len(a) + len(b) - both))
        yield pa.RecordBatch.from_arrays([x.column(c).filter(pa.array(keep, pa.bool_())) for c in ("a", "b")], ["a", "b"])


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, print, n_shingles, component_id and ``first``, true for the row that stands for its component.

    ``print`` is a fingerprint of the text. The row that stands for a component has its
    smallest id and, among rows of that id, the smallest fingerprint; rows equal in both
    are told apart by place, so that one of them is first, whichever.
    """
    sketch = materialize(_rows(docs, id_col, text_col).mapInArrow(_sketch, _SKETCH))
    full = sketch.where("n_shingles > 0")
    first = F.min(F.struct(F.col("id").isNull().alias("none"), "id", "print", "place")).alias("first")
    classes = materialize(full.groupBy("key1", "key2").agg(first, F.first("bands").alias("bands"), F.first("signature").alias("signature")).withColumn("node", F.col("first.place")))
    # What stands after the bands are shingles of a prefix, which are all of one kind.
    banded = classes.select("node", F.posexplode("bands").alias("band", "value"))
    buckets = materialize(banded.select("node", F.xxhash64(F.least("band", F.lit(_N_BANDS)), "value").alias("bucket")))
    signed = classes.select("node", "signature")

    def sets_of(nodes: DataFrame) -> DataFrame:
        """Full sets of the classes given; candidates are few beside the texts, which are read again instead of storing every set.

        Rows are known again by id and fingerprint, not by place, which another scan may number otherwise.
        """
        wanted = classes.select("node", F.col("first.id").alias("own_id"), F.col("first.print").alias("own_print")).join(nodes, "node")
        texts = _rows(docs, id_col, text_col).select("id", "print", "body").join(wanted, F.col("id").eqNullSafe(F.col("own_id")) & (F.col("print") == F.col("own_print")))
        return materialize(texts.select("node", "body").mapInArrow(_sets, "node long, shingles binary").dropDuplicates(["node"]))

    def confirmed(pairs: DataFrame) -> DataFrame:
        """Links among the candidate pairs (a, b), as a stored table."""
        side = lambda c: signed.select(F.col("node").alias(c), F.col("signature").alias(f"signature_{c}"))
        pairs = materialize(pairs.join(side("a"), "a").join(side("b"), "b").mapInArrow(_agree, "a long, b long"))
        sets = sets_of(pairs.select(F.col("a").alias("node")).union(pairs.select("b")).distinct())
        side = lambda c: sets.select(F.col("node").alias(c), F.col("shingles").alias(f"set_{c}"))
        out = materialize(pairs.join(side("a"), "a").join(side("b"), "b").mapInArrow(_confirm, "a long, b long"))
        discard(pairs)
        discard(sets)
        return out

    def label_of(joined: DataFrame, rows: DataFrame, node: str, label: str) -> DataFrame:
        return rows.join(joined.select(F.col("a").alias(node), F.col("b").alias(label)).hint("merge"), node, "left").withColumn(label, F.coalesce(label, node))

    lead = buckets.groupBy("bucket").agg(F.min("node").alias("b"), F.max("node").alias("most"), F.count("*").alias("n")).where("b < most").drop("most")
    star = meet(buckets.withColumnRenamed("node", "a"), lead, "bucket", "a", buckets.count()).where("a <> b").select("a", "b").distinct()
    links = confirmed(star)
    joined = components(links)

    rest = materialize(label_of(joined, buckets, "node", "label"))
    discard(buckets)
    split = rest.groupBy("bucket").agg(F.min("label").alias("low"), F.max("label").alias("high"), F.count("*").alias("n")).where("low < high").select("bucket", "n")
    open_ = materialize(meet(rest, split, "bucket", "node", rest.count()).join(signed, "node").select("bucket", "node", "label", "signature"))
    discard(rest)
    near = materialize(_blocks_of(open_, CHUNKS[0]).mapInArrow(_in_blocks(False), "node long").distinct())
    # Classes that may link have a bucket in common, so they are in one group of classes joined by buckets.
    met = materialize(open_.join(near, "node").select("bucket", "node"))
    low = met.groupBy("bucket").agg(F.min("node").alias("b"), F.count("*").alias("n"))
    groups = components(meet(met, low, "bucket", "node", met.count()).select(F.col("node").alias("a"), "b").where("a <> b"))
    members = label_of(groups, label_of(joined, near, "node", "label"), "node", "bucket")
    sets = sets_of(near)
    members = materialize(sets.join(members, "node"))
    across = _blocks_of(members, CHUNKS[1]).mapInArrow(_in_blocks(True), "a long, b long")
    whole = components(joined.union(across))
    for x in (links, open_, near, met, groups, sets, members, joined):
        discard(x)

    member = whole.select(F.col("a").alias("node"), F.col("b").alias("component"))
    nodes = classes.select("key1", "key2", "node", "first").join(member, "node", "left").withColumn("component", F.coalesce("component", "node"))
    smallest = nodes.groupBy("component").agg(F.min("first").alias("first"))
    nodes = nodes.select("key1", "key2", "component").join(smallest, "component")
    rows = sketch.drop("bands", "signature").join(nodes, ["key1", "key2"], "left")
    alone = F.col("n_shingles") == 0
    return rows.select(
        "id", "print", "n_shingles",
        F.when(alone, F.col("id")).otherwise(F.col("first.id")).alias("component_id"),
        (alone | (F.col("place") == F.col("first.place"))).alias("first"),
    )
