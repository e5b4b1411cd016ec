"""Language-model scoring with class-based bigrams.

The most frequent words of the training texts are put into classes by exchange
clustering (the assignment that the class bigram likelihood asks for) until no
word moves; then every further training word joins the class that the likelihood
gains most from, by the summed classes of all its neighbours. Only words that no
training text has are classed by shape. A text's probability is the product over
its tokens of a class transition and a word emission, both smoothed. Every count
covers all training texts: word counts and neighbours are summed by key, and
bigrams of the clustered words, shapes and ends are summed before they reach the
driver, whose share is bounded by ``clustered`` squared.

Words are known by a 64-bit hash. Null and empty texts are a single end token.
Rows with null ids take part in training unless ``held_out`` says otherwise.
Repeated rows count each. An empty table gives an empty result; without training
texts every token is unknown.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from traincube.llm.scratch import materialize
from traincube.llm.words import Block, Words, blocks, documents

#: The end token's place among words; no word hashes are near it by design, only by chance.
END = np.int64(np.iinfo(np.int64).min)
SHAPES = 4
#: In place of the class of a word that is not yet looked up.
UNKNOWN = 255
BLOCK_TAGS = 1 << 18

_FULL_STOP = np.zeros(256, bool)
_FULL_STOP[[ord(c) for c in ".!?"]] = True
_COMMA = np.zeros(256, bool)
_COMMA[[ord(c) for c in ",;:"]] = True
_LETTER = np.zeros(256, bool)
_LETTER[ord("a") : ord("z") + 1] = _LETTER[ord("A") : ord("Z") + 1] = True
_LETTER[128:] = True


class Tokens:
    """The lower-cased words of a block as signed hashes with their shapes, an end after each text."""

    def __init__(self, block: Block):
        words = Words(block, lower=True)
        n, last = words.counts(), block.data[words.end - 1]
        shape = np.where(_FULL_STOP[last], 1, np.where(_COMMA[last], 2, np.where(_LETTER[last], 0, 3)))
        self.edge = np.concatenate(([0], np.cumsum(n + 1)))
        at = np.ones(self.edge[-1], bool)
        at[self.edge[1:] - 1] = False
        self.key = np.full(self.edge[-1], END)
        self.key[at] = words.hash.astype(np.int64)
        self.shape = np.full(self.edge[-1], SHAPES)
        self.shape[at] = shape


def lookup(keys: np.ndarray, known: np.ndarray) -> np.ndarray:
    """Place of each key in the sorted array, or -1."""
    if not len(known):
        return np.full(len(keys), -1)
    at = np.minimum(np.searchsorted(known, keys), len(known) - 1)
    return np.where(known[at] == keys, at, -1)


_COUNTS = "word long, shape int, n long"


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Word counts of a task's texts, summed as far as memory holds them."""
    held: list[tuple] = []
    rows = 0

    def emit():
        key, shape, n = (np.concatenate(x) for x in zip(*held))
        own, at, back = np.unique(key, return_index=True, return_inverse=True)
        total = np.zeros(len(own), np.int64)
        np.add.at(total, back, n)
        return pa.RecordBatch.from_arrays([pa.array(own), pa.array(shape[at].astype(np.int32)), pa.array(total)], ["word", "shape", "n"])

    for block in blocks(batches):
        tokens = Tokens(block)
        own, at, n = np.unique(tokens.key, return_index=True, return_counts=True)
        held.append((own, tokens.shape[at], n))
        rows += len(own)
        if rows > 800_000:
            yield emit()
            held, rows = [], 0
    if held:
        yield emit()


def word_counts(texts: DataFrame) -> DataFrame:
    """Count and shape of each word, and of the end, in texts (see documents())."""
    return texts.mapInArrow(_count, _COUNTS).groupBy("word").agg(F.first("shape").alias("shape"), F.sum("n").alias("n"))


def bigrams(texts: DataFrame, words: np.ndarray) -> DataFrame:
    """Counts of neighbours among the sorted words given and, for all else, shapes; code = before * size + after."""
    n_words = len(words)
    size = n_words + SHAPES + 1

    def run(batches):
        total = np.zeros(0, np.int64)
        seen = np.zeros(0, np.int64)

        def merge(codes, counts):
            own, back = np.unique(codes, return_inverse=True)
            out = np.zeros(len(own), np.int64)
            np.add.at(out, back, counts)
            return own, out

        for block in blocks(batches):
            tokens = Tokens(block)
            at = lookup(tokens.key, words)
            at = np.where(at < 0, n_words + tokens.shape, at)
            before = np.concatenate(([n_words + SHAPES], at[:-1]))
            codes, counts = np.unique(before * size + at, return_counts=True)
            seen, total = merge(np.concatenate((seen, codes)), np.concatenate((total, counts)))
        yield pa.RecordBatch.from_arrays([pa.array(seen), pa.array(total)], ["code", "n"])

    return texts.mapInArrow(run, "code long, n long").groupBy("code").agg(F.sum("n").alias("n"))


def _xlogx(x: np.ndarray) -> np.ndarray:
    return x * np.log(np.maximum(x, 1))


def exchange(before: np.ndarray, after: np.ndarray, count: np.ndarray, n_words: int, fixed: int, classes: int) -> np.ndarray:
    """Class of each of n_words words, and of ``fixed`` further symbols that keep a class of their own.

    Bigrams are given as (before, after, count). Each word in turn moves to the
    class that raises the class bigram likelihood most, until a sweep moves none.
    """
    size, k = n_words + fixed, classes + fixed
    right: list[tuple] = [()] * size
    left: list[tuple] = [()] * size
    for own, other, out in ((before, after, right), (after, before, left)):
        order = np.argsort(own, kind="stable")
        cuts = np.searchsorted(own[order], np.arange(size + 1))
        for w in range(size):
            part = order[cuts[w] : cuts[w + 1]]
            out[w] = (other[part], count[part])
    label = np.concatenate((np.arange(n_words) % classes, classes + np.arange(fixed)))
    table = np.zeros((k, k))
    np.add.at(table, (label[before], label[after]), count)
    rows, cols = table.sum(1), table.sum(0)
    least = 1e-9 + 1e-12 * float(_xlogx(table.sum()))  # above rounding, so that sweeps end
    moved = 1
    while moved:
        moved = 0
        for w in range(n_words):
            (r_w, r_n), (l_w, l_n) = right[w], left[w]
            own = int(r_n[r_w == w].sum())
            other_r, other_l = r_w != w, l_w != w
            to = np.bincount(label[r_w[other_r]], weights=r_n[other_r], minlength=k)
            by = np.bincount(label[l_w[other_l]], weights=l_n[other_l], minlength=k)
            n_to, n_by, old = to.sum() + own, by.sum() + own, label[w]
            table[old] -= to
            table[:, old] -= by
            table[old, old] -= own
            rows[old] -= n_to
            cols[old] -= n_by
            # What the likelihood gains if the word joins class c; the cell (c, c) is in both sums once.
            g, d = table[:classes], np.diagonal(table)[:classes]
            gain = (_xlogx(g + to) - _xlogx(g)).sum(1) + (_xlogx(table[:, :classes] + by[:, None]) - _xlogx(table[:, :classes])).sum(0)
            t, b = to[:classes], by[:classes]
            gain += _xlogx(d + t + b + own) - _xlogx(d + t) - _xlogx(d + b) + _xlogx(d)
            gain -= _xlogx(rows[:classes] + n_to) - _xlogx(rows[:classes]) + _xlogx(cols[:classes] + n_by) - _xlogx(cols[:classes])
            new = int(np.argmax(gain))
            if gain[new] <= gain[old] + least:
                new = old
            moved += new != old
            label[w] = new
            table[new] += to
            table[:, new] += by
            table[new, new] += own
            rows[new] += n_to
            cols[new] += n_by
    return label


def best_classes(table: np.ndarray, classes: int, word: np.ndarray, code: np.ndarray, n: np.ndarray, n_words: int) -> np.ndarray:
    """For each of n_words words the class that the class bigram likelihood gains most from, all else as counted in ``table``.

    Neighbours of a word are given as (word, code, n); code is a class before it, or the number of classes plus one after it.
    """
    k = len(table)
    key, back = np.unique(word * (2 * k) + code, return_inverse=True)
    n = np.bincount(back, weights=n, minlength=len(key))
    word, code = key // (2 * k), key % (2 * k)
    held = np.concatenate((table[:, :classes], table[:classes].T))
    plain = _xlogx(held)
    total = np.bincount(word[code < k], weights=n[code < k], minlength=n_words)
    out = np.zeros(n_words, np.int64)
    edge = np.searchsorted(word, np.arange(n_words + 1))
    rows, cols = table.sum(1)[:classes], table.sum(0)[:classes]
    for first in range(0, n_words, 4096):
        last = min(first + 4096, n_words)
        part = slice(edge[first], edge[last])
        gain = np.add.reduceat(_xlogx(held[code[part]] + n[part, None]) - plain[code[part]], edge[first:last] - edge[first])
        m = total[first:last, None]
        gain -= _xlogx(rows + m) - _xlogx(rows) + _xlogx(cols + m) - _xlogx(cols)
        out[first:last] = np.argmax(gain, 1)
    return out


def whole_groups(batches: Iterator[pa.RecordBatch], key: str) -> Iterator[pa.Table]:
    """Sorted batches cut so that no key's rows are parted."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        keys = batch.column(key).to_numpy()
        last = int(np.searchsorted(keys, keys[-1]))
        if held and (last or held[-1].column(key)[-1].as_py() != keys[0]):
            yield pa.Table.from_batches([*held, batch.slice(0, last)]).combine_chunks()
            held = []
        elif last:
            yield pa.Table.from_batches([batch.slice(0, last)]).combine_chunks()
        held.append(batch.slice(last))
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def contexts(texts: DataFrame, top: np.ndarray, label: np.ndarray, classes: int, frequent: np.ndarray) -> DataFrame:
    """Counts of the classes before (``left``) and after (``right``) each word that is not in the sorted ``top``; -1 where a row is of one side only."""
    k = classes + SHAPES + 1

    def run(batches):
        dense = np.zeros((len(frequent), 2 * k), np.int32)
        for block in blocks(batches):
            tokens = Tokens(block)
            at = lookup(tokens.key, top)
            own = np.where(at >= 0, label[at] if len(label) else 0, classes + tokens.shape)
            left, right = np.concatenate(([k - 1], own[:-1])), np.append(own[1:], k - 1)
            other = np.flatnonzero((at < 0) & (tokens.shape != SHAPES))
            place = lookup(tokens.key[other], frequent)
            near, far = place >= 0, other[place < 0]
            np.add.at(dense, (place[near], left[other[near]]), 1)
            np.add.at(dense, (place[near], k + right[other[near]]), 1)
            pair = left[far] * k + right[far]
            order = np.lexsort((pair, tokens.key[far]))
            word, pair = tokens.key[far][order], pair[order]
            new = np.flatnonzero(np.append(True, (word[1:] != word[:-1]) | (pair[1:] != pair[:-1]))) if len(word) else np.zeros(0, np.int64)
            yield rows(word[new], pair[new] // k, pair[new] % k, np.diff(np.append(new, len(word))))
        for first in range(0, len(frequent), 2000):
            at, code = np.nonzero(dense[first : first + 2000])
            yield rows(frequent[first + at], np.where(code < k, code, -1), np.where(code < k, -1, code - k), dense[first + at, code].astype(np.int64))

    def rows(word, left, right, n):
        return pa.RecordBatch.from_arrays([pa.array(word), pa.array(left.astype(np.int16)), pa.array(right.astype(np.int16)), pa.array(n)], ["word", "left", "right", "n"])

    return texts.mapInArrow(run, "word long, left short, right short, n long")


def assign(around: DataFrame, table: np.ndarray, classes: int) -> DataFrame:
    """word, n and label of every word of contexts(): one pass against the exchange's class bigrams."""
    k = len(table)

    def run(batches):
        for group in whole_groups(batches, "word"):
            word, at = np.unique(group["word"].to_numpy(), return_inverse=True)
            left, right, n = (group[c].to_numpy().astype(np.int64) for c in ("left", "right", "n"))
            l, r = left >= 0, right >= 0
            label = best_classes(table, classes, np.concatenate((at[l], at[r])), np.concatenate((left[l], k + right[r])), np.concatenate((n[l], n[r])), len(word))
            total = np.bincount(at[l], weights=n[l], minlength=len(word)).astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(word), pa.array(total), pa.array(label.astype(np.int16))], ["word", "n", "label"])

    return around.repartition("word").sortWithinPartitions("word").mapInArrow(run, "word long, n long, label short")


class ClassModel:
    """Every training word's count and class as a stored table, and those of the frequent ones for every task."""

    def __init__(self, labels: DataFrame, words: np.ndarray, counts: np.ndarray, classes: np.ndarray, n_classes: int, train_tokens: int, types: int):
        self.labels, self.words, self.counts, self.classes, self.n_classes = labels, words, counts, classes, n_classes
        self.train_tokens, self.types = train_tokens, types


def fit(texts: DataFrame, counts: DataFrame, clustered: int = 1200, frequent: int = 60_000, classes: int = 48) -> ClassModel:
    """counts: the stored word_counts of the texts.

    The ``clustered`` most frequent words are put into classes by exchange; then each
    other word joins its best class. ``frequent`` words go to every task; the others' counts and classes are joined.
    """
    if classes + SHAPES + 1 > UNKNOWN:
        raise ValueError("a class is stored in one byte")
    total = counts.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()
    head = counts.where(F.col("word") != int(END)).orderBy(F.desc("n"), "word").limit(frequent).toArrow()
    words, n = (head.column(c).to_numpy() for c in ("word", "n"))
    top = np.sort(words[:clustered])
    pairs = bigrams(texts, top).toArrow()
    code, count = (pairs.column(c).to_numpy() for c in ("code", "n"))
    size, fixed = len(top) + SHAPES + 1, SHAPES + 1
    before, after = code // size, code % size
    place = np.concatenate((lookup(words[: len(top)], top), []))
    rank = np.empty(size, np.int64)  # clustering goes through the words by frequency
    rank[place.astype(np.int64)] = np.arange(len(top))
    rank[len(top) :] = np.arange(len(top), size)
    classes = max(1, min(classes, len(top)))
    label = exchange(rank[before], rank[after], count, len(top), fixed, classes)
    k = classes + fixed
    table = np.zeros((k, k))
    np.add.at(table, (label[rank[before]], label[rank[after]]), count)
    others = assign(contexts(texts, top, label[rank[: len(top)]], classes, np.sort(words[clustered:])), table, classes)
    ends = counts.where(F.col("word") == int(END)).select("word", "n", F.lit(k - 1).cast("short").alias("label"))
    known = texts.sparkSession.createDataFrame([(int(w), int(x), int(c)) for w, x, c in zip(words[: len(top)], n, label)], "word long, n long, label short")
    labels = materialize(others.unionByName(known).unionByName(ends))
    near = labels.where(F.col("word") != int(END)).orderBy(F.desc("n"), "word").limit(frequent).unionByName(ends).toArrow().sort_by("word")
    return ClassModel(labels, *(near.column(c).to_numpy().astype(np.int64) for c in ("word", "n", "label")), k, total[0], total[1])


_PARTS = "place long, id long, held_out boolean, word long, i int, label short, labels binary, far binary, n_known long, seen double"
_TAGGED = "place long, id long, held_out boolean, n_tokens long, n_known long, seen double, labels binary"


def _pieces(column, kind) -> tuple[np.ndarray, np.ndarray]:
    """The numbers of a binary column end to end, and how many each row has."""
    got = [np.frombuffer(x, kind) for x in column.to_pylist()]
    return np.concatenate(got) if got else np.zeros(0, kind), np.array([len(x) for x in got], np.int64)


def tag(texts: DataFrame, model: ClassModel) -> DataFrame:
    """Each text with the class of every token (a byte each) and the summed log counts of its words.

    Classes of frequent words are known in place; each further word of a text is one
    row that meets its count and class, so no frequent word gathers rows.
    """
    share = texts.sparkSession.sparkContext.broadcast((model.words, model.counts, model.classes, model.n_classes))

    def run(batches):
        words, counts, classes, k = share.value
        for block in blocks(batches):
            tokens = Tokens(block)
            at = lookup(tokens.key, words)
            known = at >= 0
            label = np.where(known, classes[at] if len(classes) else 0, UNKNOWN).astype(np.uint8)
            seen = np.where(known, np.log10((counts[at] if len(counts) else 0) + 0.5), 0.0)
            first = tokens.edge[:-1]
            n = len(block)
            doc = np.repeat(np.arange(n), np.diff(tokens.edge))
            far = np.flatnonzero(~known)
            order = np.lexsort((tokens.key[far], doc[far]))
            ordered = far[order]
            new = np.ones(len(order), bool)
            new[1:] = (tokens.key[ordered][1:] != tokens.key[ordered][:-1]) | (doc[ordered][1:] != doc[ordered][:-1])
            lead = ordered[new]
            lead_edge = np.searchsorted(doc[lead], np.arange(n + 1))
            index = np.empty(len(far), np.int32)  # of each such token, which of its text's further words it is
            index[order] = np.cumsum(new) - 1 - lead_edge[doc[ordered]]
            far_edge = np.searchsorted(doc[far], np.arange(n + 1))
            raw, raw_far = label.tobytes(), index.tobytes()
            # A row for the text itself has i = -1 and a word that is its own, so that it meets no count and no crowd.
            place = block.column("place")
            own = np.concatenate((np.arange(n), doc[lead]))
            pick = pa.array(np.arange(len(own)), mask=np.arange(len(own)) >= n)
            none = np.zeros(len(lead))
            empty = [None] * len(lead)
            ids, held = block.rows.column("id"), block.rows.column("held_out")
            cols = [
                pa.array(place[own]), ids.take(pick), held.take(pick),
                pa.array(np.concatenate((place, tokens.key[lead]))),
                pa.array(np.concatenate((np.full(n, -1), np.arange(len(lead)) - lead_edge[doc[lead]])).astype(np.int32)),
                pa.array(np.concatenate((np.zeros(n, np.int64), k - fixed_shapes + tokens.shape[lead])).astype(np.int16)),
                pa.array([raw[a:b] for a, b in zip(tokens.edge.tolist(), tokens.edge[1:].tolist())] + empty, pa.binary()),
                pa.array([raw_far[4 * a : 4 * b] for a, b in zip(far_edge.tolist(), far_edge[1:].tolist())] + empty, pa.binary()),
                pa.array(np.concatenate((np.add.reduceat(known.astype(np.int64), first), none)).astype(np.int64)),
                pa.array(np.concatenate((np.add.reduceat(seen, first), none))),
            ]
            yield pa.RecordBatch.from_arrays(cols, [c.split()[0] for c in _PARTS.split(", ")])

    fixed_shapes = SHAPES + 1

    def fill(batches):
        for group in whole_groups(batches, "place"):
            i = group["i"].to_numpy()
            texts_at = np.flatnonzero(i < 0)
            text = group.take(pa.array(texts_at))
            text_place = text["place"].to_numpy()
            labels, sizes = _pieces(text["labels"], np.uint8)
            labels = labels.copy()
            index, far_sizes = _pieces(text["far"], np.int32)
            rest = np.flatnonzero(i >= 0)
            doc = np.searchsorted(text_place, group["place"].to_numpy()[rest])
            words_of = np.bincount(doc, minlength=len(text_place))
            begin = np.concatenate(([0], np.cumsum(words_of)))
            slot = begin[doc] + i[rest]
            label, c = np.empty(len(rest), np.uint8), np.empty(len(rest), np.int64)
            label[slot], c[slot] = group["label"].to_numpy()[rest], group["c"].to_numpy()[rest]
            at = np.repeat(begin[:-1], far_sizes) + index
            whose = np.repeat(np.arange(len(text_place)), far_sizes)
            labels[labels == UNKNOWN] = label[at]
            seen = text["seen"].to_numpy() + np.bincount(whose, weights=np.log10(c[at] + 0.5), minlength=len(text_place))
            n_known = text["n_known"].to_numpy() + np.bincount(whose, weights=c[at] > 0, minlength=len(text_place)).astype(np.int64)
            edge = np.concatenate(([0], np.cumsum(sizes))).tolist()
            raw = labels.tobytes()
            cols = [pa.array(text_place), text["id"].combine_chunks(), text["held_out"].combine_chunks(), pa.array(sizes), pa.array(n_known), pa.array(seen), pa.array([raw[a:b] for a, b in zip(edge, edge[1:])], pa.binary())]
            yield pa.RecordBatch.from_arrays([x.combine_chunks() if isinstance(x, pa.ChunkedArray) else x for x in cols], [c.split()[0] for c in _TAGGED.split(", ")])

    parts = texts.mapInArrow(run, _PARTS)
    found = model.labels.select(F.col("word").alias("counted"), F.col("n").alias("c"), F.col("label").alias("own"))
    met = parts.join(found, (parts["word"] == found["counted"]) & (F.col("i") >= 0), "left")
    met = met.select("place", "id", "held_out", "i", F.coalesce("own", "label").alias("label"), F.coalesce("c", F.lit(0)).alias("c"), "labels", "far", "n_known", "seen")
    return met.repartition("place").sortWithinPartitions("place").mapInArrow(fill, _TAGGED)


def transitions(tagged: DataFrame, k: int) -> np.ndarray:
    """Counts of neighbouring classes in the texts that are not held out; each text begins after an end."""

    def run(batches):
        total = np.zeros(k * k, np.int64)
        for block in blocks(batches, BLOCK_TAGS, "labels"):
            own = block.data.astype(np.int64)
            total += np.bincount(np.append(k - 1, own[:-1]) * k + own, minlength=k * k)
        some = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(total[some])], ["code", "n"])

    table = np.zeros(k * k)
    for r in tagged.where("not held_out").select("labels").mapInArrow(run, "code long, n long").groupBy("code").agg(F.sum("n").alias("n")).collect():
        table[r["code"]] = r["n"]
    return table.reshape(k, k)


def score(texts: DataFrame, model: ClassModel) -> DataFrame:
    """place, id, held_out, n_tokens, n_known, base_score, score and train_tokens of each text."""
    k = model.n_classes
    tagged = materialize(tag(texts, model))
    table = transitions(tagged, k)
    tokens, types = np.zeros(k), np.zeros(k)
    for r in model.labels.groupBy("label").agg(F.sum("n").alias("n"), F.count("*").alias("v")).collect():
        tokens[r["label"]], types[r["label"]] = r["n"], r["v"]
    step = np.log10((table + 0.5) / (table.sum(1, keepdims=True) + 0.5 * k)) - np.log10(tokens + 0.5 * (types + 1))
    whole = float(np.log10(model.train_tokens + 0.5 * (model.types + 1)))

    def run(batches):
        for block in blocks(batches, BLOCK_TAGS, "labels"):
            own = block.data.astype(np.int64)
            seen = block.column("seen")
            out = {c: block.rows.column(c) for c in ("place", "id", "held_out", "n_tokens", "n_known")}
            out["base_score"] = pa.array(seen - np.diff(block.edge) * whole)
            out["score"] = pa.array(seen + np.add.reduceat(step[np.append(k - 1, own[:-1]), own], block.edge[:-1]))
            yield pa.RecordBatch.from_pydict(out)

    out = tagged.mapInArrow(run, "place long, id long, held_out boolean, n_tokens long, n_known long, base_score double, score double")
    return out.withColumn("train_tokens", F.lit(int(model.train_tokens)).cast("long"))


def score_documents(docs: DataFrame, held_out: Column, id_col: str = "doc_id", text_col: str = "text", **sizes: int) -> DataFrame:
    """Train on the rows for which held_out is not true, and score all rows."""
    texts = documents(docs, text_col, id=F.col(id_col).cast("long"), place=F.monotonically_increasing_id(), held_out=F.coalesce(held_out, F.lit(False)))
    train = texts.where("not held_out")
    counts = materialize(word_counts(train))
    return score(texts, fit(train, counts, **sizes))
