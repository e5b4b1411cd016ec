"""Packing token sequences by cutting-stock column generation.

Every document's ids, with an end id, are cut into full sequences and one rest. A
rest above half a sequence is cut at the half, as long pieces leave room that nothing
fills, and then at a sixteenth, so that few lengths occur and the program over them
takes few steps. The histogram of piece lengths is a cutting-stock problem: a linear program over
patterns of lengths that fit a sequence, whose columns are priced by a knapsack
dynamic program. The solution is rounded down to whole sequences, what is left is
filled longest first into the fullest place that holds it, and the documents of
each length, ranked, take the pattern places in order. The driver only ever holds
the histogram and the patterns, both bounded by the sequence length.

Null text counts as empty; such a document is its end id alone. Rows with null or
repeated ids are packed like any other. An empty table gives an empty result.
"""

from __future__ import annotations

import os
import re
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from traincube.llm.scratch import materialize
from traincube.llm.words import blocks, documents, sums_by

CAPACITY = 1024
END_ID = 0
_MOST_WORDS = 200_000
_LONG = 64
# Marks that stand after words.
_MARKS = ".,;:!?"
_ODD_SPACE = re.compile(r"[^\S \n]")
# Bytes with which white space other than space and line break can begin.
_MAYBE_ODD = np.zeros(256, bool)
_MAYBE_ODD[[9, 11, 12, 13, 28, 29, 30, 31, 0xC2, 0xE1, 0xE2, 0xE3]] = True
_SEGMENT = re.compile(r"[ \n]*[^ \n]+|[ \n]+")


class IdCache:
    """Ids as little-endian bytes; parts of a text that the tokenizer treats alone are encoded once.

    The tokenizer's pattern never joins a character that is not white space to white
    space after it, nor letters to the marks of _MARKS after them, so parts that begin
    at such places are encoded alone.
    """

    def __init__(self, path: str):
        # Tasks share the cores already; threads of each worker's own would only take memory.
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.model = self.tokenizer.model
        self.special = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        # Two generations: what the last _MOST_WORDS new parts did not use is forgotten.
        self.ids: dict[str, bytes] = {"": b""}
        self.old: dict[str, bytes] = {}
        # The vocabulary writes each byte as a printable character: itself, or one from 256 on.
        plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
        odd = [b for b in range(256) if b not in set(plain)]
        self.written = {b: chr(b) for b in plain} | {b: chr(256 + k) for k, b in enumerate(odd)}

    def encode(self, text: str) -> bytes:
        return array("I", self.tokenizer.encode(text, add_special_tokens=False).ids).tobytes()

    def _word(self, word: str) -> bytes:
        """Ids of letters with at most a space before them, which the pattern never parts."""
        return array("I", [t.id for t in self.model.tokenize(word.encode().decode("latin-1").translate(self.written))]).tobytes()

    def parts(self, text: str, odd: bool = True) -> list[str] | None:
        """None: the text is encoded as a whole. odd: white space other than space and line break may occur."""
        if odd and _ODD_SPACE.search(text) or any(s in text for s in self.special):
            return None
        if "  " in text or " \n" in text or "\n " in text or "\n\n" in text or "\x01" in text or text[:1].isspace() or text[-1:].isspace():
            return _SEGMENT.findall(text)
        return text.replace(" ", "\x01 ").replace("\n", "\x01\n\x01").split("\x01")

    def _learn(self, part: str) -> bytes:
        ids = self.old.get(part)
        if ids is None:
            core = part.rstrip(_MARKS)
            if not (core[1:] if core[:1] == " " else core).isalpha():
                ids = self.encode(part)
            elif len(core) == len(part):
                ids = self._word(part)
            else:
                ids = (self.ids.get(core) or self.old.get(core) or self._word(core)) + (self.ids.get(part[len(core) :]) or self._learn(part[len(core) :]))
        if len(part) <= _LONG:
            self.ids[part] = ids
        return ids

    def of(self, text: str, odd: bool = True) -> bytes:
        parts = self.parts(text, odd)
        if parts is None:
            return self.encode(text)
        found = list(map(self.ids.get, parts))
        if None in found:
            for k, x in enumerate(found):
                if x is None:
                    found[k] = self._learn(parts[k])
            if len(self.ids) > _MOST_WORDS:
                self.old, self.ids = self.ids, {"": b""}
        return b"".join(found)


_caches: dict[str, IdCache] = {}


def id_cache(path: str) -> IdCache:
    """One for each worker process and tokenizer file."""
    if path not in _caches:
        _caches[path] = IdCache(path)
    return _caches[path]


def price(dual: np.ndarray, lengths: np.ndarray, capacity: int, copies: np.ndarray) -> tuple[float, np.ndarray]:
    """The pattern of greatest dual value with at most ``copies`` of each length: a knapsack over total lengths."""
    some = np.flatnonzero(dual > 1e-12)
    items = np.repeat(some, copies[some])
    best = np.zeros(capacity + 1)
    taken = np.zeros((len(items), capacity + 1), bool)
    for k, (size, gain) in enumerate(zip(lengths[items].tolist(), dual[items].tolist())):
        value = best[: capacity + 1 - size] + gain
        better = value > best[size:] + 1e-13
        taken[k, size:] = better
        best[size:] = np.where(better, value, best[size:])
    pattern, c = np.zeros(len(lengths), np.int64), capacity
    for k in range(len(items) - 1, -1, -1):
        if taken[k, c]:
            pattern[items[k]] += 1
            c -= int(lengths[items[k]])
    return float(best[capacity]), pattern


def price_all(dual: np.ndarray, lengths: np.ndarray, capacity: int) -> tuple[float, np.ndarray]:
    """The pattern of greatest dual value, with any number of copies that fits."""
    items = np.flatnonzero(dual > 1e-12)
    sizes, gains = lengths[items], dual[items]
    best, last = np.zeros(capacity + 1), np.full(capacity + 1, -1)
    for c in range(1, capacity + 1):
        best[c] = best[c - 1]
        n = int(np.searchsorted(sizes, c, "right"))
        if n:
            value = best[c - sizes[:n]] + gains[:n]
            k = int(value.argmax())
            if value[k] > best[c] + 1e-13:
                best[c], last[c] = value[k], k
    pattern, c = np.zeros(len(lengths), np.int64), capacity
    while c > 0:
        if last[c] < 0:
            c -= 1
        else:
            pattern[items[last[c]]] += 1
            c -= int(sizes[last[c]])
    return float(best[capacity]), pattern


def cutting_stock(lengths: np.ndarray, demand: np.ndarray, capacity: int = CAPACITY, gap: float = 5e-4) -> tuple[np.ndarray, np.ndarray, float]:
    """Patterns [pattern, length], how often the linear program uses each, and a bound below which no packing lies; lengths ascend.

    Patterns with about as many copies of a length as its demand gives each sequence are
    priced first, as they lead to the optimum in fewer steps; when none of them improves
    the program, any number of copies is priced. That value also bounds the optimum from below (the duals divided
    by it are feasible), as the total length does. Ends within ``gap`` of the larger
    bound, at the latest when no pattern at all improves the program.
    """
    fit = capacity // lengths
    columns = np.diag(fit).astype(np.int64)
    # Demands are raised by tiny unequal amounts, so that no step is empty and the program can't go in circles.
    inverse, use = np.diag(1.0 / fit), (demand + 1e-7 * np.arange(1, len(lengths) + 1)) / fit
    bound = float((lengths * demand).sum()) / capacity
    copies = np.minimum(fit, np.maximum(2, np.ceil(2 * demand / bound))).astype(np.int64)
    while use.sum() > bound * (1 + gap):
        dual = inverse.sum(0)
        value, pattern = price(dual, lengths, capacity, copies)
        if value <= 1 + 1e-6:
            value, pattern = price_all(dual, lengths, capacity)
            bound = max(bound, float(dual @ demand) / max(value, 1.0))
            if value <= 1 + 1e-9:
                break
        step = inverse @ pattern
        able = np.flatnonzero(step > 1e-10)
        out = int(able[(use[able] / step[able]).argmin()])
        theta = use[out] / step[out]
        use = np.maximum(use - theta * step, 0)
        use[out] = theta
        row = inverse[out] / step[out]
        inverse -= np.outer(step, row)
        inverse[out] = row
        columns[out] = pattern
    return columns, use, bound


def fill(lengths: np.ndarray, demand: np.ndarray, capacity: int = CAPACITY) -> list[dict[int, int]]:
    """Sequences as {length index: times}: longest first, each into the fullest sequence with room for it."""
    room: list[list[int]] = [[] for _ in range(capacity + 1)]
    out: list[dict[int, int]] = []
    for k in range(len(lengths) - 1, -1, -1):
        size = int(lengths[k])
        for _ in range(int(demand[k])):
            r = next((r for r in range(size, capacity) if room[r]), None)
            if r is None:
                out.append({})
                s, r = len(out) - 1, capacity
            else:
                s = room[r].pop()
            out[s][k] = out[s].get(k, 0) + 1
            room[r - size].append(s)
    return out


def plan(histogram: dict[int, int], capacity: int = CAPACITY) -> np.ndarray:
    """Rows (length, first rank, sequences, times in each, first sequence, offset) by length and rank.

    Documents of a length with ranks from ``first rank`` on fill these sequences'
    places in turn. Sequences of full pieces come first.
    """
    full = histogram.get(capacity, 0)
    lengths = np.array(sorted(k for k in histogram if k < capacity), np.int64)
    demand = np.array([histogram[k] for k in lengths.tolist()], np.int64)
    rows, done, sequence = [[capacity, 0, full, 1, 0, 0]], np.zeros(len(lengths), np.int64), full

    def take(pattern: dict[int, int], times: int):
        nonlocal sequence
        offset = 0
        for k in sorted(pattern, reverse=True):
            rows.append([int(lengths[k]), int(done[k]), times, pattern[k], sequence, offset])
            done[k] += times * pattern[k]
            offset += int(lengths[k]) * pattern[k]
        sequence += times

    if len(lengths):
        columns, use, _ = cutting_stock(lengths, demand, capacity)
        for column, x in zip(columns, np.floor(use + 1e-6).astype(np.int64)):
            own = np.flatnonzero(column)
            times = int(min([x, *((demand[own] - done[own]) // column[own])]))
            if times > 0:
                take({int(k): int(column[k]) for k in own}, times)
        for pattern in fill(lengths, demand - done, capacity):
            take(pattern, 1)
    rows.sort()
    return np.array(rows, np.int64)


def cut_points(n: int, capacity: int = CAPACITY) -> list[int]:
    """Where n ids are cut, from 0 to n."""
    cuts, grid = list(range(0, n - capacity + 1, capacity)), max(1, capacity // 16)
    done = len(cuts) * capacity
    for step in (capacity // 2, grid):
        if n - done > step > 0:
            cuts.append(done)
            done += (n - done) // step * step
    return [*cuts, *([done] if done < n else []), n]


_PIECES = "id long, start long, length long, ids_crc32 long, doc_tokens long, part int, local long"


def pieces(docs: DataFrame, path: str, capacity: int = CAPACITY, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The pieces of each document, ranked by length within each task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache, part, seen = id_cache(path), TaskContext.get().partitionId(), {}
        end = np.array([END_ID], "<u4").tobytes()
        for block in blocks(batches):
            ids, out = block.rows.column("id").to_pylist(), []
            odd = sums_by(block.edge, _MAYBE_ODD[block.data].astype(np.int64)).tolist()
            for i, body, o in zip(ids, block.bodies(), odd):
                raw = cache.of(body.decode("utf-8", "replace"), o > 0) + end
                n = len(raw) // 4
                cuts = cut_points(n, capacity)
                for a, b in zip(cuts, cuts[1:]):
                    length = b - a
                    local = seen[length] = seen.get(length, -1) + 1
                    out.append((i, a, length, zlib.crc32(raw[4 * a : 4 * b]), n, part, local))
            kinds = [pa.int64()] * 5 + [pa.int32(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(list(x), t) for x, t in zip(zip(*out), kinds)], [c.split()[0] for c in _PIECES.split(", ")])

    return documents(docs, text_col, id=F.col(id_col).cast("long")).mapInArrow(run, _PIECES)


def pack(docs: DataFrame, path: str, capacity: int = CAPACITY, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, start, length, ids_crc32, doc_tokens, sequence_id and offset of each piece."""
    cut = materialize(pieces(docs, path, capacity, id_col, text_col))
    groups = materialize(cut.groupBy("length", "part").agg(F.count("*").alias("n")))
    table = plan({r["length"]: r["n"] for r in groups.groupBy("length").agg(F.sum("n").alias("n")).collect()}, capacity)
    before = groups.select("length", "part", (F.sum("n").over(Window.partitionBy("length").orderBy("part")) - F.col("n")).alias("before"))
    ranked = cut.join(before, ["length", "part"]).withColumn("rank", F.col("before") + F.col("local"))

    def place(batches):
        # Ranks of a length never pass 2**40.
        key = (table[:, 0] << 40) + table[:, 1]
        for x in batches:
            length, rank = (x.column(c).to_numpy() for c in ("length", "rank"))
            at = np.searchsorted(key, (length << 40) + rank, "right") - 1
            _, first, _, times, sequence, offset = table[at].T
            turn, slot = np.divmod(rank - first, times)
            cols = [x.column(c) for c in ("id", "start", "length", "ids_crc32", "doc_tokens")]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(sequence + turn), pa.array(offset + slot * length)], ["id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"])

    return ranked.select("id", "start", "length", "ids_crc32", "doc_tokens", "rank").mapInArrow(place, "id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long")
