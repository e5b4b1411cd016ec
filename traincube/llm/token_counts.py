"""Exact token counts at every prefix of a text, for a piece model with merges.

A prefix's tokens are fixed by its last one: the piece that ends there and fits
the last token of what stands before it, where two pieces fit if the two together
encode to just these. So a dynamic program over prefixes, with the pieces that
end at each place found by an automaton, gives the count of every prefix in one
pass, and questions of truncation or budget need no second encoding.

No piece holds a space mark after another character, or a line break, so texts
fall into segments whose counts add up; segments that occur again are looked up.

Null counts as empty, and an empty text has no tokens. Strings of special tokens
in a text are ordinary text. Rows with null or repeated ids are counted like any
other; an empty table gives an empty result.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from traincube.llm.words import blocks, documents

MARK = "▁"
_SEGMENT = re.compile(f"{MARK}+[^{MARK}\n]*|[^{MARK}\n]+|\n")
_MOST_SEGMENTS = 400_000
_LONG = 64


class PrefixCounter:
    """The dynamic program for a sentencepiece model file."""

    def __init__(self, path: str):
        import ahocorasick
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        ids = [i for i in range(model.get_piece_size()) if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i) or model.is_unused(i))]
        self.rank = {model.id_to_piece(i): -model.get_score(i) for i in ids}
        self.text = {i: model.id_to_piece(i) for i in ids}
        if any(MARK in p.lstrip(MARK) or "\n" in p for p in self.rank):
            raise ValueError("a piece of this model crosses words or lines")
        self.pairs = {p[k : k + 2] for p in self.rank for k in range(len(p) - 1)}
        self.pieces = ahocorasick.Automaton()
        for i, p in self.text.items():
            if self.merged(p) == [p]:
                self.pieces.add_word(p, (len(p), i))
        self.pieces.make_automaton()
        self.fit: dict[int, bool] = {}
        self.ends: dict[str, int] = {}
        self.parts: dict[str, int] = {}

    def merged(self, s: str) -> list[str]:
        """The pieces of a short string: the best pair of neighbours is joined, the first among equals."""
        parts = list(s)
        while True:
            best = min(((self.rank[a + b], k) for k, (a, b) in enumerate(zip(parts, parts[1:])) if a + b in self.rank), default=None)
            if best is None:
                return parts
            k = best[1]
            parts[k : k + 2] = [parts[k] + parts[k + 1]]

    def fits(self, a: int, b: int) -> bool:
        key = a << 32 | b
        known = self.fit.get(key)
        if known is None:
            if len(self.fit) >= 4 * _MOST_SEGMENTS:
                self.fit.clear()
            known = self.fit[key] = self.merged(self.text[a] + self.text[b]) == [self.text[a], self.text[b]]
        return known

    def program(self, s: str) -> list[int]:
        """Token counts of all prefixes of a segment, from the empty one on."""
        n = len(s)
        count, last = [0] * (n + 1), [-1] * (n + 1)
        ends: list[list] = [[] for _ in range(n)]
        for end, piece in self.pieces.iter(s):
            ends[end].append(piece)
        for i in range(1, n + 1):
            for size, piece in ends[i - 1]:
                before = last[i - size]
                if before < 0 or self.fits(before, piece):
                    count[i], last[i] = count[i - size] + 1, piece
                    break
            else:  # a character that the model spells in bytes parts what is before from what is after
                count[i] = count[i - 1] + len(s[i - 1].encode("utf-8", "surrogatepass"))
        return count

    def segments(self, text: str) -> list[str]:
        """The text as the model sees it, in parts whose counts add up."""
        if not text:
            return []
        text = MARK + text.replace(" ", MARK)
        if MARK + MARK in text or "\x01" in text:
            return _SEGMENT.findall(text)
        return text.replace(MARK, "\x01" + MARK).replace("\n", "\x01\n\x01").split("\x01")

    def segment(self, s: str) -> int:
        """Token count of a segment, cut where no piece has the two neighbours."""
        total, begin, pairs, parts = 0, 0, self.pairs, self.parts
        for k in range(1, len(s) + 1):
            if k == len(s) or s[k - 1 : k + 1] not in pairs:
                part = s[begin:k]
                n = parts.get(part)
                if n is None:
                    n = self.program(part)[-1]
                    if len(part) <= _LONG:
                        if len(parts) >= _MOST_SEGMENTS:
                            parts.clear()
                        parts[part] = n
                total += n
                begin = k
        return total

    def learn(self, s: str) -> int:
        """Token count of a segment that is not known yet, kept if it is short."""
        n = self.segment(s)
        if len(s) <= _LONG:
            if len(self.ends) >= _MOST_SEGMENTS:
                self.ends.clear()
            self.ends[s] = n
        return n

    def counts(self, segments: list[str]) -> list[int]:
        """Token counts of segments."""
        get = self.ends.get
        out = [get(s) for s in segments]
        if None in out:
            for k, n in enumerate(out):
                if n is None:
                    n = get(segments[k])
                    out[k] = self.learn(segments[k]) if n is None else n
        return out

    def count(self, text: str) -> int:
        return sum(self.counts(self.segments(text)))

    def within(self, text: str, limit: int) -> tuple[int, int]:
        """Tokens of the text, and code points of its longest prefix of at most ``limit`` tokens.

        Counts at the ends of segments are counts of prefixes and never fall, so only the
        segment in which the limit is passed needs its own prefixes.
        """
        segments = self.segments(text)
        counts = self.counts(segments)
        total = sum(counts)
        if total <= limit:
            return total, len(text)
        ends = np.cumsum(counts)
        k = int(np.searchsorted(ends, limit, "right"))
        before = int(ends[k - 1]) if k else 0
        own = np.array(self.program(segments[k]))
        # The model's own leading mark is not a character of the text.
        return total, max(0, sum(map(len, segments[:k])) + int(np.flatnonzero(before + own <= limit)[-1]) - 1)

    def prefixes(self, text: str) -> np.ndarray:
        """Token counts of all prefixes of the text by code points, from the empty one on."""
        out, total = [0], 0
        for s in self.segments(text):
            if s:
                own = self.program(s)
                out += [total + n for n in own[1:]]
                total += own[-1]
        # The model's own leading mark is not a character of the text.
        return np.array(out[:1] + out[2:] if text else out)


_counters: dict[str, PrefixCounter] = {}


def counter(path: str) -> PrefixCounter:
    """One for each worker process and model file."""
    if path not in _counters:
        _counters[path] = PrefixCounter(path)
    return _counters[path]


def token_counts(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", limit: int = 4096) -> DataFrame:
    """id, n_bytes and n_tokens of each whole text, and ``fits``, the code points of its longest prefix of at most ``limit`` tokens.

    ``path`` is the model file on every executor.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = counter(path)
        for block in blocks(batches):
            n, fits = zip(*(own.within(b.decode("utf-8", "replace"), limit) for b in block.bodies()))
            yield pa.RecordBatch.from_arrays([block.rows.column("id"), pa.array(np.diff(block.edge)), pa.array(n, pa.int64()), pa.array(fits, pa.int64())], ["id", "n_bytes", "n_tokens", "fits"])

    return documents(docs, text_col, id=F.col(id_col).cast("long")).mapInArrow(run, "id long, n_bytes long, n_tokens long, fits long")


def prefix_counts(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id and prefixes: entry k is the token count of the first k code points."""

    def run(batches):
        own = counter(path)
        for block in blocks(batches):
            rows = [own.prefixes(b.decode("utf-8", "replace")) for b in block.bodies()]
            yield pa.RecordBatch.from_arrays([block.rows.column("id"), pa.array(rows, pa.list_(pa.int32()))], ["id", "prefixes"])

    return documents(docs, text_col, id=F.col(id_col).cast("long")).mapInArrow(run, "id long, prefixes array<int>")


def longest_within(prefixes, budget: int):
    """Column: code points of the longest prefix of at most ``budget`` tokens, from stored prefix counts.

    The last such prefix counts, as a longer prefix can have fewer tokens.
    """
    return F.size(prefixes) - 1 - (F.array_position(F.transform(F.reverse(prefixes), lambda n: n <= budget), True) - 1)
