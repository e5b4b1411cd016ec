"""Secret scanning with a trigram inverted index.

From each rule's regular expression a Boolean query over trigrams is derived that
every match must satisfy. Each block of texts gets an inverted index from the
trigrams asked for to the texts that hold them; postings are intersected and
united as the query says, and only the candidates are verified with the
expression. A rule without mandatory trigrams is run over every text.

Spans are in code points, end exclusive. Null and empty texts have no spans.
Texts of any length are scanned whole. Rows with null or repeated ids are
scanned like any other; an empty table gives an empty result.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import cached_property
from itertools import product
from re import _constants as C  # the parsed form that the standard library compiles from
from re import _parser

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from traincube.llm.words import Block, blocks, documents

#: A query is a set of alternatives, each a set of trigrams that all must occur; ANY holds for every text.
Query = frozenset
ANY: Query = frozenset([frozenset()])
_MOST = 64


def _least(alternatives) -> Query:
    """Without alternatives that another implies."""
    out: list[frozenset] = []
    for a in sorted(set(alternatives), key=len):
        if not any(b <= a for b in out):
            out.append(a)
    return frozenset(out) if len(out) <= _MOST else ANY


def _both(a: Query, b: Query) -> Query:
    if len(a) * len(b) > _MOST * 4:
        return min(a, b, key=len) if ANY not in (a, b) else (a if b == ANY else b)
    return _least(x | y for x in a for y in b)


def _of_strings(strings: set[str]) -> Query:
    """What a text holds that contains one of the strings."""
    return _least(frozenset(s.encode()[i : i + 3] for i in range(len(s.encode()) - 2)) for s in strings)


def _parts(tree, flags: int) -> tuple[set[str] | None, Query]:
    """The strings that a sequence can match, if few, and the query that its matches satisfy."""
    run: set[str] | None = {""}
    whole, query = True, ANY

    def close():
        nonlocal run, query, whole
        if run and run != {""}:
            query = _both(query, _of_strings(run))
        run, whole = {""}, False

    for op, arg in tree:
        strings, own = _item(op, arg, flags)
        if strings is not None and len(run) * len(strings) <= _MOST:
            run = {a + b for a, b in product(run, strings)}
        else:
            close()
            query = _both(query, own)
            if strings is not None and len(strings) <= _MOST:
                run = strings
    if whole:
        return run, _of_strings(run)
    close()
    return None, query


def _item(op, arg, flags: int) -> tuple[set[str] | None, Query]:
    if op is C.LITERAL:
        return ({chr(arg).lower()}, ANY) if arg < 128 else (None, ANY)
    if op is C.IN:
        chars: set[str] = set()
        for kind, x in arg:
            if kind is C.LITERAL and x < 128:
                chars.add(chr(x).lower())
            elif kind is C.RANGE and x[1] < 128 and x[1] - x[0] < _MOST:
                chars |= {chr(c).lower() for c in range(x[0], x[1] + 1)}
            else:
                return None, ANY
        return (chars, ANY) if len(chars) <= 8 else (None, ANY)
    if op is C.SUBPATTERN:
        return _parts(arg[3], flags)
    if op is C.BRANCH:
        found = [_parts(x, flags) for x in arg[1]]
        strings = set().union(*(s for s, _ in found if s is not None))
        if all(s is not None for s, _ in found) and len(strings) <= _MOST:
            return strings, _of_strings(strings)
        return None, _least(a for _, q in found for a in q)
    if op in (C.MAX_REPEAT, C.MIN_REPEAT, C.POSSESSIVE_REPEAT):
        low, high, tree = arg
        strings, own = _parts(tree, flags)
        if low == 0:
            return ({""} | strings, ANY) if high == 1 and strings is not None else (None, ANY)
        if strings is not None and len(strings) ** low <= _MOST and low == high:
            return {"".join(x) for x in product(strings, repeat=low)}, ANY
        if strings is not None and len(strings) ** min(low, 3) <= _MOST:
            own = _of_strings({"".join(x) for x in product(strings, repeat=min(low, 3))})
        return None, own
    if op is C.AT:
        return {""}, ANY
    return None, ANY


def trigram_query(pattern: str) -> Query:
    """Trigrams, lower-cased in ASCII, that a text must hold to match; ANY if none are certain."""
    strings, query = _parts(_parser.parse(pattern), 0)
    return _of_strings(strings) if strings is not None else query


@dataclass(frozen=True)
class Rule:
    """A kind of secret: matches of ``pattern`` count whose group ``group`` has at least ``least`` characters."""

    kind: str
    pattern: str
    least: int = 0
    group: int = 0
    query: Query = field(init=False)

    def __post_init__(self):
        object.__setattr__(self, "query", trigram_query(self.pattern))

    @cached_property
    def compiled(self) -> re.Pattern:
        return re.compile(self.pattern, re.ASCII)

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k != "compiled"}

    def spans(self, text: str) -> list[tuple[int, int]]:
        return [m.span() for m in self.compiled.finditer(text) if len(m[self.group]) >= self.least]


# The expressions of the rules.
BASE_RULES = (
    Rule("assign", r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 8, 2),
    Rule("access", r"AKIA[A-Z0-9]+", 16),
    Rule("hex", r"[0-9a-f]+", 32),
)
MORE_RULES = (
    Rule("github", r"gh[pousr]_[A-Za-z0-9]{36,}"),
    Rule("slack", r"xox[abprs]-[0-9A-Za-z-]{10,}"),
    Rule("google", r"AIza[0-9A-Za-z_-]{35}"),
    Rule("stripe", r"[sr]k_live_[0-9A-Za-z]{20,}"),
    Rule("jwt", r"eyJ[A-Za-z0-9_-]{10,}\.eyJ[A-Za-z0-9_-]{10,}\.[A-Za-z0-9_-]{10,}"),
    Rule("bearer", r"[Bb]earer\x20+[A-Za-z0-9._~+/-]{20,}=*"),
    Rule("pem", r"-----BEGIN (?:[A-Z]+ ){0,3}PRIVATE KEY-----"),
)
RULES = BASE_RULES + MORE_RULES

_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[ord("A") : ord("Z") + 1] += 32


class Index:
    """Postings, sorted text numbers of a block, of the trigrams asked for."""

    def __init__(self, block: Block, trigrams: list[bytes]):
        codes = np.array([int.from_bytes(t, "big") for t in trigrams], np.int32)
        order = np.argsort(codes)
        self.size = len(block)
        self.postings: dict[bytes, np.ndarray] = {t: np.zeros(0, np.int64) for t in trigrams}
        data = _LOWER[block.data]
        if len(data) < 3 or not len(codes):
            return
        pairs = np.zeros(1 << 16, bool)
        pairs[codes >> 8] = True
        pair = (data[:-1].astype(np.uint16) << 8) | data[1:]
        at = np.flatnonzero(pairs[pair[:-1]])
        code = (pair[at].astype(np.int32) << 8) | data[at + 2]
        slot = np.minimum(np.searchsorted(codes[order], code), len(codes) - 1)
        found = codes[order][slot] == code
        at, slot = at[found], slot[found]
        text = np.searchsorted(block.edge, at, "right") - 1
        inside = at + 2 < block.edge[text + 1]
        pairs_found = np.unique(slot[inside] * len(block) + text[inside])
        cuts = np.searchsorted(pairs_found, np.arange(len(codes) + 1) * len(block))
        for k, o in enumerate(order.tolist()):
            self.postings[trigrams[o]] = pairs_found[cuts[k] : cuts[k + 1]] - k * len(block)

    def candidates(self, query: Query) -> np.ndarray:
        """Texts that may match: intersections of postings, united."""
        if query == ANY:
            return np.arange(self.size)
        found = []
        for alternative in query:
            lists = sorted((self.postings[t] for t in alternative), key=len)
            hit = lists[0]
            for other in lists[1:]:
                if not len(hit):
                    break
                hit = hit[np.isin(hit, other, assume_unique=True)]
            found.append(hit)
        return np.unique(np.concatenate(found)) if found else np.zeros(0, np.int64)


def needed(rules: tuple[Rule, ...]) -> list[bytes]:
    return sorted({t for r in rules for a in r.query for t in a})


def _full(rule: Rule) -> re.Pattern:
    """For a first look at bytes: a repeat whose whole match must be long needs that many characters at once."""
    m = re.fullmatch(r"(\[[^\]\\]*\])\+", rule.pattern)
    return re.compile((f"{m[1]}{{{rule.least},}}" if m and not rule.group else rule.pattern).encode())


_SPAN = pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())])
SPANS = "id long, spans array<struct<kind: string, start: long, end: long>>"


def _scan(rules: tuple[Rule, ...]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trigrams = needed(rules)
        for block in blocks(batches):
            index, bodies = Index(block, trigrams), block.bodies()
            found: list[list] = [[] for _ in bodies]
            for k, rule in enumerate(rules):
                look = _full(rule) if rule.query == ANY else None
                for d in index.candidates(rule.query).tolist():
                    if look is None or look.search(bodies[d]):
                        found[d] += [(a, k, b) for a, b in rule.spans(bodies[d].decode("utf-8", "replace"))]
            spans = [[{"kind": rules[k].kind, "start": a, "end": b} for a, k, b in sorted(x)] for x in found]
            yield pa.RecordBatch.from_arrays([block.rows.column("id"), pa.array(spans, pa.list_(_SPAN))], ["id", "spans"])

    return run


def find_secrets(docs: DataFrame, rules: tuple[Rule, ...] = RULES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id`` and ``spans`` by start and then by the rules' order, for each document."""
    return documents(docs, text_col, id=F.col(id_col).cast("long")).mapInArrow(_scan(rules), SPANS)


def inverted_index(docs: DataFrame, rules: tuple[Rule, ...] = RULES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The index as a table: a trigram, and the ids of the texts of one block that hold it."""
    trigrams = needed(rules)

    def run(batches):
        for block in blocks(batches):
            ids = block.rows.column("id").to_pylist()
            posts = {t: p for t, p in Index(block, trigrams).postings.items() if len(p)}
            yield pa.RecordBatch.from_pydict({"trigram": pa.array([t.decode("latin-1") for t in posts], pa.string()), "ids": pa.array([[ids[i] for i in p.tolist()] for p in posts.values()], pa.list_(pa.int64()))})

    return documents(docs, text_col, id=F.col(id_col).cast("long")).mapInArrow(run, "trigram string, ids array<long>")


def redact(docs: DataFrame, rules: tuple[Rule, ...] = RULES, text_col: str = "text", mark: str = "[secret]") -> DataFrame:
    """``docs`` with each span, overlapping ones together, replaced by ``mark``; other texts stay as they are."""
    trigrams = needed(rules)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in blocks(batches, column=text_col):
            index, bodies = Index(block, trigrams), block.bodies()
            found: dict[int, list] = {}
            for rule in rules:
                look = _full(rule) if rule.query == ANY else None
                for d in index.candidates(rule.query).tolist():
                    if look is None or look.search(bodies[d]):
                        if spans := rule.spans(bodies[d].decode("utf-8", "replace")):
                            found.setdefault(d, []).extend(spans)
            rows = block.rows
            if found:
                at = rows.schema.get_field_index(text_col)
                texts = rows.column(at).to_pylist()
                for d, spans in found.items():
                    parts, done = [], 0
                    for a, b in sorted(spans):
                        if a >= done:
                            parts += [texts[d][done:a], mark]
                        done = max(done, b)
                    texts[d] = "".join([*parts, texts[d][done:]])
                rows = pa.RecordBatch.from_arrays([pa.array(texts, rows.column(k).type) if k == at else rows.column(k) for k in range(rows.num_columns)], schema=rows.schema)
            yield rows

    return docs.mapInArrow(run, docs.schema)
