"""Words of UTF-8 texts as numpy arrays.

A word is a run of bytes other than space and 0x09-0x0D, which is the same as a
run of such code points. All words of a block of texts are found and hashed with
a fixed number of array passes, so cost follows bytes and not words.
"""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BLOCK_BYTES = 2 << 20

_U = np.uint64
_BASE = 0x9E3779B97F4A7C15


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads every bit over the others."""
    x = x ^ (x >> _U(30))
    x = x * _U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> _U(27))
    x = x * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


def seeds(n: int, salt: int) -> np.ndarray:
    """n odd 64-bit numbers that depend on salt alone."""
    return mix(np.arange(1, n + 1, dtype=_U) * _U(_BASE) + _U(salt)) | _U(1)


SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
_CODES = seeds(256, 7)
_LOWER_CODES = _CODES.copy()
_LOWER_CODES[ord("A") : ord("Z") + 1] = _CODES[ord("a") : ord("z") + 1]
for _t in (_CODES, _LOWER_CODES):
    _t[SPACE] = 0
_STEP = int(seeds(1, 11)[0])
_BACK = pow(_STEP, -1, 1 << 64)
_powers: dict[int, np.ndarray] = {}


def _power(base: int, n: int) -> np.ndarray:
    """base to 0, 1, ... n-1, modulo 2 to the 64."""
    have = _powers.get(base)
    if have is None or len(have) < n:
        size = 1 << max(12, (n - 1).bit_length())
        have = np.full(size, base, _U)
        have[0] = 1
        have = np.multiply.accumulate(have)
        if n <= 4 * BLOCK_BYTES:
            _powers[base] = have
    return have[:n]


def documents(docs: DataFrame, text: str = "text", **keep: Column | str) -> DataFrame:
    """The columns named in keep and the text as bytes in ``body``, null as empty.

    Only these columns are read, so further columns of any name do no harm.
    """
    columns = [(docs[c] if isinstance(c, str) else c).alias(name) for name, c in keep.items()]
    return docs.select(*columns, F.coalesce(docs[text].cast("binary"), F.lit(b"")).alias("body"))


class Block:
    """Some texts, end to end: ``data`` bytes, ``edge`` where each begins, ``rows`` with the other columns."""

    def __init__(self, rows: pa.RecordBatch, data: np.ndarray, edge: np.ndarray):
        self.rows, self.data, self.edge = rows, data, edge

    def __len__(self) -> int:
        return len(self.edge) - 1

    def column(self, name: str) -> np.ndarray:
        """A column without nulls."""
        return self.rows.column(name).to_numpy(zero_copy_only=False)

    def bodies(self) -> list[bytes]:
        raw, edge = self.data.tobytes(), self.edge.tolist()
        return [raw[a:b] for a, b in zip(edge, edge[1:])]


def release() -> None:
    """Give back to the system what this worker has freed: workers live on between tasks, and their executor counts what they hold."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(AttributeError, OSError):  # of glibc alone
        ctypes.CDLL(None).malloc_trim(0)


def blocks(batches: Iterator[pa.RecordBatch], size: int = BLOCK_BYTES, column: str = "body") -> Iterator[Block]:
    """Cut Arrow batches with a column of texts into blocks of about ``size`` bytes, a long text alone; null is empty."""
    release()
    for batch in batches:
        body = batch.column(column)
        if isinstance(body, pa.ChunkedArray):
            body = body.combine_chunks()
        wide = pa.types.is_large_binary(body.type) or pa.types.is_large_string(body.type)
        _, at, data = body.buffers()
        at = np.frombuffer(at, np.int64 if wide else np.int32)[body.offset : body.offset + len(body) + 1].astype(np.int64) if len(body) else np.zeros(1, np.int64)
        data = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
        first = 0
        while first < len(body):
            last = max(first + 1, int(np.searchsorted(at, at[first] + size, "right")) - 1)
            edge = at[first : last + 1]
            yield Block(batch.slice(first, last - first), data[edge[0] : edge[-1]], edge - edge[0])
            first = last
    release()


class Words:
    """Where the words of a block begin and end, which text each is of, and a 64-bit hash of each."""

    def __init__(self, block: Block, lower: bool = False, hashed: bool = True):
        data, edge = block.data, block.edge
        n = len(data)
        inside = np.zeros(n + 2, bool)
        np.logical_not(SPACE[data], out=inside[1:-1])
        begins = inside[1:-1] & ~inside[:-2]
        ends = inside[1:-1] & ~inside[2:]
        cut = edge[(edge > 0) & (edge < n)]
        begins[cut] |= inside[1:-1][cut]
        ends[cut - 1] |= inside[1:-1][cut - 1]
        self.begin, self.end = np.flatnonzero(begins), np.flatnonzero(ends) + 1
        self.edge = np.searchsorted(self.begin, edge)
        self.block = block
        if hashed:
            self.hash = self.spans(self.begin, self.end, lower)

    def spans(self, begin: np.ndarray, end: np.ndarray, lower: bool = False) -> np.ndarray:
        """Hashes of byte ranges of the block that hold no white space."""
        sums = self._sums(lower)
        return mix((sums[end] - sums[begin]) * _power(_BACK, len(sums))[begin] + (end - begin).astype(_U))

    def _sums(self, lower: bool) -> np.ndarray:
        if not hasattr(self, "_prefix"):
            data = self.block.data
            self._prefix = np.zeros(len(data) + 1, _U)
            np.cumsum((_LOWER_CODES if lower else _CODES)[data] * _power(_STEP, len(data)), out=self._prefix[1:])
        return self._prefix

    def counts(self) -> np.ndarray:
        return np.diff(self.edge)

    def grams(self, k: int, salt: int = 0) -> tuple[np.ndarray, np.ndarray]:
        """Hash of the k words from each word on, and whether these lie in one text."""
        n = max(0, len(self.hash) - k + 1)
        out = np.zeros(n, _U)
        for j, c in enumerate(seeds(k, 1000 + salt)):
            out += self.hash[j : j + n] * c
        last = np.repeat(self.edge[1:], self.counts())[:n]
        return mix(out), np.arange(n) + k <= last


def sums_by(edge: np.ndarray, values: np.ndarray) -> np.ndarray:
    """Sums of values between consecutive edges."""
    total = np.zeros(len(values) + 1, values.dtype if values.dtype.kind == "f" else np.int64)
    np.cumsum(values, out=total[1:])
    return total[edge[1:]] - total[edge[:-1]]
