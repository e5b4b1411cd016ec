"""Mode lists: how long axes are split into short ones, and long indices.

Flattening is column-major everywhere: the first mode runs fastest. A mode list is
plain data, so a reshape never moves a row.
"""

from __future__ import annotations

from math import prod

from pyspark.sql import Column
from pyspark.sql import functions as F


def strides(modes: list[int]) -> list[int]:
    """Distance in the flat array between neighbours along each mode."""
    out, step = [], 1
    for n in modes:
        out.append(step)
        step *= n
    return out


def long_index(columns: list[Column], modes: list[int]) -> Column:
    """0-based flat index from 0-based digits."""
    total = F.lit(0).cast("long")
    for c, s in zip(columns, strides(modes)):
        total = total + c.cast("long") * F.lit(s).cast("long")
    return total


def digits(index: Column, modes: list[int]) -> list[Column]:
    """0-based digits of a flat index."""
    return [F.pmod(F.floor(index / F.lit(s)).cast("long"), F.lit(n).cast("long")) for n, s in zip(modes, strides(modes))]


def unfold(index: Column, modes: list[int], k: int) -> tuple[Column, Column]:
    """Row and column of the matrix whose rows are the first k modes."""
    rows = F.lit(prod(modes[:k])).cast("long")
    return F.pmod(index, rows), F.floor(index / rows).cast("long")


def small_primes(n: int) -> list[int]:
    """Prime factors, ascending."""
    out, p = [], 2
    while p * p <= n:
        while n % p == 0:
            out.append(p)
            n //= p
        p += 1
    return [*out, n] if n > 1 or not out else out


def smooth_ceiling(n: int, primes: tuple[int, ...] = (2, 5)) -> int:
    """The smallest number from n on with no prime factors but these."""
    while True:
        rest = n
        for p in primes:
            while rest % p == 0:
                rest //= p
        if rest == 1:
            return n
        n += 1


def modes_for_vector(d: int, level: int) -> list[int]:
    """A vector of length 2**d bisected level - 1 times: one leaf mode, then binary ones."""
    return [2 ** (d - level + 1)] + [2] * (level - 1)


def modes_for_matrix(d: int, level: int, interlace: bool = True, merge_pairs: bool = False) -> list[int]:
    """A square matrix of size 2**d; interlaced: both leaves, then the digits of the axes in turn."""
    one = modes_for_vector(d, level)
    if not interlace:
        return one + one
    if merge_pairs:
        return [one[0] * one[0]] + [4] * (level - 1)
    return [one[0], one[0]] + [2, 2] * (level - 1)


def interlaced_axes(axes: list[list[int]]) -> tuple[list[int], list[tuple[int, int]]]:
    """Digits of any number of axes in turn: the modes, and (axis, digit) of each."""
    order = [(a, k) for k in range(max(map(len, axes))) for a in range(len(axes)) if k < len(axes[a])]
    return [axes[a][k] for a, k in order], order


def interlaced_index(columns: list[Column], axes: list[list[int]]) -> Column:
    """Flat index after interlacing, from 0-based axis indices."""
    modes, order = interlaced_axes(axes)
    split = [digits(c, own) for c, own in zip(columns, axes)]
    return long_index([split[a][k] for a, k in order], modes)


def modes_for_particles(steps: int, entities: int, components: int) -> list[int]:
    """Prime modes of steps, then of entities; components stay whole."""
    return [p for n in (steps, entities) for p in small_primes(n) if p > 1] + [components]


def ratio_ceiling(modes: list[int]) -> float:
    """The compression ratio when every rank is 1."""
    return prod(modes) / sum(modes)


def train_numel(modes: list[int], ranks: list[int]) -> int:
    """Numbers in all cores; ranks include the two ones at the ends."""
    return sum(a * n * b for a, n, b in zip(ranks, modes, ranks[1:]))


def cost_model(modes: list[int], rank: int) -> dict[str, float]:
    """Numbers kept and operations, to leading order, with all ranks the same: the whole array, its train, rounding, and the largest factorization."""
    n, d, widest = prod(modes), len(modes), max(modes)
    first = max(min(rank * m, n // m) ** 2 * max(rank * m, n // m) for m in modes)
    return {"dense": n, "train": d * widest * rank**2, "rounding": d * widest * rank**3, "factorization": float(first)}
