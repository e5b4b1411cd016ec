"""Lazy expressions over trains, rewritten before anything runs.

Scalings fold into coefficients, sums of sums become one sum, and reductions (fixed
indices, weighted sums over modes) move below sums and below expansion, so that they
meet the smallest trains. A chain of sums is rounded once, at its end. What is left
is lowered to joins of packed trains and one Arrow function.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace
from math import prod

import numpy as np
from pyspark.sql import DataFrame

from traincube.functions import kernels as K
from traincube.operators import trains

#: A mode is fixed at an index, summed with weights, or summed as it is (None).
Reduction = dict[int, "int | list[float] | None"]


def _weights(how: Reduction, modes: list[int]) -> dict[int, np.ndarray]:
    return {k: np.ones(modes[k]) if w is None else np.eye(modes[k])[w] if isinstance(w, int) else np.asarray(w, float) for k, w in how.items()}


@dataclass(frozen=True)
class Combination:
    """Sum of coefficient times trains, each reduced the same way, then rounded if a tolerance is given."""

    terms: tuple[tuple[float, DataFrame], ...]
    reduced: tuple[Reduction, ...] = ()
    tau: float | None = None

    def __add__(self, other: Combination) -> Combination:
        if self.reduced != other.reduced:
            raise ValueError("the terms of a sum must have the same modes")
        return Combination(self.terms + other.terms, self.reduced, self.tau if other.tau is None else other.tau if self.tau is None else min(self.tau, other.tau))

    def __mul__(self, c: float) -> Combination:
        return replace(self, terms=tuple((a * c, t) for a, t in self.terms))

    __rmul__ = __mul__

    def __neg__(self) -> Combination:
        return self * -1.0

    def __sub__(self, other: Combination) -> Combination:
        return self + -other

    def reduce(self, how: Reduction) -> Combination:
        """how is by the modes that are left after earlier reductions."""
        return replace(self, reduced=(*self.reduced, how))

    def round(self, tau: float) -> Combination:
        return replace(self, tau=tau)

    def expand(self) -> Cells:
        return Cells(self)

    def optimized(self) -> Combination:
        """The same trains once each, without those that cancel."""
        weight: dict[int, float] = {}
        frames: dict[int, DataFrame] = {}
        for c, t in self.terms:
            weight[id(t)] = weight.get(id(t), 0.0) + c
            frames[id(t)] = t
        kept = tuple((c, frames[k]) for k, c in weight.items() if c != 0.0) or ((0.0, self.terms[0][1]),)
        return replace(self, terms=kept)

    def steps(self) -> list[str]:
        """What will run, innermost first."""
        own = self.optimized()
        out = [f"reduce modes {sorted(r)} of each term" for r in own.reduced] + [f"sum of {len(own.terms)} trains"] * (len(own.terms) > 1)
        return [*out, *([f"round to {own.tau:g}"] if own.tau is not None else [])]

    def _change(self) -> Callable[[K.Train], K.Train]:
        reduced = self.reduced

        def change(cores: K.Train) -> K.Train:
            for how in reduced:
                cores = K.contract(cores, _weights(how, [c.shape[1] for c in cores]))
            return cores

        return change

    def _gain(self, c: float) -> Callable[[list[int]], float]:
        """How many times scaling and reductions can enlarge the norm of an error."""
        reduced = self.reduced

        def gain(modes: list[int]) -> float:
            out, left = abs(c), list(modes)
            for how in reduced:
                out *= prod(float(np.linalg.norm(w)) for w in _weights(how, left).values())
                left = [n for k, n in enumerate(left) if k not in how] or [1]
            return out

        return gain

    def frame(self) -> DataFrame:
        """Trains, with statistics and error bounds of the result."""
        own, change = self.optimized(), self._change()
        part = lambda c, t: trains.map_trains(t, lambda x: K.scale(change(x), c), own._gain(c))
        out = part(*own.terms[0])
        for c, t in own.terms[1:]:
            out = trains.pair_trains(out, part(c, t), K.add)
        return out if own.tau is None else trains.rounded(out, own.tau)


@dataclass(frozen=True)
class Cells:
    """All entries of a combination; reductions of cells are reductions of trains."""

    of: Combination
    most: int = field(default=1 << 20)

    def where(self, at: dict[int, int]) -> Cells:
        return replace(self, of=self.of.reduce(at))

    def sum(self, *modes: int) -> Cells:
        return replace(self, of=self.of.reduce({k: None for k in modes}))

    def frame(self) -> DataFrame:
        return trains.expand(self.of.frame(), self.most)


def of(frame: DataFrame) -> Combination:
    return Combination(((1.0, frame),))
