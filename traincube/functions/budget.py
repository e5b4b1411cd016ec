"""Error targets and how they are shared among stages."""

from __future__ import annotations

from dataclasses import dataclass
from math import sqrt

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Budget:
    """``kind`` fro: error relative to the norm; nrmse: root mean square error relative to the range."""

    kind: str
    tau: float

    def absolute(self, n: int, vmin: float, vmax: float, norm: float) -> float:
        """The Frobenius norm that the error may have."""
        return self.tau * norm if self.kind == "fro" else self.tau * (vmax - vmin) * sqrt(n)


def fro_from_nrmse(tau, vmin, vmax, n, norm) -> Column:
    return tau * (vmax - vmin) * F.sqrt(n) / norm


def nrmse_from_fro(tau, vmin, vmax, n, norm) -> Column:
    return tau * norm / ((vmax - vmin) * F.sqrt(n))


def composed(tau, tau_round, levels=1) -> Column:
    """Relative error after ``levels`` roundings on top of tau."""
    return (1 + tau) * F.pow(1 + tau_round, levels) - 1


def stage_tau(tau, levels) -> Column:
    """The same relative error for each of levels + 1 stages that compose to tau."""
    return F.pow(1 + tau, 1.0 / (levels + 1)) - 1
