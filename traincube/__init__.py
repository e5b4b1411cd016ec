"""Tensor-train compression of numeric tables on Spark."""

from __future__ import annotations

import os
from pathlib import Path


def importable(spark) -> None:
    """Let the Python workers of a running session import this package from where the driver found it."""
    root, env = str(Path(__file__).resolve().parent.parent), spark.sparkContext.environment
    paths = [p for p in env.get("PYTHONPATH", "").split(os.pathsep) if p]
    if root not in paths:
        env["PYTHONPATH"] = os.pathsep.join([*paths, root])
