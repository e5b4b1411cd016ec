"""Functions for SQL: keys and tolerances as inlined expressions, trains as Arrow functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, LongType

from traincube.functions import kernels as K


def _spread(x: str, q: int, shift: int, bits: int) -> str:
    return " | ".join(f"shiftleft(shiftright({x}, {b}) & 1L, {q * b + shift})" for b in range(bits))


def _train(parts) -> K.Train:
    return [np.asarray(c["core"], float).reshape(c["r_left"], c["n"], c["r_right"], order="F") for c in sorted(parts, key=lambda c: c["k"])]


@F.pandas_udf(DoubleType())
def tt_norm(cores: pd.Series) -> pd.Series:
    """The Frobenius norm from the cores."""
    return cores.map(lambda c: K.norm(_train(c)))


@F.pandas_udf(DoubleType())
def tt_entry(cores: pd.Series, digits: pd.Series) -> pd.Series:
    """The entry at 0-based digits."""
    return pd.Series([K.entries(_train(c), np.array([d], int))[0] for c, d in zip(cores, digits)])


@F.pandas_udf(LongType())
def tt_numel(cores: pd.Series) -> pd.Series:
    return cores.map(lambda c: sum(p["r_left"] * p["n"] * p["r_right"] for p in c))


@F.udtf(returnType="idx bigint, val double")
class ExpandTrain:
    """Every entry of a train: SELECT ... FROM trains, LATERAL tt_expand(cores)."""

    def eval(self, cores: list):
        for k, v in enumerate(K.expand(_train(cores)).tolist()):
            yield k, v


_CORES = "ARRAY<STRUCT<k: INT, r_left: INT, n: INT, r_right: INT, core: ARRAY<DOUBLE>>>"


def register(spark: SparkSession) -> None:
    """Make morton2, morton3, compose_tol, long_index, tt_ratio, tt_norm, tt_entry, tt_numel and the table function tt_expand known to SQL."""
    places = "aggregate(sequence(1, size(modes)), named_struct('i', 0L, 'step', 1L), (s, k) -> named_struct('i', s.i + s.step * element_at(digits, k), 'step', s.step * element_at(modes, k)), s -> s.i)"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION long_index(digits ARRAY<BIGINT>, modes ARRAY<BIGINT>) RETURNS BIGINT RETURN {places}")
    numel = "aggregate(cores, 0L, (s, c) -> s + CAST(c.r_left AS BIGINT) * c.n * c.r_right)"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION tt_ratio(n BIGINT, cores {_CORES}) RETURNS DOUBLE RETURN n / {numel}")
    spark.udtf.register("tt_expand", ExpandTrain)
    for name, args, q in (("morton2", "xy", 2), ("morton3", "xyz", 3)):
        bits = 63 // q if q == 3 else 31
        body = " | ".join(f"({_spread(a, q, q - 1 - k, bits)})" for k, a in enumerate(args))
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({', '.join(a + ' BIGINT' for a in args)}) RETURNS BIGINT RETURN {body}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION compose_tol(tau DOUBLE, tau_round DOUBLE, levels INT) RETURNS DOUBLE RETURN (1 + tau) * pow(1 + tau_round, levels) - 1")
    for f, name in ((tt_norm, "tt_norm"), (tt_entry, "tt_entry"), (tt_numel, "tt_numel")):
        spark.udf.register(name, f)
