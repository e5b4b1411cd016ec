"""Rewritten expressions give what plain arrays give."""

import numpy as np

from traincube.functions import kernels as K
from traincube.operators import compress, trains
from traincube.plans import expr


def frame(spark, x):
    row = trains.pack(K.decompose(x, [2, 3, 4], 0.0)[0], variable="v", level=0, seg=0, n_original=24, vmin=0.0, vmax=1.0, fro2=1.0, err_abs=0.0, steps=1)
    return spark.createDataFrame(trains.table([row])).cache()


def cells(e):
    return np.array([r["val"] for r in e.frame().orderBy("idx").collect()])


def test_expressions(spark):
    x, y = np.random.default_rng(0).standard_normal((2, 24))
    a, b = expr.of(frame(spark, x)), expr.of(frame(spark, y))
    assert np.allclose(cells((2 * a - b).expand()), 2 * x - y)
    t = (2 * a - b + a).round(1e-12)
    assert t.steps() == ["sum of 2 trains", "round to 1e-12"] and np.allclose(cells(t.expand()), 3 * x - y)
    whole = (x + y).reshape(2, 3, 4, order="F")
    assert np.allclose(cells((a + b).expand().where({1: 2})), whole[:, 2].ravel(order="F"))
    assert np.allclose(cells((a + b).expand().sum(0, 2)), whole.sum((0, 2)))
    assert np.allclose(cells((a + b).expand().where({0: 1}).sum(1)), whole[1].sum(1))
    assert np.allclose(cells((a - a).expand()), 0)


def test_statistics_follow_arithmetic(spark):
    """Size, norm and error bound of results, where operands carry errors of their own."""
    x, y = np.random.default_rng(3).standard_normal((2, 24))

    def rough(v):
        cores, lost = K.decompose(v, [2, 3, 4], 0.3)
        row = trains.pack(cores, variable="v", level=0, seg=0, n_original=24, vmin=float(v.min()), vmax=float(v.max()), fro2=float(v @ v), err_abs=lost**0.5, steps=1)
        return spark.createDataFrame(trains.table([row]))

    a, b = rough(x), rough(y)
    whole = lambda v: v.reshape(2, 3, 4, order="F")
    cases = {
        "scale": (trains.scaled(a, -3.0), -3 * x), "sum": (trains.pair_trains(a, b, K.add), x + y), "product": (trains.product(a, b, 0.1), x * y), "round": (trains.rounded(a, 0.5), x),
        "slice": (trains.contracted(a, {1: np.eye(3)[2]}), whole(x)[:, 2].ravel(order="F")), "modes": (trains.contracted(a, {0: np.ones(2), 2: np.ones(4)}), whole(x).sum((0, 2))),
        "lazy": ((2 * expr.of(a) - expr.of(b)).reduce({0: None}).round(0.2).frame(), whole(2 * x - y).sum(0).ravel(order="F")),
    }
    for name, (frame_, want) in cases.items():
        r = frame_.collect()[0].asDict(True)
        got = K.expand(trains.unpack(r))
        assert r["n"] == r["n_original"] == len(want) and np.isclose(r["fro2"], got @ got), name
        assert np.linalg.norm(got - want) <= r["err_abs"] * (1 + 1e-9), name
        assert (r["vmin"] is None) == (name != "scale"), name
    r = trains.numel(cases["round"][0]).collect()[0]
    assert r["nrmse"] is None and r["err_abs"] >= 0.1 * np.linalg.norm(x)
    r = cases["scale"][0].collect()[0]
    assert (r["vmin"], r["vmax"]) == (-3 * x.max(), -3 * x.min())


def test_strategy():
    assert compress.strategy(1000, 1 << 20) == "task" and compress.strategy(1 << 30, 8 << 30) == "panels"
