"""Every query with SQL gives the rows that the SQL gives; the others run."""

import duckdb
import numpy as np
import pandas as pd
import pytest

from traincube.plans import relational, registry, streams, workloads  # noqa: F401

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SLOW = {"q_kernel_sweep", "q_levels_ratio", "q_order_ablation", "q_segment_length_sweep", "q_timestep_sweep", "q_measured_errors"}


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


def same(got: pd.DataFrame, want: pd.DataFrame) -> None:
    columns = sorted(want.columns)
    assert sorted(got.columns) == columns
    got, want = (x[columns].sort_values(columns, ignore_index=True) for x in (got, want))
    assert len(got) == len(want)
    for c in columns:
        equal = (got[c] == want[c]) | (got[c].isna() & want[c].isna())
        assert equal.all(), (c, got[c][~equal].head(), want[c][~equal].head())


@pytest.mark.parametrize("name", sorted(registry.ORACLES))
def test_sql(spark, sf, duck, name):
    same(registry.QUERIES[name](spark, sf).toPandas(), duck.execute(registry.ORACLES[name]).df())


@pytest.mark.parametrize("name", sorted(set(registry.QUERIES) - set(registry.ORACLES) - SLOW))
def test_runs(spark, sf, name):
    assert registry.QUERIES[name](spark, sf).count() > 0


def test_filters_and_columns_reach_the_scan(spark, sf):
    plan = relational.triaxial_grid(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "l_orderkey" not in plan and "l_shipdate" in plan
    plan = relational.front_mask(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "event_type" not in plan and "user_id" in plan


def test_measured_errors_keep_the_bounds(spark, sf):
    rows = registry.QUERIES["q_measured_errors"](spark, sf).collect()
    assert len(rows) == 10 and all(r["bounded"] and 0 < r["max_nrmse"] <= 0.1 for r in rows)


def test_baselines_against_numpy(spark, sf):
    """Numbers kept and errors of SVD and Tucker of one variable, from numpy alone."""
    cells = workloads.grids.triaxial_cells(spark, sf, *workloads.FULL).toPandas()
    x = np.zeros((2, workloads.FULL[1], 64, 6))
    for k in range(6):
        x[cells["status"], cells["step"], cells["rve"], k] = cells[f"s{k}"]
    span = x.max() - x.min()
    got = {r["tau"]: r for r in registry.QUERIES["q_baseline_svd"](spark, sf).where("variable = 'incremental_stress'").collect()}
    m = x.reshape(2 * workloads.FULL[1], -1, order="F")
    u, sigma, v = np.linalg.svd(m, full_matrices=False)
    for tau in workloads.TAUS:
        r = next(r for r in range(1, len(sigma) + 1) if np.linalg.norm(sigma[r:]) <= tau * span * np.sqrt(x.size))
        off = np.linalg.norm(m - (u[:, :r] * sigma[:r]) @ v[:r]) / np.sqrt(x.size) / span
        assert got[tau]["ratio"] == pytest.approx(x.size / (r * sum(m.shape))) and got[tau]["nrmse"] == pytest.approx(off, rel=1e-6)
    tucker = registry.QUERIES["q_baseline_tucker"](spark, sf).collect()
    assert all(r["nrmse"] <= r["tau"] * (1 + 1e-9) for r in tucker)


def test_entry(spark):
    import __spark_entry__

    rows = {(r["variable"], r["level"]): r for r in __spark_entry__.entry(spark).collect()}
    assert len(rows) == 10 and all(r["max_nrmse"] <= 0.1 for r in rows.values())
    assert rows["position", 4]["ratio_pooled"] > rows["position", 0]["ratio_pooled"]


def test_triaxial_has_every_row_and_variable(spark, sf):
    cells = workloads.grids.triaxial_cells(spark, sf, *workloads.FULL)
    assert cells.selectExpr("sum(s4)").first()[0] == spark.read.parquet(f"{sf}/lineitem.parquet").count()
    assert registry.QUERIES["q_baseline_svd"](spark, sf).select("variable").distinct().count() == 5


def test_univariate_sweep_is_whole(spark, sf):
    out = registry.QUERIES["q_univariate_sweep"](spark, sf).collect()
    assert len(out) == 132 and {r["level"] for r in out} == set(range(10, 21)) and {r["n"] for r in out} == {1 << 20} and all(r["within_tol"] for r in out)


@pytest.mark.parametrize("name,table", [(f"q_{n}", t) for n, t in {"kernel_index": "lineitem", "kernel_samples": "lineitem", "univariate_samples": "orders", "long_index": "orders", "ratio_formula": "lineitem", "small_primes": "lineitem", "smooth_ceiling": "orders", "vector_levels": "orders", "tolerance_compose": "lineitem", "tolerance_split": "lineitem"}.items()])
def test_formulas_read_a_table(spark, sf, name, table):
    assert f"{table}.parquet" in registry.QUERIES[name](spark, sf)._jdf.queryExecution().executedPlan().toString()


def test_kernels_are_sampled_at_the_orders(spark, sf, tmp_path):
    """All cells are there from sf0.001 on; with fewer orders their cells alone are sampled."""
    assert len(workloads._sampled(spark, sf, 10)) == 1024
    spark.read.parquet(f"{sf}/orders.parquet").where("o_orderkey < 3").write.parquet(str(tmp_path / "orders.parquet"))
    at = workloads._sampled(spark, str(tmp_path), 10)
    assert list(at) == [0, 1, 2] and np.count_nonzero(workloads._kernel(at, 1024)) == 9
