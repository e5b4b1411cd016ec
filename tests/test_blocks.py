"""Segments that are cut into blocks of entities: the same rows as from whole ones, or as from SQL."""

from dataclasses import replace

import numpy as np
import pytest

from pyspark.sql import functions as F

from traincube.functions import kernels as K
from traincube.functions.budget import Budget
from traincube.operators import compare, compress, merge
from traincube.operators.trains import pack, unpack
from traincube.plans import registry, workloads
from traincube.sources import grids

from test_queries import duck, same  # noqa: F401  the fixture

EXACT = "q_tt_roundtrip q_tt_add q_tt_sub q_tt_scale q_tt_hadamard q_tt_round_exact q_order_roundtrip_every q_order_roundtrip_first q_tt_statistics q_tt_entry q_tt_slice q_tt_mode_sum q_tt_mode_mean q_tt_norm q_tt_dot q_tt_dist q_tt_concat_roundtrip q_tt_stack_roundtrip q_tree_roundtrip q_late_update q_vehicle_level0 q_sediment_level0 q_vehicle_levels q_sediment_levels q_error_bound".split()


@pytest.fixture
def blocks(monkeypatch):
    """Sets whose segments are cut into several blocks already at sf0.001."""
    for name, part in (("vehicle", 48 * 4), ("sediment", 96 * 64)):
        real = getattr(grids, name)

        def cut(*args, real=real, part=part, **kw):
            kind, cells = real(*args, **kw)
            return replace(kind, whole=part, part=part), cells

        monkeypatch.setattr(grids, name, cut)


@pytest.mark.parametrize("name", EXACT)
def test_sql_with_blocks(spark, sf, duck, blocks, name):  # noqa: F811
    assert grids.vehicle(spark, sf)[0].blocks > 2 and grids.sediment(spark, sf)[0].blocks > 2
    same(registry.QUERIES[name](spark, sf).toPandas(), duck.execute(registry.ORACLES[name]).df())


@pytest.mark.parametrize("name,rows", [("q_concat_vs_stack", 4), ("q_ratio_timeline", 160), ("q_sediment_natural_vs_tensorized", 160), ("q_sediment_natural_levels", 12), ("q_oneshot_vs_stream", 4), ("q_segment_length_sweep", 8)])
def test_ratios_with_blocks(spark, sf, blocks, name, rows):
    """One row for each segment, level or method, over all its blocks, within the target."""
    out = registry.QUERIES[name](spark, sf).collect()
    assert len(out) == rows
    for r in out:
        assert r.asDict().get("within_tol", True) and all(v > 0 for c, v in r.asDict().items() if c.startswith("ratio"))
        assert all(v <= 0.1 * (1 + 1e-9) for c, v in r.asDict().items() if "nrmse" in c)


def test_levels_with_blocks(spark, sf, blocks):
    """Bounds of the merged blocks hold, and no cell is left out."""
    kind, _ = grids.sediment(spark, sf)
    t = workloads.tree(spark, sf, "sediment").groupBy("variable", "level").agg({"n_original": "sum", "nrmse": "max", "seg": "count"}).collect()
    assert len(t) == 12 and all(r["sum(n_original)"] == kind.steps * kind.entities * 3 and r["max(nrmse)"] <= 0.1 * (1 + 1e-9) for r in t)
    assert sorted(r["count(seg)"] for r in t) == sorted(2 * [80, 40, 20, 10, 5, 1])


def test_block_sizes():
    kind = grids.ParticleSet("x", 64, 16, 90_000, 100_000, "none", ())
    assert kind.block == 5120 and kind.blocks == 18 and sum(map(kind.size, range(18))) == 90_000 and kind.padded_size(17) == kind.padded_size(17) >= kind.size(17)
    assert replace(kind, padded=90_000).padded_size(17) == kind.size(17) and replace(kind, entities=1500, padded=1600).blocks == 1


def test_hadamard_ranks_stay_within_the_array():
    """Two trains of rank 20 would give cores of 400 x 400; the product's ranks are those that its modes allow from the left."""
    rng = np.random.default_rng(1)
    a = [rng.standard_normal(s) for s in ((1, 4, 20), (20, 5, 20), (20, 6, 1))]
    out = K.hadamard(a, a)
    assert K.ranks(out) == [1, 4, 20, 1] and np.allclose(K.expand(out), K.expand(a) ** 2)


def test_joins_without_block_cores():
    """Many trains are joined as by their block cores, which would have the squares of all ranks together."""
    rng = np.random.default_rng(2)
    parts = [K.decompose(rng.standard_normal(4 * 6 * 3), [4, 6, 3], 0.2)[0] for _ in range(7)]
    for tau in (1e-12, 0.3):
        for got, want in ((K.concat_rounded(parts, tau), K.recompress(K.concat(parts), tau)), (K.stack_rounded(parts, tau), K.recompress(K.stack(parts), tau))):
            assert K.ranks(got[0]) == K.ranks(want[0]) and np.allclose(K.expand(got[0]), K.expand(want[0])) and np.isclose(got[1], want[1])


ONE_TASK = "q_tt_roundtrip q_tt_add q_tt_sub q_tt_scale q_tt_hadamard q_tt_round_exact q_tt_slice q_tt_mode_sum q_tt_mode_mean q_tt_concat_roundtrip q_tt_stack_roundtrip q_tree_roundtrip q_late_update".split()


@pytest.mark.parametrize("name", ONE_TASK)
def test_no_train_travels(spark, sf, blocks, name):
    """Trains are made, changed and expanded in one task: there is one Python step only, so executors hold no batches of trains."""
    plan = registry.QUERIES[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("FlatMapGroupsInArrow") >= 1 and "MapInArrow" not in plan


def test_level0_leaves_cores_behind(spark, sf, blocks):
    """Ratios ask for sizes and bounds; cores, which are most of a train, stay in their task."""
    _, t = workloads.level0(spark, sf, "sediment")
    assert t.where("cores is not null").isEmpty() and t.where("size(ranks) > 1 and err_abs is not null").count() > 0


def test_block_is_worked_out_once(monkeypatch):
    """Each segment asks for the block, which took longer to find than a segment to compress."""
    kind, asked = grids.ParticleSet("x", 2560, 8, 1_200_000, 1_200_000, "first", ()), []
    monkeypatch.setattr(grids, "smooth_ceiling", lambda n, real=grids.smooth_ceiling: asked.append(n) or real(n))
    first = [kind.padded_size(0), kind.size(3), kind.blocks], len(asked)
    assert first == ([kind.padded_size(0), kind.size(3), kind.blocks], len(asked))


def test_segments_of_a_train_are_expanded_together(monkeypatch):
    """What the segments of a merged train share is expanded once, with the entries of each as from its own train."""
    rng = np.random.default_rng(3)
    parts = [dict(pack(K.decompose(rng.standard_normal(4 * 6 * 3), [4, 6, 3], 0.2)[0]), variable="v", level=0, seg=s, n_original=72, vmin=-3.0, vmax=3.0, fro2=72.0, err_abs=1.0, steps=4) for s in range(6)]
    top = merge.merge_rows(parts, (2, 3), Budget("fro", 0.5))[-1]
    want, made = [K.expand(merge.piece(top, s, (2, 3))) for s in range(6)], []
    monkeypatch.setattr(K, "rows", lambda cores, real=K.rows: made.append(1) or real(cores))
    shared, alone = merge.expander(top, (2, 3)), merge.expander(top, (2, 3), 10)
    assert all(np.allclose(shared(s), x) for s, x in enumerate(want)) and len(made) == 1
    assert all(np.allclose(alone(s), x) for s, x in enumerate(want)) and len(made) == 7


def test_tasks_are_dealt_evenly(spark):
    """Partitions hold as many tasks' rows as others or one more; hashes left some empty and gave others several."""
    kind = grids.ParticleSet("x", 64, 16, 90_000, 90_000, "none", ())
    jobs = spark.range(kind.blocks * 4).selectExpr("id % 4 AS seg", "cast(id div 4 AS int) AS block")
    for each in (1, 4):
        own = compress.dealt(jobs, kind, 1, each)._df.groupBy(F.spark_partition_id()).count().collect()
        sizes = [r["count"] for r in own]
        assert len(sizes) == -(-jobs.count() // each) and max(sizes) - min(sizes) <= 1


def test_pairs_are_rounded_by_their_trains(spark, sf):
    """q_error_bound makes no block cores of a pair, which would be mostly zeros."""
    inner = next(c for c in workloads.error_bound.__code__.co_consts if getattr(c, "co_name", "") == "pairwise")
    assert "stack_rounded" in inner.co_names and "recompress" not in inner.co_names


@pytest.mark.parametrize("how", ["stack", "concat"])
def test_few_cores_are_held_while_merging(how):
    """Rows merged as they come are those merged all at once, and most have left before the last has come; the last groups are short here."""
    rng = np.random.default_rng(5)
    parts = [dict(pack(K.decompose(rng.standard_normal(4 * 6 * 3), [4, 6, 3], 0.2)[0]), variable=v, level=0, seg=s, n_original=72, vmin=-3.0, vmax=3.0, fro2=72.0, err_abs=1.0, steps=4) for s in range(27) for v in "vw"]
    budget, here, most, got = Budget("fro", 0.5), 0, 0, []

    def come():
        nonlocal here, most
        for r in parts:
            here += 1
            most = max(most, here)
            yield r

    for r in merge.merge_along(come(), (2, 2, 3, 3), budget, how):
        here -= not r["level"]
        got.append(r)
    want = merge.merge_rows(parts, (2, 2, 3, 3), budget, how)
    key = lambda r: (r["variable"], r["level"], r["seg"])
    got, want = sorted(got, key=key), sorted(want, key=key)
    assert most <= 4 and len(got) == len(want)
    for a, b in zip(got, want):
        assert key(a) == key(b) and a["ranks"] == b["ranks"] and a["err_abs"] == b["err_abs"] and np.array_equal(K.expand(unpack(a)), K.expand(unpack(b)))


def test_trees_let_cores_go_as_they_are_merged(spark, sf, blocks, monkeypatch):
    """No tree over blocks gathers all its rows in a task before it merges them."""
    monkeypatch.setattr(merge, "merge_rows", None)
    assert workloads.tree(spark, sf, "sediment").count() == 312 and compare.tree_in_tasks(grids.sediment(spark, sf)[1], grids.sediment(spark, sf)[0], workloads.TENTH, fanin=())[1].count() == 160
