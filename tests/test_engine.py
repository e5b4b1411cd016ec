"""Segments, merges, streams and tables against arrays built in one process."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from traincube.functions import kernels as K
from traincube.functions import shapes, sqlfns
from traincube.functions.budget import Budget
from traincube.operators import compare, compress, measures, merge, panels, trains
from traincube.plans.streams import train_stream
from traincube.sources import grids, tables
from traincube.sources.scratch import stored


def toy(spark, steps=10, entities=3, segment=4):
    rng = np.random.default_rng(3)
    rates = np.where(rng.random((steps, entities, 3)) < 0.4, rng.random((steps, entities, 3)), 0)
    rows = [(t, e, *map(float, rates[t, e])) for t in range(steps) for e in range(entities) if rates[t, e].any()]
    shape = grids.ParticleSet("toy", steps, segment, entities, 4, "none", (2, 2))
    return rates, shape, spark.createDataFrame(rows, "step long, entity long, c1 double, c2 double, c3 double")


@pytest.mark.parametrize("order", ["none", "first", "every", "hilbert_first"])
def test_segments_hold_rates_and_levels_with_padding(spark, order):
    rates, shape, cells = toy(spark)
    shape = grids.ParticleSet("toy", shape.steps, shape.segment, shape.entities, shape.padded, order, shape.fanin)
    got = {(r["variable"], r["seg"]): r.asDict(True) for r in compress.segments(cells, shape, Budget("fro", 1e-13)).collect()}
    assert len(got) == 6
    full = np.concatenate((rates, np.zeros((2, 3, 3))))
    levels = np.cumsum(full, 0)
    for s in range(3):
        for name, x in (("velocity", rates), ("position", levels[:10])):
            own = x[4 * s : 4 * s + 4]
            own = np.concatenate((own, np.repeat(own[-1:], 4 - len(own), 0)))
            y = K.expand(trains.unpack(got[name, s])).reshape(4, 4, 3, order="F")
            if order == "none":
                assert np.allclose(y[:, :3], own) and np.allclose(y[:, 3], own[:, 2])
            else:
                assert np.allclose(np.sort(y[:, :3].ravel()), np.sort(own.ravel()))
            assert got[name, s]["n_original"] == min(4, 10 - 4 * s) * 9


def test_tree_keeps_the_target_and_handles_a_short_group(spark):
    rates, shape, cells = toy(spark)
    first = compress.segments(cells, shape, Budget("nrmse", 0.1), share=1 / 3)
    got = [r.asDict(True) for r in merge.merge_tree(first, (2, 2), Budget("nrmse", 0.1)).collect()]
    assert sorted((r["variable"], r["level"], r["seg"]) for r in got if r["level"]) == [(v, k, s) for v in ("position", "velocity") for k, s in ((1, 0), (1, 1), (2, 0))]
    for r in got:
        assert r["err_abs"] <= 0.1 * (r["vmax"] - r["vmin"]) * np.sqrt(r["n_original"]) * (1 + 1e-9)


def test_partitions_do_not_matter(spark):
    _, shape, cells = toy(spark)
    a, b = ({(r["variable"], r["seg"]): r["ranks"] for r in compress.segments(cells.repartition(n), shape, Budget("nrmse", 0.05)).collect()} for n in (1, 7))
    assert a == b


def test_panels_equal_the_local_result(spark):
    modes = [2, 3, 4, 5]
    x = np.random.default_rng(5).standard_normal(120)
    cells = spark.createDataFrame([(i, float(v)) for i, v in enumerate(x)], "idx long, val double")
    near, lost = K.decompose(x, modes, 0.2)
    for inside, method in ((1, "qr"), (2, "gram"), (3, "qr")):
        far, _ = panels.decompose(cells, modes, 0.2, inside, method)
        assert K.ranks(far) == K.ranks(near) and np.allclose(K.expand(far), K.expand(near))
    for memory in (1 << 20, 48 * 6):
        far, off = compress.factorized(cells, modes, 0.2, memory)
        assert K.ranks(far) == K.ranks(near) and np.isclose(off, lost)
    for k in (1, 2):
        sigma = np.linalg.svd(x.reshape(int(np.prod(modes[:k])), -1, order="F"), compute_uv=False)
        assert panels.unfolding_rank(cells, modes, k, 0.4) == K.cut_rank(sigma, 0.4 * np.linalg.norm(x)) <= K.ranks(K.decompose(x, modes, 0.4)[0])[k] + 99
    with pytest.raises(ValueError, match="tolerance"):
        panels.decompose(cells, modes, 1e-9, 1, "gram")


def test_spectral_norm_and_costs(spark):
    m = np.random.default_rng(8).standard_normal((7, 5)) + 2
    cells = spark.createDataFrame([(i, j, float(m[i, j])) for i in range(7) for j in range(5)], "i long, j long, val double")
    assert measures.spectral_norm(cells, 8) == pytest.approx(np.linalg.norm(m, 2), rel=1e-6)
    cost = shapes.cost_model([4, 4, 4], 2)
    assert cost["dense"] == 64 and cost["train"] == 48 and cost["rounding"] == 96
    rows = spark.createDataFrame([(k, float(k)) for k in range(4)], "idx long, val double")
    other = rows.withColumn("val", F.col("val") + F.when(F.col("idx") == 0, 1.0).otherwise(0.0))
    r = measures.nrmse(rows, other, ["idx"]).first()
    assert (r["rmse"], r["nrmse"]) == (0.5, pytest.approx(0.5 / 3)) and r["rel_fro"] == pytest.approx(1 / 14**0.5)


@pytest.mark.parametrize("order", ["first", "every"])
def test_orders_and_measured_errors(spark, order):
    """Entities come back through the order table, and measured errors are those of the expanded arrays."""
    rates, shape, cells = toy(spark)
    shape = grids.ParticleSet("toy", 12, 4, 3, 4, order, (3,))
    cells = stored(cells)
    t = stored(compress.segments(cells, shape, Budget("nrmse", 0.2), share=0.5, keep_order=True))
    levels = merge.merge_tree(t.drop("places"), (3,), Budget("nrmse", 0.2))
    errors = {(r["variable"], r["level"], r["seg"]): r for r in compare.measured(levels, cells, shape, compress.orders(t)).collect()}
    full = np.concatenate((rates, np.zeros((2, 3, 3))))
    array = {"velocity": full, "position": np.cumsum(full, 0)}
    places = {r["seg"]: np.array(r["places"]) for r in compress.orders(t).collect()}
    off = dict.fromkeys([("velocity", 0), ("velocity", 1), ("position", 0), ("position", 1)], 0.0)
    for r in merge.parts(levels, (3,), 4).collect():
        y = K.expand(trains.unpack(r.asDict(True))).reshape(4, 4, 3, order="F")[:, :3]
        x = array[r["variable"]][4 * r["part"] : 4 * r["part"] + 4]
        off[r["variable"], r["level"]] += ((np.take_along_axis(x, np.broadcast_to(places[r["part"]], (4, 3))[:, :, None], 1) - y) ** 2).sum()
    for name, x in array.items():
        r = errors[name, 1, 0]
        assert (r["n"], r["vmin"], r["vmax"]) == (x.size, x.min(), pytest.approx(x.max())) and r["fro"] == pytest.approx(np.linalg.norm(x))
        assert r["nrmse"] == pytest.approx((off[name, 1] / x.size) ** 0.5 / (x.max() - x.min())) and r["nrmse"] <= 0.2
        assert sum(errors[name, 0, s]["rel_fro"] ** 2 * errors[name, 0, s]["fro"] ** 2 for s in range(3)) == pytest.approx(off[name, 0])
    exact = stored(compress.segments(cells, shape, Budget("fro", 1e-13), variables=("velocity",), keep_order=True))
    at = shapes.digits(F.col("idx"), [4, 4, 3])
    out = trains.expand(exact.drop("places")).select((F.col("seg") * 4 + at[0]).alias("step"), at[1].alias("place"), at[2].alias("comp"), "val")
    back = np.zeros((12, 3, 3))
    for r in compress.restore_identity(out, compress.orders(exact), 4).collect():
        back[r["step"], r["entity"], r["comp"]] = r["val"]
    assert np.allclose(back, full)


def test_rank_cap_and_report(spark):
    _, shape, cells = toy(spark)
    free, capped = (trains.numel(compress.segments(cells, shape, Budget("nrmse", 1e-6), max_rank=k)).collect() for k in (None, 1))
    assert max(max(r["ranks"]) for r in capped) == 1 and any(r["nrmse"] > 1e-6 for r in capped) and all(r["nrmse"] <= 1e-6 for r in free)
    out = measures.report(trains.numel(compress.segments(cells, shape, Budget("nrmse", 0.1))), "toy", 100)
    text = measures.to_markdown(out.orderBy("variable"))
    assert len(text.split("\n")) == 4 and out.where("ratio_with_order >= ratio_pooled or ratio_pooled > ratio_ceiling").count() == 0


@pytest.mark.parametrize("fmt", ["parquet", "orc", "csv", "json"])
def test_snapshots_in_files(spark, tmp_path, fmt):
    _, _, cells = toy(spark)
    path = str(tmp_path / fmt)
    (cells.write.option("header", True) if fmt == "csv" else cells.write).format(fmt).save(path)
    back = tables.read_snapshots(spark, path, fmt, "step long, entity long, c1 double, c2 double, c3 double")
    assert sorted(map(tuple, back.collect())) == sorted(map(tuple, cells.collect()))


def test_stream_equals_batch_and_replay_changes_nothing(spark, sf):
    own = train_stream(spark, sf)
    shape, cells = grids.vehicle(spark, sf)
    batch = {(r["variable"], r["seg"]): (r["ranks"], round(r["fro2"], 6)) for r in compress.segments(cells, shape, Budget("nrmse", 0.1), share=0.2).collect()}
    stream = {(r["variable"], r["seg"]): (r["ranks"], round(r["fro2"], 6)) for r in own.trains(0).collect()}
    assert spark.read.parquet(f"{own.folder}/trains0").select("b").distinct().count() > 2  # several batches closed segments
    assert spark.read.parquet(f"{own.folder}/late").count() == 0
    assert stream == batch
    own.finish()
    assert own.trains(0).count() == len(batch)


def test_late_cells_are_set_aside(spark):
    _, shape, cells = toy(spark)
    from traincube.streaming.segments import TrainStream

    own = TrainStream(spark, shape, ([0.0] * 3, [10.0] * 3), Budget("nrmse", 0.1), lateness=0)
    own.fold(cells.where("step < 8"), 0)
    assert own.trains(0).select("seg").distinct().count() == 2 and own.trains(1).count() == 2
    own.fold(cells.where("step >= 8").union(cells.limit(1)), 1)
    own.finish()
    assert spark.read.parquet(f"{own.folder}/late").count() == 1 and own.trains(0).select("seg").distinct().count() == 3
    assert own.trains(2).count() == 0  # three segments make one pair and one that waits


def test_tables_and_sql(spark, tmp_path):
    _, shape, cells = toy(spark)
    t = compress.segments(cells, shape, Budget("fro", 1e-12))
    tables.write_trains(t, str(tmp_path / "t"))
    back = tables.read_trains(spark, str(tmp_path / "t"))
    assert back.count() == 6 and trains.valid(back.where("level = 0")).count() == 6
    sqlfns.register(spark)
    back.createOrReplaceTempView("trains")
    assert spark.sql("SELECT count(*), count(DISTINCT idx) FROM trains, LATERAL tt_expand(cores) WHERE variable = 'velocity' AND seg = 0").first()[:] == (48, 48)
    assert spark.sql("SELECT long_index(array(1L, 2L, 3L), array(3L, 4L, 5L)) AS i").first()["i"] == 1 + 3 * 2 + 12 * 3
    assert spark.sql("SELECT max(abs(tt_ratio(n, cores) * tt_numel(cores) - n)) AS off FROM trains").first()["off"] < 1e-9
    row = spark.sql("SELECT max(abs(tt_norm(cores) - sqrt(fro2))) AS off, min(tt_numel(cores)) AS n FROM trains").first()
    assert row["off"] < 1e-9 and row["n"] > 0
    assert spark.sql("SELECT morton3(1, 0, 0) AS x, morton3(0, 1, 2) AS y, morton2(1, 1) AS z").first() == (4, 10, 3)
    bad = cells.withColumn("c1", F.lit(float("nan")))
    with pytest.raises(Exception, match="finite"):
        tables.checked(bad).collect()
    assert tables.checked(bad, on_missing="zero").agg(F.sum("c1")).first()[0] == 0


def test_warm_up_steps_are_dropped(spark, sf):
    _, all_ = grids.vehicle(spark, sf, minutes=28, steps=1533)
    shape, kept = grids.vehicle(spark, sf, minutes=28, steps=1440, drop_first=93)
    want = all_.where("step >= 93").agg(F.round(F.sum("c1"), 4), F.count("*"), F.max("step") - 93).first()
    assert kept.agg(F.round(F.sum("c1"), 4), F.count("*"), F.max("step")).first() == want and shape.steps == 1440


def test_sediment_has_every_row(spark, sf):
    """No part and no day is left out of the grid."""
    kind, cells = grids.sediment(spark, sf)
    assert cells.agg(F.sum("c3")).first()[0] == spark.read.parquet(f"{sf}/lineitem.parquet").count()
    assert kind.segments == np.prod(kind.fanin) and cells.agg(F.max("entity")).first()[0] < kind.entities <= kind.padded
