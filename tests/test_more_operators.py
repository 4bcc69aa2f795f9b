"""Operators that no workload query reaches: gates, interpolation between samples, sampling, aggregate functions, movement patterns."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from harvestgrid.functions import registry
from harvestgrid.operators import activity, baselines, direction, geometry, network, occupancy
from harvestgrid.queries import QUERIES


def test_fix_gate(spark):
    rows = [(1, 0, t, f) for t, f in ((1, False), (2, True), (3, False), (4, True))] + [(2, 0, 1, False)]
    got = geometry.require_fix(spark.createDataFrame(rows, "cart_id long, session int, t_us long, has_fix boolean"))
    assert sorted((r.cart_id, r.t_us) for r in got.collect()) == [(1, 2), (1, 4)]


def test_linear_interpolation_keeps_mass(spark):
    rows = [(1, 0, 0.0, 1.0), (1, 1, 1.0, 1.5), (1, 2, 1.1, 1.5), (1, 3, 0.5, 2.5)]
    got = baselines.linear_interp(spark.createDataFrame(rows, "cart_id long, t long, y double, w double"), ["cart_id"], ["t"], step=0.25).collect()
    assert sum(r.dmass for r in got) == pytest.approx(1.5) and [r.y_int for r in got[:4]] == pytest.approx([0.0, 0.25, 0.5, 0.75])


@pytest.mark.parametrize(
    "y,want",
    [
        (np.linspace(30, 0, 61), (-1,)),  # (a) from the middle to the start
        (np.linspace(30, 60, 61), (1,)),  # (b) from the middle to the end
        (np.concatenate([np.linspace(30, 0, 61), np.linspace(30, 60, 61)]), (-1, 1)),  # (c) one side, a pause, the other
        (np.concatenate([np.linspace(30, 60, 61), np.linspace(30, 0, 61)]), (1, -1)),  # (d) the other way round
        (np.concatenate([np.linspace(0, 60, 121), np.linspace(60, 0, 121), np.linspace(0, 60, 121)]), (1, -1, 1)),
    ],
)
def test_movement_patterns(spark, y, want):
    rng = np.random.default_rng(1)
    noisy = y + rng.normal(size=len(y)) * 0.2
    noisy[len(y) // 3] += 40.0  # a jump that the filter has to remove
    df = spark.createDataFrame([(1, i, float(v)) for i, v in enumerate(noisy)], "g int, i int, y double")
    got = [r.direction for r in direction.filtered_direction(df, ["g"], ["i"], half_window=5, prominence=5.0, distance=10).orderBy("i").collect()]
    runs = tuple(v for k, v in enumerate(got) if k == 0 or v != got[k - 1])
    assert runs == want


def test_samples_of_windows_are_stable(spark):
    df = spark.createDataFrame([(i, "Pick" if i % 3 else "NoPick") for i in range(3000)], "win_no long, label string")
    a = {r.win_no for r in activity.sample_windows(df, {"Pick": 0.1, "NoPick": 1.0}).collect()}
    assert a == {r.win_no for r in activity.sample_windows(df.repartition(7), {"Pick": 0.1, "NoPick": 1.0}).collect()}
    assert len([i for i in a if i % 3 == 0]) == 1000 and 140 < len([i for i in a if i % 3]) < 260


def test_scores_of_windows_do_not_depend_on_batches(spark):
    """Short windows too get the same score in any company."""
    rng = np.random.default_rng(3)
    rows = [(i, [float(x) for x in rng.normal(size=n)], "Pick" if i % 2 else "NoPick") for i, n in enumerate([64] * 20 + [30, 12, 8, 7, 3])]
    df = spark.createDataFrame(rows, "vec_id long, sample array<double>, label string")
    model = network.ConvRecurrentClassifier(channels=1, epochs=1).fit(df)
    whole = {r.vec_id: r.score for r in model.transform(df.repartition(1)).collect()}
    alone = {r.vec_id: r.score for r in model.transform(df.repartition(25, "vec_id")).collect()}
    assert whole == pytest.approx(alone) and whole[24] == 0 and whole[22] > 0


def test_aggregate_functions(spark):
    registry.register(spark)
    rng = np.random.default_rng(4)
    rows = [(k % 3, float(y), float(y**2 + rng.normal() * 0.1)) for k, y in enumerate(rng.uniform(-1, 1, 90))]
    spark.createDataFrame(rows, "g int, y double, w double").createOrReplaceTempView("pts")
    got = {r.g: r for r in spark.sql("SELECT g, poly_score(y, w, 1) AS p, poly_score(y, w, 2) AS q FROM pts GROUP BY g").collect()}
    plain = {r.g: r.r for r in spark.sql("SELECT g, regr_r2(w, y) AS r FROM pts GROUP BY g").collect()}
    assert len(got) == 3 and all(r.p == pytest.approx(plain[g], abs=1e-9) and r.q > 0.8 > r.p for g, r in got.items())
    assert spark.sql("SELECT poly_value(2.0D, array(1.0D, 0.0D, 3.0D)) AS v").first().v == 13.0


def test_degree_three_against_numpy(spark, sf):
    from harvestgrid.queries import YEAR, _curves

    got = {(r.cart_id, r.year): r.m for r in QUERIES["ablate_degree3"](spark, sf).collect()}
    pdf = _curves(spark, sf, YEAR).toPandas()
    for key, g in list(pdf.groupby(list(YEAR)))[::40]:
        y, w = g["y"].to_numpy(), g["w"].to_numpy()
        c, h = (y.min() + y.max()) / 2, (y.max() - y.min()) / 2
        p = np.polyfit((y - c) / h, w, 3)
        at = y.min() + 0.3048 * np.arange(int(np.floor((y.max() - y.min()) / 0.3048 + 1e-9)) + 1)
        assert got[tuple(int(k) for k in key)] == pytest.approx(np.abs(np.diff(np.polyval(p, (at - c) / h))).sum(), abs=2e-3)


def test_moved_segments_go_back_where_they_came_from():
    seg = lambda cart, row, lo, hi, w, moved=0, came=None: {"cart_id": cart, "row_idx": row, "y_min": lo, "y_max": hi, "n": w, "moved_flag": moved, "second_idx": came}
    got = occupancy.resolve_day([seg(1, 5, 0, 50, 90, 1, 4), seg(2, 5, 0, 50, 10), seg(1, 9, 0, 50, 80)], 5.0, "n", None, 3)
    assert got[1, 5] == (4, "moved") and got[2, 5] == (5, "kept")  # not to row 9, where the cart was most otherwise


def test_chain_queries(spark):
    small = "/root/testdata/sf0.001"
    study = QUERIES["activity_feature_study"](spark, small).collect()
    assert len(study) == 7 and all(r.accuracy is not None for r in study)
    assert QUERIES["pipeline_season"](spark, small).count() > 0
