"""Accuracy on the simulator: targets and orderings, no replication of private data."""

import pytest
from pyspark.sql import functions as F

from harvestgrid import simulate
from harvestgrid.operators import activity, gridmap, metrics
from harvestgrid.operators.network import ConvRecurrentClassifier
from harvestgrid.params import Params
from harvestgrid.plans import pipeline

FIELD = simulate.Field(rows=24)
GRID = gridmap.Grid(-FIELD.spacing / 2, 0.0, FIELD.spacing * 23.5, FIELD.length, FIELD.spacing)
# Here each cart picks a block of neighbouring rows one after the other, which only the option tells from a violation.
PARAMS = Params(min_pts=4, scale_t=8.0, scale_y=4.0, scale_x=2.4, require_interleaving=True)


@pytest.fixture(scope="module")
def sim(spark):
    return simulate.traces(spark, FIELD, carts=4, trays=6).cache()


def row_accuracy(stage, sim):
    t = stage.select("src_id", "row_idx").join(sim.select("src_id", "truth_row"), "src_id")
    return t.agg(F.avg((F.col("row_idx") == F.col("truth_row")).cast("double"))).first()[0]


def tray_pairs(points, sim):
    est = points.groupBy("cart_id", "session", F.col("tray_id").alias("truth_tray")).agg(F.sum("dmass").alias("est"))
    return simulate.truth_trays(sim).join(est, ["cart_id", "session", "truth_tray"]).withColumn("tray", F.concat_ws("_", "cart_id", "session", "truth_tray"))


def test_rows_and_trays(sim):
    full = pipeline.run(sim, GRID, PARAMS)
    plain = pipeline.run(sim, GRID, PARAMS, upto="rows", skip=("cluster",))
    clustered = row_accuracy(full["rows"], sim)
    assert clustered >= 0.95 and clustered >= row_accuracy(plain["rows"], sim)
    assert row_accuracy(full["occupancy"], sim) >= 0.95
    pairs = tray_pairs(full["yield"], sim)
    assert pairs.count() == 24
    assert metrics.tray_level(pairs, "tray").first().accuracy >= 0.94
    counts = full["trays"].groupBy("cart_id").agg(F.count_distinct("tray_id").cast("double").alias("est")).withColumn("gt", F.lit(6.0))
    assert metrics.summary(counts).first().accuracy >= 0.94
    points, cells = full["yield"].agg(F.sum("dmass")).first()[0], full["daily"].agg(F.sum("mass")).first()[0]
    assert abs(points - cells) < 1e-6 * points  # mass is conserved on the map
    stair = tray_pairs(pipeline.run(sim, GRID, PARAMS, skip=("interpolation",))["yield"], sim)
    assert metrics.tray_level(pairs, "tray").first().accuracy >= metrics.tray_level(stair, "tray").first().accuracy


def test_activity_network(sim):
    labelled = activity.with_velocity(sim).withColumn("label", F.col("truth_state"))
    windows = activity.make_windows(labelled, 20, by=("session", "cart_id")).cache()
    net = ConvRecurrentClassifier(4, epochs=15, features=("w", "ax", "ay", "az")).fit(windows.where("pmod(cart_id, 2) = 0"))
    scored = net.transform(windows.where("pmod(cart_id, 2) = 1"))
    f1 = metrics.confusion(scored.withColumn("t", (F.col("label") == "Pick").cast("int")), F.col("t"), F.col("predicted")).first().f1
    assert f1 >= 0.97
    kept = activity.keep_picking(scored, sim.where("pmod(cart_id, 2) = 1"))
    assert kept.where("truth_state = 'Pick'").count() > 0.9 * kept.count()
