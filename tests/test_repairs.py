"""The chain's repairs on simulated faults: what they move, what they win, and which violations stay."""

import pytest
from pyspark.sql import functions as F

from harvestgrid import simulate
from harvestgrid.operators import gridmap
from harvestgrid.params import Params
from harvestgrid.plans import pipeline

FIELD = simulate.Field(rows=28)
GRID = gridmap.Grid(-FIELD.spacing / 2, 0.0, FIELD.spacing * 27.5, FIELD.length, FIELD.spacing)
PARAMS = Params(min_pts=4, scale_t=8.0, scale_y=4.0, scale_x=0.8)


def accuracy(stage, sim):
    t = stage.select("src_id", "row_idx").join(sim.select("src_id", "truth_row"), "src_id")
    return t.agg(F.avg((F.col("row_idx") == F.col("truth_row")).cast("double"))).first()[0]


@pytest.mark.parametrize("part,share", [(0.4, 0.25), (0.7, 0.12)])
def test_repairs_raise_row_accuracy(spark, part, share):
    """Positions one row off for less than half of a tray are mended by completion, for more by occupancy."""
    sim = simulate.traces(spark, FIELD, carts=4, trays=6, crew=True, burst_share=0.0, bias_share=share, bias_part=part, gap_share=0.02).cache()
    out = pipeline.run(sim, GRID, PARAMS, upto="occupancy")
    raw, mid, end = (accuracy(out[k], sim) for k in ("rows", "completion", "occupancy"))
    seen = {r.step: r for r in pipeline.effects(out, PARAMS).collect()}
    print(part, raw, mid, end, seen)
    assert raw < 0.95 and end >= 0.95
    if part < 0.5:
        assert mid >= 0.95 and seen["completion"].moved > 0
    else:
        assert mid < raw < end and seen["occupancy"].moved > 0 and seen["occupancy"].violations_after < seen["occupancy"].violations_before
    assert seen["completion"].violations_before > seen["completion"].violations_after == 0


def test_revisited_rows_are_legal(spark):
    """A row picked from the middle to one end and then to the other is one row; nothing moves."""
    sim = simulate.traces(spark, FIELD, carts=3, trays=4, crew=True, burst_share=0.0, revisit_share=1.0).cache()
    out = pipeline.run(sim, GRID, PARAMS, upto="occupancy")
    assert out["moves"].where("moved_flag = 1").count() == 0 and accuracy(out["occupancy"], sim) >= 0.99
    signs = {tuple(r.direction_sig) for r in out["segments"].collect()}
    assert signs == {(-1, 1)}
