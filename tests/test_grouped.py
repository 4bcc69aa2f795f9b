"""Sequential steps over runs of sorted rows: any batch size, null keys, and no Python call per group."""

import numpy as np
import pytest
from pyspark.sql import types as T

from harvestgrid.operators import cluster, direction
from harvestgrid.operators.grouped import add_columns

ADDED = T.StructType().add("before", T.DoubleType()).add("size", T.IntegerType())


def running():
    """Made here, as workers can't import a test module."""
    return lambda v: (np.concatenate([[0.0], np.cumsum(v)[:-1]]), np.full(len(v), len(v)))


@pytest.mark.parametrize("batch", [1, 2, 3, 7, 10_000])
def test_groups_across_batches(spark, batch):
    rng = np.random.default_rng(3)
    rows = [(None if k == 3 else k, None if k % 5 == 0 else "s%d" % (k % 2), i, float(rng.integers(0, 9))) for k in range(40) for i in range(int(rng.integers(1, 9)))]
    df = spark.createDataFrame(rows, "k long, s string, i int, v double").repartition(3)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(batch))
    try:
        got = {(r.k, r.s, r.i): (r.before, r.size) for r in add_columns(df, ["k", "s"], ["i"], ["v"], ADDED, running()).collect()}
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    want = {}
    for k, s, i, _ in rows:
        mine = sorted(r for r in rows if r[:2] == (k, s)) if None not in (k, s) else sorted((r for r in rows if r[:2] == (k, s)), key=lambda r: r[2])
        want[k, s, i] = (sum(r[3] for r in mine if r[2] < i), len(mine))
    assert got == want


def test_empty_and_replaced_column(spark):
    df = spark.createDataFrame([(1, 0, 2.0, 9.0)], "k long, i int, v double, before double")
    assert add_columns(df.limit(0), ["k"], ["i"], ["v"], ADDED, running()).count() == 0
    assert [tuple(r) for r in add_columns(df, ["k"], ["i"], ["v"], ADDED, running()).collect()] == [(1, 0, 2.0, 0.0, 1)]


def test_directions_need_no_call_per_group(spark):
    df = spark.createDataFrame([(k, i, float(i if k % 2 else -i)) for k in range(50) for i in range(4)], "k long, i int, y double")
    for out in (direction.travel_direction(df, ["k"], ["i"], prominence=0.5, distance=1), direction.filtered_direction(df, ["k"], ["i"], half_window=1, distance=1)):
        assert "FlatMapGroupsInPandas" not in out._jdf.queryExecution().executedPlan().toString()
        assert {(r.k % 2, r.direction) for r in out.collect()} == {(0, -1), (1, 1)}


def test_clusters_need_no_call_per_group(spark):
    rng = np.random.default_rng(5)
    rows = [(int(g), i, float(x), float(y)) for g in range(30) for i, (x, y) in enumerate(rng.random((int(rng.integers(1, 90)), 2)) * 6)]
    df = spark.createDataFrame(rows, "g long, src_id long, x double, y double").repartition(4)
    out = cluster.group(df, ["g"], {"x": 1.0, "y": 1.0}, 1.0, 4)
    assert "FlatMapGroupsInPandas" not in out._jdf.queryExecution().executedPlan().toString()
    got = {(r.g, r.src_id): (r.is_core, r.cluster_id) for r in out.collect()}
    for g in range(30):
        mine = sorted((r for r in rows if r[0] == g), key=lambda r: (r[2], r[1]))
        label, core = cluster.cluster_points(np.array([r[2:] for r in mine]), 1.0, 4)
        assert [got[g, r[1]] for r in mine] == list(zip(core.tolist(), label.tolist()))


def test_few_points_pair_as_by_cells():
    rng = np.random.default_rng(6)
    for d in (1, 2, 3, 4):
        points = rng.random((60, d)) * 3
        pairs = [sorted(zip(*(v.tolist() for v in near(points, 0.7)))) for near in (cluster._near_all, cluster._near_cells)]
        assert len(pairs[0]) > 60 and pairs[0] == pairs[1]
