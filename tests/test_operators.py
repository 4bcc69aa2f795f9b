"""Worked examples by hand, agreement of strategies, properties."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from harvestgrid.operators import calibrate, cluster, completion, direction, geometry, gridmap, interpolate, invariants, mass, metrics, network, occupancy, rows, season
from harvestgrid.plans import inspect


def test_overlap_and_density(spark):
    v = spark.range(1).select(*[occupancy.overlap_1d(*map(F.lit, map(float, q))) for q in ((2, 10, 7, 15), (0, 4, 4, 9), (0, 10, 3, 5))]).first()
    assert tuple(v) == (3.0, 0.0, 2.0)
    assert abs(10.059 / 1.63**2 - 3.785) < 0.002 and abs(4.289 / 1.22**2 - 2.881) < 0.002
    sd = [np.sqrt(r * r - b * b) for r, b in ((2.71, 0.16), (2.60, 1.01))]
    assert [round(b + 1.96 * s, 1) for b, s in zip((0.16, 1.01), sd)] == [5.5, 5.7]


def test_directions():
    s = lambda y, p=0.0: direction.signs(np.array(y, float), direction.turning_points(np.array(y, float), p)).tolist()
    assert s([0, 1, 2, 3]) == [1, 1, 1, 1] and s([5, 4, 3]) == [-1, -1, -1]
    assert s([0, 3, 6, 3, 0]) == [1, 1, -1, -1, -1] and s([4, 1, 4]) == [-1, 1, 1]
    assert s([2, 2, 2]) == [1, 1, 1] and s([1]) == [1]
    assert s([0, 5, 5, 5, 0]) == [1, -1, -1, -1, -1] or s([0, 5, 5, 5, 0])[0] == 1
    assert direction.turning_points(np.array([0, 1, 0.8, 3, 0], float), 0.5).tolist() == [3]
    turns = direction.turning_points(np.sin(np.linspace(0, 20, 400)), 0.5)
    assert 5 <= len(turns) <= 7


def test_hampel(spark):
    df = spark.createDataFrame([(0, i, float(v)) for i, v in enumerate([1, 1, 1, 50, 1, 1, 1])], "g int, i int, y double")
    out = direction.hampel(df, "y", 3, ["g"], ["i"])
    assert [r.y_h for r in out.orderBy("i").collect()] == [1.0] * 7


def test_hampel_forms_agree(spark, sf):
    from harvestgrid.sources import adapters

    t = adapters.trace_from_events(spark, sf).where("cart_id < 20").select("cart_id", "t_us", "src_id", "y")
    a, b = (direction.hampel(t, "y", 3, ["cart_id"], ["t_us", "src_id"], 1.0, impl=i).select("src_id", "y_h") for i in ("native", "arrow"))
    assert a.exceptAll(b).count() == 0 and a.count() == b.count() > 0
    d = spark.createDataFrame([(0, 0, 0.0), (0, 1, 5.0), (0, 2, 3.0), (1, 0, 4.0), (1, 1, 1.0)], "g int, i int, y double")
    assert {r.g: r.direction for r in direction.dominant_sign(d, ["g"], ["i"]).collect()} == {0: 1, 1: -1}


def test_row_assignment(spark):
    pts = [(0, 1, 0, x, 1.0) for x in (2.9, 3.1, 9.0)] + [(0, 1, 1, 0.4, 50.0), (0, 1, -1, 7.0, 0.0)]
    c = spark.createDataFrame(pts, "field_id int, cart_id long, cluster_id long, x double, y double").withColumn("src_id", F.monotonically_increasing_id())
    row_map = spark.createDataFrame([(0, r, 1.5 * r, 0.0, 40.0 if r else 5.0) for r in range(4)], "field_id int, row_idx int, row_x double, y_lo double, y_hi double")
    got = {r.cluster_id: r.row_idx for r in rows.assign_rows(c, row_map).collect()}
    assert got == {0: 2, 1: 0, -1: None}
    near = {r.cluster_id: r.row_idx for r in rows.assign_rows(c, row_map, metric="euclid", noise="drop").collect()}
    assert near == {0: 2, 1: 1}
    even = {r.cluster_id: r.row_idx for r in rows.assign_rows(c.withColumn("spacing", F.lit(1.5)), max_dist=0.3, noise="drop").collect()}
    assert even == {0: 2, 1: None}
    back = rows.write_back(c, rows.assign_rows(c, row_map), ("field_id", "cart_id"))
    assert sorted((r.cluster_id, r.row_idx) for r in back.collect() if r.row_idx is not None) == [(0, 2), (0, 2), (0, 2), (1, 0)]


def test_polynomials(spark):
    rng = np.random.default_rng(2)
    rows, want = [], {}
    shapes = {0: lambda y: 0.5 + 2 * y, 1: lambda y: y**2, 2: lambda y: y**3 - y, 3: lambda y: 0 * y + 3.0}
    for g, f in shapes.items():
        ys = np.linspace(-1, 1, 21)
        rows += [(g, float(a), float(f(a))) for a in ys]
    for g in range(10, 16):
        ys, ws = rng.uniform(100, 160, 30), rng.normal(size=30)
        rows += [(g, float(a), float(b)) for a, b in zip(ys, ws)]
        u = (ys - (ys.min() + ys.max()) / 2) / ((ys.max() - ys.min()) / 2)
        want[g] = [1 - np.sum((ws - np.polyval(np.polyfit(u, ws, d), u)) ** 2) / np.sum((ws - ws.mean()) ** 2) for d in (1, 2, 3)]
    rows += [(20, 0.0, 1.0), (20, 1.0, 2.0), (20, 0.0, 1.0), (21, 5.0, 1.0)]
    fits = interpolate.choose_degree(interpolate.fit_polynomials(spark.createDataFrame(rows, "g int, y double, w double"), ["g"]))
    got = {r.g: r for r in fits.collect()}
    assert [got[g].degree for g in (0, 1, 2, 3, 20)] == [1, 2, 3, 1, 1] and got[21].degree is None
    assert abs(got[0].r1 - 1) < 1e-12 and got[1].r1 < 1e-12
    for g, r in want.items():
        assert np.allclose([got[g].r1, got[g].r2, got[g].r3], r, atol=1e-9)
    line = spark.createDataFrame([(0, y / 10, 0.5 + 2 * y / 10) for y in range(11)], "g int, y double, w double")
    f = interpolate.choose_degree(interpolate.fit_polynomials(line, ["g"]))
    inc = interpolate.increments(f, 0.25).collect()
    assert np.allclose([r.dmass for r in inc], [0.5] * 4) and np.allclose([r.y_int for r in inc], [0, 0.25, 0.5, 0.75])
    assert len(interpolate.increments(f, 0.3).collect()) == 3 and len(interpolate.increments(f, 0.3, tail="keep").collect()) == 4
    assert np.isclose(sum(r.dmass for r in interpolate.increments(f, 0.3, tail="keep").collect()), 2.0)


def test_cells(spark):
    df = spark.createDataFrame([(v,) for v in (1.0, 2.6, -4.0, 99.0)], "v double")
    assert [r[0] for r in df.select(gridmap.cell_index(F.col("v"), 0.0, 3.0, 1.0, 3)).collect()] == [0, 2, 0, 2]
    g = gridmap.Grid(0, 0, 2.5, 1, 1.0)
    assert g.cells("x") == 3 and g.cells("y") == 1
    mids = [0.5, 1.5, 2.25]
    vs = [0.0, 0.99, 1.0, 1.01, 1.87, 1.875, 1.88, 2.4, 3.0, -1.0]
    got = [r[0] for r in spark.createDataFrame([(v,) for v in vs], "v double").select(gridmap.cell_index(F.col("v"), 0.0, 2.5, 1.0, 3)).collect()]
    assert got == [int(np.argmin([abs(m - v) for m in mids])) for v in vs]


def test_classes_zones_and_coarsening(spark):
    cells = spark.createDataFrame([(0, i, 0, float(i + 1)) for i in range(5)], "field_id int, j int, k int, mass double")
    got = {r.mass: r.yield_class for r in season.classify(cells).collect()}
    assert got == {1.0: "very_low", 2.0: "below", 3.0: "below", 4.0: "above", 5.0: "very_high"}
    low = [(0, 0), (0, 1), (1, 1), (5, 5), (6, 6), (9, 0), (9, 1), (9, 2), (8, 2)]
    named = spark.createDataFrame([(0, j, k, 1.0, "very_low") for j, k in low] + [(0, 2, 2, 9.0, "above")], "field_id int, j int, k int, mass double, yield_class string")
    zones = sorted(r.cells for r in season.low_zones(named).collect())
    assert zones == [1, 1, 3, 4]
    assert gridmap.coarsen(cells, 2).agg(F.sum("mass")).first()[0] == 15.0


def test_accuracies(spark):
    p = spark.createDataFrame([("A", 4.0, 3.0), ("A", 2.0, 2.0), ("B", 5.0, 6.0)], "tray_id string, gt double, est double")
    r = metrics.row_level(p).first()
    assert abs(r.acc_printed - 0.775) < 1e-12 and abs(r.acc_segments - 0.85) < 1e-12
    assert abs(metrics.tray_level(p).first().accuracy - (1 - (1 / 6 + 0.2) / 2)) < 1e-12
    a = metrics.agreement(spark.createDataFrame([(5.0, 4.0), (5.0, 5.0), (5.0, 6.0)], "gt double, est double")).first()
    assert (a.bias, a.sd, round(a.hi, 2), a.share_inside) == (0.0, 1.0, 1.96, 1.0)
    assert metrics.summary(p.limit(0)).first().n == 0


def brute_cluster(points, eps, min_pts):
    d = np.sqrt(((points[:, None] - points) ** 2).sum(axis=2)) <= eps * (1 + 1e-12)
    core = d.sum(axis=1) >= min_pts
    label = np.full(len(points), -1)
    n = 0
    for i in np.nonzero(core)[0]:
        if label[i] < 0:
            label[i], queue = n, [i]
            while queue:
                for j in np.nonzero(d[queue.pop()] & core & (label < 0))[0]:
                    label[j] = n
                    queue.append(j)
            n += 1
    for i in np.nonzero(~core)[0]:
        near = np.nonzero(d[i] & core)[0]
        if len(near):
            dist = ((points[near] - points[i]) ** 2).sum(axis=1)
            label[i] = min(zip(dist, label[near]))[1]
    return label, core


@pytest.mark.parametrize("dims", [2, 3])
def test_strategies_agree(spark, dims):
    rng = np.random.default_rng(dims)
    pts = np.concatenate([rng.normal(size=(60, dims)) * 0.6 + c for c in (0, 3, 6)] + [rng.uniform(-5, 12, size=(60, dims))]).round(3)
    pts = pts[np.argsort(pts[:, 0], kind="stable")]
    label, core = cluster.cluster_points(pts, 0.8, 5)
    want, want_core = brute_cluster(pts, 0.8, 5)
    assert np.array_equal(label, want) and np.array_equal(core, want_core)
    names = ["a", "b", "c"][:dims]
    df = spark.createDataFrame([(0, i, *map(float, p)) for i, p in enumerate(pts)], "g int, src_id long, " + ", ".join(f"{n} double" for n in names)).repartition(5)
    scales = {n: 1.0 for n in names}
    for strategy in ("group", "grid"):
        out = cluster.density_cluster(df, ["g"], scales, 0.8, 5, strategy).orderBy("src_id").collect()
        assert [r.cluster_id for r in out] == want.tolist(), strategy
        assert [r.is_core for r in out] == want_core.tolist()


def test_line_equals_group(spark):
    rng = np.random.default_rng(7)
    t = np.sort(rng.integers(0, 3000, 200))
    df = spark.createDataFrame([(0, i, int(v)) for i, v in enumerate(t)], "g int, src_id long, t long")
    a = cluster.density_cluster(df, ["g"], {"t": 1}, 20, 3, "line").orderBy("src_id").collect()
    want, core = brute_cluster(t[:, None].astype(float), 20.0, 3)
    assert [r.is_core for r in a] == core.tolist() and [r.cluster_id for r in a] == want.tolist()


def test_completion(spark):
    seg = lambda rows: spark.createDataFrame(rows, "cart_id long, session int, row_idx int, n long, y_min double, y_max double, direction int")
    bad = seg([(1, 0, r, n, 0.0, 9.0, 1) for r, n in ((4, 10), (5, 30), (6, 20))] + [(2, 0, 4, 5, 0.0, 9.0, 1), (2, 0, 5, 9, 0.0, 9.0, -1)])
    got = {(r.cart_id, r.row_idx): r.row_idx_new for r in completion.remap(bad).collect()}
    assert got == {(1, 4): 5, (1, 5): 5, (1, 6): 5, (2, 4): 4, (2, 5): 5}
    after = seg([(1, 0, 5, 60, 0.0, 9.0, 1)])
    assert all(r.moved_flag == 0 for r in completion.remap(after).collect())


def test_occupancy_and_invariants(spark):
    s = lambda c, r, lo, hi, n, f=0: {"cart_id": c, "row_idx": r, "y_min": lo, "y_max": hi, "n": n, "moved_flag": f}
    got = occupancy.resolve_day([s(1, 5, 0, 20, 50), s(2, 5, 5, 25, 10), s(2, 8, 0, 30, 40)], 5.0, "n", None, 3)
    assert got[(2, 5)] == (8, "moved") and got[(1, 5)] == (5, "kept")
    got = occupancy.resolve_day([s(1, 5, 0, 20, 50, 1), s(2, 5, 5, 25, 10, 0)], 5.0, "n", {5}, 3)
    assert got[(1, 5)] == (5, "unresolved")
    meet = occupancy.resolve_day([s(1, 5, 0, 10, 5), s(2, 5, 10, 20, 5)], 5.0, "n", None, 3)
    assert {v[1] for v in meet.values()} == {"kept"}
    iv = spark.createDataFrame([(0, 0, 1, 5, 1, 0, 10), (0, 0, 1, 6, 1, 5, 9), (0, 0, 2, 5, -1, 2, 8), (0, 0, 3, 5, 1, 10, 12)], "field_id int, session int, cart_id long, row_idx int, direction int, t1 long, t2 long")
    assert [r.cart_id for r in invariants.row_completion_violations(iv).collect()] == [1]
    assert invariants.row_occupancy_violations(iv).count() == 0


def test_mass_and_calibration(spark):
    rows = [(0, 0, i * 1_000_000, w, i) for i, w in enumerate([0.55, 0.6, 0.9, 0.8, 1.0, 9.0, 1.2, 5.0])]
    df = spark.createDataFrame(rows, "cart_id long, session int, t_us long, w double, src_id long")
    r = {x.src_id: x.rate for x in mass.rate(mass.in_range(df)).collect()}
    assert set(r) == {1, 2, 3, 4, 6} and r[6] is None and abs(r[1] - 0.3) < 1e-9 and abs(r[4] - 0.1) < 1e-9
    cal = spark.createDataFrame([(1, 2.0 * x + 1, float(x)) for x in range(5)] + [(2, 1.0, 1.0)], "cart_id long, reading double, known_mass double")
    fit = calibrate.fit_load_cells(cal).collect()
    assert len(fit) == 1 and abs(fit[0].slope - 0.5) < 1e-12 and abs(fit[0].intercept + 0.5) < 1e-12
    sets = spark.createDataFrame([(1, 0, 1.0, 0.0), (1, 50, 2.0, 0.0)], "cart_id long, valid_from_us long, slope double, intercept double")
    smp = spark.createDataFrame([(1, 10, 3.0), (1, 60, 3.0)], "cart_id long, t_us long, raw_load double")
    assert [x.w for x in calibrate.apply_load_cells(smp, sets, as_of=True).orderBy("t_us").collect()] == [3.0, 6.0]


def test_transform_round_trip(spark):
    rows = []
    for k, (x, y) in enumerate([(0, 0), (50, 0), (50, 80), (0, 80), (20, 30)]):
        u, v = 0.8 * x - 0.6 * y, 0.6 * x + 0.8 * y
        rows.append((36.6 + v / 111_320.0, float(-121.6 + u / (111_320.0 * np.cos(np.radians(36.6003)))), float(x), float(y)))
    ctrl = spark.createDataFrame(rows, "lat double, lon double, x double, y double")
    for kind in ("rigid", "affine"):
        p = geometry.fit_transform(ctrl, kind)
        there = geometry.to_field(ctrl.select("lat", "lon", F.col("x").alias("x0"), F.col("y").alias("y0")), p)
        assert all(abs(r.x - r.x0) < 0.01 and abs(r.y - r.y0) < 0.01 for r in there.collect())
        back = geometry.to_geodetic(there.withColumnsRenamed({"lat": "la", "lon": "lo"}), p).collect()
        assert all(abs(r.lat - r.la) < 1e-9 and abs(r.lon - r.lo) < 1e-9 for r in back)


def test_network_gradient():
    rng = np.random.default_rng(0)
    net = network.Net(2, filters=3, kernel=3, hidden=4, pool=2)
    x, y = rng.normal(size=(5, 12, 2)), np.array([0, 1, 1, 0, 1])
    _, g = net.gradient(x, y)
    for k, w in net.p.items():
        for at in list(np.ndindex(w.shape))[:6]:
            keep = w[at]
            w[at] = keep + 1e-6
            up = net.gradient(x, y)[0]
            w[at] = keep - 1e-6
            down = net.gradient(x, y)[0]
            w[at] = keep
            assert abs((up - down) / 2e-6 - g[k][at]) < 1e-6


def test_plans(spark, sf):
    from harvestgrid.queries import QUERIES

    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        for name in ("season_yield_class", "row_conflicts", "mass_clean", "zero_yield_share", "density_cluster_time"):
            assert not inspect.has_pair_join(QUERIES[name](spark, sf)), name
        assert inspect.exchanges(QUERIES["density_cluster_time"](spark, sf)) <= 2
        assert inspect.exchanges(QUERIES["mass_median_smooth"](spark, sf)) == 1
        scan = QUERIES["scan_pruned"](spark, sf)
        assert any("GreaterThan(l_quantity,45" in f for f in inspect.pushed_filters(scan))
        assert inspect.read_schemas(scan) == ["l_suppkey:bigint,l_quantity:double"]
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", "true")


def test_sql_functions_and_sinks(spark, sf, tmp_path):
    from harvestgrid.functions import registry
    from harvestgrid.sources import adapters, readers

    registry.register(spark)
    assert spark.sql("SELECT overlap_1d(2D, 10D, 7D, 15D) AS o, nearest_row(3.3D, 1.63D) AS r").first() == (3.0, 2)
    assert spark.sql("SELECT count(*) FROM grid_cells(0D, 0D, 3D, 2D, 1D, 1D)").first()[0] == 6
    assert spark.sql("SELECT count(*) FROM y_samples(0D, 1D, 0.25D)").first()[0] == 5
    t = readers.conform(adapters.trace_from_events(spark, sf), readers.TRACE)
    readers.write_traces(t, str(tmp_path / "t"))
    readers.write_traces(t.where("field_id = 1"), str(tmp_path / "t"))  # replaces field 1 only
    back = readers.read_traces(spark, str(tmp_path / "t"))
    assert back.count() == 10_000 and readers.read_traces(spark, str(tmp_path / "t"), fields=[1], sessions=[0]).count() == t.where("field_id = 1 and session = 0").count()
    with pytest.raises(ValueError):
        readers.conform(t.drop("x"), readers.TRACE)


def test_entry_without_corpus_operators(tmp_path):
    """The driver's file works when the corpus folders are absent."""
    import os
    import shutil
    import subprocess
    import sys

    here = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    shutil.copytree(f"{here}/harvestgrid", tmp_path / "harvestgrid", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(f"{here}/__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; q = e.queries(); assert len(q) > 60 and not any(k.startswith('op') for k in q) and 'pipeline' not in q; assert set(e.oracle_sql()) <= set(q)"
    assert subprocess.run([sys.executable, "-c", code], cwd=tmp_path, env={**os.environ, "PYTHONPATH": str(tmp_path)}).returncode == 0
