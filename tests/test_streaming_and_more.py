import pytest
from pyspark.sql import functions as F

from harvestgrid import simulate
from harvestgrid.operators import activity, direction, network, trays
from harvestgrid.plans import cost
from harvestgrid.sources import adapters
from harvestgrid.streaming import jobs


def test_stateful_trays_equal_batch(spark):
    sf = "/root/testdata/sf0.001"
    q = jobs.stateful_trays(jobs.source(spark, sf), 1.0, "3650 days").writeStream.outputMode("append").format("memory").queryName("closed_trays").trigger(availableNow=True).start()
    q.awaitTermination()
    got = {(r.cart_id, r.tray_no): (r.n, round(r.mass, 6)) for r in spark.table("closed_trays").collect()}
    t = trays.by_mass_reset(adapters.trace_from_events(spark, sf), 1.0)
    batch = t.groupBy("cart_id", "tray_id").agg(F.count(F.lit(1)).alias("n"), F.sum("w").alias("mass")).collect()
    last = {}
    for r in batch:
        last[r.cart_id] = max(last.get(r.cart_id, 0), r.tray_id)
    assert got == {(r.cart_id, r.tray_id): (r.n, round(r.mass, 6)) for r in batch if r.tray_id < last[r.cart_id]}


def test_deduplicated_and_upsert(spark, tmp_path):
    events = jobs.source(spark, "/root/testdata/sf0.001")
    q = jobs.deduplicated(events).writeStream.outputMode("append").format("memory").queryName("dedup_events").trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.table("dedup_events").count() == 1000
    from harvestgrid.plans.shared import keep

    keep(spark.range(1))  # sets the checkpoint folder
    sink = jobs.upsert_daily_map(str(tmp_path / "map"))
    one = spark.createDataFrame([(0, 1, 2, 3, 4.0)], "field_id int, day int, j int, k int, mass double")
    for batch in (0, 1, 1):  # a repeated batch adds nothing
        sink(one, batch)
    assert spark.read.parquet(str(tmp_path / "map")).agg(F.sum("mass")).first()[0] == 8.0


def test_annotate(spark):
    trace = spark.createDataFrame([(1, t, t) for t in (5, 10, 15, 20, 25)], "cart_id long, t_us long, src_id long")
    states = spark.createDataFrame([(1, "picking", 10, 20), (1, "transport", 20, 24)], "cart_id long, state string, t_start_us long, t_end_us long")
    got = [(r.t_us, r.state, r.label) for r in activity.annotate(trace, states).orderBy("t_us").collect()]
    assert got == [(5, None, "NoPick"), (10, "picking", "Pick"), (15, "picking", "Pick"), (20, "transport", "NoPick"), (25, None, "NoPick")]


def test_windows_with_stride(spark):
    t = spark.createDataFrame([(1, i, i, float(i), "Pick" if i < 7 else "NoPick") for i in range(10)], "cart_id long, t_us long, src_id long, w double, label string")
    w = {r.win_no: ([s.w for s in r.sample], r.label) for r in activity.make_windows(t, 4, 2, ("w",)).collect()}
    assert w[0] == ([0.0, 1.0, 2.0, 3.0], "Pick") and w[1][0] == [2.0, 3.0, 4.0, 5.0] and w[3] == ([6.0, 7.0, 8.0, 9.0], "NoPick")


@pytest.fixture(scope="module")
def windows(spark):
    sim = simulate.traces(spark, carts=4, trays=3)
    return activity.make_windows(activity.with_velocity(sim).withColumn("label", F.col("truth_state")), 20, by=("session", "cart_id")).cache()


def test_feature_subsets(windows):
    rows = {r.subset: r for r in network.feature_ablation(windows, epochs=6).collect()}
    assert len(rows) == 7 and rows["mass+acceleration"].f1 >= 0.9
    assert all(0 <= v <= 1 for r in rows.values() for v in (r.precision, r.recall, r.f1, r.accuracy) if v is not None)


@pytest.mark.parametrize("kind", ["logistic", "forest", "boosted", "perceptron"])
def test_summary_baselines(windows, kind):
    m = network.SummaryBaseline(kind).fit(windows.where("pmod(cart_id, 2) = 0"))
    out = m.transform(windows.where("pmod(cart_id, 2) = 1"))
    assert out.agg(F.avg(((F.col("label") == "Pick").cast("int") == F.col("predicted")).cast("double"))).first()[0] > 0.8


def test_travel_on_simulated_rows(spark):
    sim = simulate.traces(spark, carts=2, trays=2).where("truth_state = 'Pick'").withColumn("row_idx", F.col("truth_row"))
    from harvestgrid.plans.pipeline import travel

    d = travel(sim).groupBy("cart_id", "truth_tray").agg(F.avg((F.col("direction") == F.when(F.col("truth_tray") % 2 == 0, 1).otherwise(-1)).cast("double")).alias("right"))
    assert all(r.right > 0.95 for r in d.collect())
    assert direction.simple_direction(sim, ["cart_id", "truth_tray"], ["t_us"]).count() == 4


def test_cost(spark):
    c = cost.measure(spark.range(100_000).groupBy((F.col("id") % 10).alias("k")).count())
    assert c["stages"] >= 2 and c["shuffle_records"] >= 10 and c["shuffle_bytes"] > 0 and c["wall_s"] > 0
