"""Picking activity: annotation, windows, labels, rules, summary baselines."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .states import pick_label


def with_velocity(trace: DataFrame, by=("cart_id", "session"), tie=("src_id",)) -> DataFrame:
    """+ vel: distance to the previous sample over time (m/s)."""
    w = Window.partitionBy(*by).orderBy("t_us", *tie)
    d = F.hypot(F.col("x") - F.lag("x").over(w), F.col("y") - F.lag("y").over(w))
    s = (F.col("t_us") - F.lag("t_us").over(w)) / 1e6
    return trace.withColumn("vel", F.coalesce(F.when(s > 0, d / s), F.lit(0.0)))


def annotate(trace: DataFrame, states: DataFrame, by=("cart_id",)) -> DataFrame:
    """+ state, label: the state whose interval holds the sample; as-of by union and carry-forward, so one sort and no range join."""
    marks = states.select(*by, F.col("t_start_us").alias("t_us"), F.col("state").alias("_state"), F.col("t_end_us").alias("_end"), F.lit(0).alias("_kind"))
    both = trace.drop("state").withColumn("_kind", F.lit(1)).unionByName(marks, allowMissingColumns=True)
    w = Window.partitionBy(*by).orderBy("t_us", "_kind").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    held = both.withColumn("_at", F.last(F.when(F.col("_kind") == 0, F.struct("_state", "_end")), ignorenulls=True).over(w)).where("_kind = 1")
    state = F.when(F.col("t_us") < F.col("_at._end"), F.col("_at._state"))
    return held.withColumn("state", state).withColumn("label", pick_label(F.coalesce("state", F.lit("idle")))).drop("_at", "_state", "_end", "_kind")


def numbered(trace: DataFrame, size: int, by=("cart_id",), tie=("src_id",)) -> DataFrame:
    """+ win_no, pos: tumbling windows of ``size`` samples."""
    w = Window.partitionBy(*by).orderBy("t_us", *tie)
    return trace.withColumn("_i", F.row_number().over(w) - 1).withColumns({"win_no": F.floor(F.col("_i") / size), "pos": (F.col("_i") % size).cast("int")}).drop("_i")


def make_windows(trace: DataFrame, size: int = 100, stride: int | None = None, features=("w", "ax", "ay", "az", "vel"), by=("cart_id",), label: str | None = "label", tie=("src_id",)) -> DataFrame:
    """by, win_no, sample (array of structs in time order), label by majority (tie: NoPick).

    With a stride below the size a sample enters every window that covers it.
    """
    stride = stride or size
    w = Window.partitionBy(*by).orderBy("t_us", *tie)
    rows = trace.withColumn("_i", (F.row_number().over(w) - 1).cast("long"))
    last = F.floor(F.col("_i") / stride)
    first = F.greatest(F.lit(0), F.ceil((F.col("_i") - size + 1) / stride))
    rows = rows.withColumn("win_no", F.explode(F.sequence(first.cast("long"), last.cast("long"))))
    got = F.transform(F.array_sort(F.collect_list(F.struct("_i", F.struct(*features).alias("s")))), lambda z: z["s"])
    aggs = [got.alias("sample"), F.collect_list("src_id").alias("src_ids")]
    if label:
        picks = F.count_if(F.col(label) == "Pick")
        aggs.append(F.when(picks * 2 > F.count(F.lit(1)), "Pick").otherwise("NoPick").alias("label"))
    return rows.groupBy(*by, "win_no").agg(*aggs)


def sample_windows(windows: DataFrame, shares: dict[str, float], by: str = "label", seed: int = 7) -> DataFrame:
    """A share of the windows of each class, to learn from: the same rows in every run and under every partitioning; classes not named go."""
    key = [c for c in windows.columns if c != by and not windows.schema[c].dataType.typeName() == "map"]
    draw = F.pmod(F.xxhash64(F.lit(seed), *key), F.lit(1 << 30)) / F.lit(float(1 << 30))
    chance = F.lit(0.0)
    for name, share in shares.items():
        chance = F.when(F.col(by) == name, F.lit(float(share))).otherwise(chance)
    return windows.where(draw < chance)


def window_summaries(trace: DataFrame, size: int, by=("cart_id",), w: str = "w") -> DataFrame:
    return numbered(trace, size, by).groupBy(*by, "win_no").agg(
        F.count(F.lit(1)).alias("n"), F.avg(w).alias("mean_w"), F.stddev_samp(w).alias("sd_w"), F.min_by(w, "pos").alias("first_w"), F.max_by(w, "pos").alias("last_w")
    )


def majority_label(trace: DataFrame, size: int, by=("cart_id",)) -> DataFrame:
    label = pick_label(F.col("state"))
    per = numbered(trace, size, by).groupBy(*by, "win_no").agg(F.avg((label == "Pick").cast("double")).alias("p"))
    return per.select(*by, "win_no", F.when(F.col("p") > 0.5, "Pick").otherwise("NoPick").alias("label"), F.greatest("p", 1 - F.col("p")).alias("share"))


def rising_mass_rule(trace: DataFrame, size: int, by=("cart_id",)) -> DataFrame:
    """A window is picking if its load rises: slope of mass over sample order.

    The sums are updated in sample order within each window, as one running pass does. Where the slope is zero but for rounding, the
    sign is then the same however the aggregation is split, spilled or merged.
    """
    rows = F.array_sort(F.collect_list(F.struct("pos", "w")))
    start = F.struct(*[F.lit(0.0).alias(c) for c in ("n", "at", "load", "c")])

    def update(s, z):
        n, pos = s["n"] + 1, z["pos"].cast("double")
        at, load = s["at"] + (pos - s["at"]) / n, s["load"] + (z["w"] - s["load"]) / n
        return F.when(z["w"].isNull(), s).otherwise(F.struct(n.alias("n"), at.alias("at"), load.alias("load"), (s["c"] + (pos - s["at"]) * (z["w"] - load)).alias("c")))

    # Positions differ, so the slope's sign is that of the co-moment.
    rising = F.aggregate("_rows", start, update, lambda s: s["c"] > 0)
    return numbered(trace, size, by).groupBy(*by, "win_no").agg(rows.alias("_rows")).select(*by, "win_no", rising.cast("int").alias("predicted"))


def keep_picking(scored_windows: DataFrame, trace: DataFrame, id_col: str = "src_id") -> DataFrame:
    """Samples of the windows predicted as picking (``src_ids`` carries each window's samples)."""
    ids = scored_windows.where("predicted = 1").select(F.explode("src_ids").alias(id_col)).distinct()
    return trace.join(ids, id_col, "left_semi")
