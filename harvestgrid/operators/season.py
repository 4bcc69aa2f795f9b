"""Season maps: accumulation, classes, densities, trends, zones."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

POUND, FOOT = 0.45359237, 0.3048
CLASSES = ("very_low", "below", "above", "very_high")


def accumulate(daily: DataFrame, first=None, last=None, by=("field_id",)) -> DataFrame:
    """Sum of the daily maps of any span of days; the filter reaches the day partitions."""
    if first is not None:
        daily = daily.where(F.col("day") >= F.lit(first))
    if last is not None:
        daily = daily.where(F.col("day") <= F.lit(last))
    return daily.groupBy(*by, "j", "k").agg(F.sum("mass").alias("mass"))


def classify(cells: DataFrame, by=("field_id",), ddof: int = 1, empty: bool = False) -> DataFrame:
    """Four classes by mean and standard deviation of each field's cells (cells with yield, unless ``empty``)."""
    used = cells if empty else cells.where("mass > 0")
    sd = F.stddev_samp("mass") if ddof else F.stddev_pop("mass")
    # One row per field: joined back rather than windowed, so that no task holds a field's cells.
    stats = used.groupBy(*by).agg(F.avg("mass").alias("mu"), sd.alias("sd"))
    m, mu, s = F.col("mass"), F.col("mu"), F.coalesce("sd", F.lit(0.0))
    kind = F.when(m <= mu - s, CLASSES[0]).when(m <= mu, CLASSES[1]).when(m <= mu + s, CLASSES[2]).otherwise(CLASSES[3])
    return used.join(stats, list(by)).withColumn("yield_class", kind).drop("mu", "sd")


def histogram(cells: DataFrame, low: float, high: float, bins: int) -> DataFrame:
    """Cells per bin of equal width; bins 0 and bins + 1 hold what lies outside."""
    return cells.groupBy(F.width_bucket("mass", F.lit(low), F.lit(high), F.lit(bins)).alias("bin")).agg(F.count(F.lit(1)).alias("cells"))


def density(cells: DataFrame, area: float, by=("field_id",), share: Column | None = None) -> DataFrame:
    """Mean and spread of mass per cell, and mass per area; ``share`` is the part of a cell inside the crop."""
    cover = F.sum(share * area) if share is not None else F.count(F.lit(1)) * area
    kg_m2 = F.sum("mass") / cover
    return cells.groupBy(*by).agg(F.avg("mass").alias("mean_mass"), F.stddev_samp("mass").alias("sd_mass"), kg_m2.alias("kg_m2"), (kg_m2 / POUND * FOOT * FOOT).alias("lb_ft2"))


def zero_share(sparse: DataFrame, n_cells: int, by=("field_id",), per=("month",)) -> DataFrame:
    """Mean over days (or months) of the share of cells without yield: needs no dense map, only the count of cells that have some."""
    each = sparse.groupBy(*by, *per).agg((1 - F.count_if(F.col("mass") > 0) / F.lit(n_cells)).alias("share"))
    return each.groupBy(*by).agg(F.avg("share").alias("mean_zero_share"), F.count(F.lit(1)).alias("months"))


def running(daily: DataFrame, by=("field_id",), at: str = "month") -> DataFrame:
    per = daily.groupBy(*by, at).agg(F.sum("mass").alias("mass"))
    order = Window.partitionBy(*by).orderBy(at).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return per.withColumn("cumulative_mass", F.sum("mass").over(order))


def temporal(daily: DataFrame, at: str = "day_no", by=("field_id",)) -> DataFrame:
    """Per cell: trend of mass over time and coefficient of variation."""
    return daily.groupBy(*by, "j", "k").agg(
        F.regr_slope("mass", F.col(at).cast("double")).alias("slope"), F.try_divide(F.stddev_samp("mass"), F.avg("mass")).alias("cv"), F.count(F.lit(1)).alias("n")
    )


def low_zones(classified: DataFrame, classes=("very_low",), by=("field_id",), max_rounds: int = 60) -> DataFrame:
    """Connected zones of low cells (4 neighbours): field, zone, cells, mass.

    Labels spread by joins on neighbouring cells until none changes; the tables hold
    cells of low yield only. Each round is checkpointed, which cuts the lineage.
    """
    low = classified.where(F.col("yield_class").isin(*classes)).select(*by, "j", "k", "mass")
    label = F.struct("j", "k")
    cells = low.select(*by, "j", "k", label.alias("zone"))
    from ..plans.shared import keep

    cells = keep(cells)
    for _ in range(max_rounds):
        steps = F.array(*[F.struct((F.col("j") + a).alias("j"), (F.col("k") + b).alias("k")) for a, b in ((0, 0), (1, 0), (-1, 0), (0, 1), (0, -1))])
        offered = cells.select(*by, F.col("zone").alias("offer"), F.inline(steps)).groupBy(*by, "j", "k").agg(F.min("offer").alias("offer"))
        grown = keep(cells.join(offered, [*by, "j", "k"]).select(*by, "j", "k", F.least("zone", "offer").alias("zone"), (F.col("offer") < F.col("zone")).alias("moved")))
        moved = grown.where("moved").limit(1).count()
        cells = grown.drop("moved")
        if not moved:
            break
        # Jump: a zone's label takes its own cell's label.
        head = cells.select(*by, F.struct("j", "k").alias("zone"), F.col("zone").alias("jump"))
        cells = keep(cells.join(head, [*by, "zone"]).select(*by, "j", "k", F.least("zone", "jump").alias("zone")))
    joined = cells.join(low, [*by, "j", "k"])
    return joined.groupBy(*by, "zone").agg(F.count(F.lit(1)).alias("cells"), F.sum("mass").alias("mass"))
