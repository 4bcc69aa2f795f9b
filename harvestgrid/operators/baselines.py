"""Plainer methods that the pipeline is compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import rows


def counted_trays(df: DataFrame, by=("cart_id",), tray: str = "tray_id") -> DataFrame:
    return df.where(F.col(tray) >= 0).groupBy(*by).agg(F.count_distinct(F.col(tray)).alias("counted"))


def reconcile(counts: DataFrame, payroll: DataFrame, by=("cart_id",)) -> DataFrame:
    """Counts against piece-rate records; a side without the key counts as zero."""
    both = counts.join(payroll, list(by), "full_outer")
    c, p = F.coalesce("counted", F.lit(0)), F.coalesce("paid", F.lit(0))
    return both.select(*by, c.alias("counted"), p.alias("paid"), (c - p).alias("diff"))


def snap_pointwise(trace: DataFrame, spacing: str = "spacing") -> DataFrame:
    """+ row_idx: the nearest row of each sample alone."""
    return trace.withColumn("row_idx", rows.nearest_row(F.col("x"), F.col(spacing)))


def container_average(trays: DataFrame, cells: DataFrame, by=("cart_id",), average: float = 4.25) -> DataFrame:
    """Containers times their mean mass, spread evenly over the cells visited."""
    n = trays.groupBy(*by).agg(F.count(F.lit(1)).alias("trays"))
    visited = cells.groupBy(*by).agg(F.count(F.lit(1)).alias("cells"))
    return n.join(visited, list(by)).withColumn("mass_per_cell", F.col("trays") * average / F.col("cells"))


def staircase_yield(df: DataFrame, by, order, w: str = "w") -> DataFrame:
    """+ dmass: raw differences of the load, no interpolation."""
    o = Window.partitionBy(*by).orderBy(*order)
    return df.withColumn("dmass", F.abs(F.col(w) - F.lag(w).over(o)))


def linear_interp(df: DataFrame, by, order, y: str = "y", w: str = "w", step: float = 0.3048) -> DataFrame:
    """Staircase differences spread evenly over the positions between two samples."""
    o = Window.partitionBy(*by).orderBy(*order)
    gap = df.withColumns({"_y0": F.lag(y).over(o), "_d": F.abs(F.col(w) - F.lag(w).over(o))}).where("_d is not null")
    n = F.greatest(F.lit(1), F.ceil(F.abs(F.col(y) - F.col("_y0")) / step).cast("int"))
    cut = gap.withColumn("_n", n).withColumn("_i", F.explode(F.sequence(F.lit(0), F.col("_n") - 1)))
    return cut.select(*by, (F.col("_y0") + (F.col(y) - F.col("_y0")) * F.col("_i") / F.col("_n")).alias("y_int"), (F.col("_d") / F.col("_n")).alias("dmass"))
