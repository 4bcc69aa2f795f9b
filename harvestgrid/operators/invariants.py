"""The two conditions of a valid harvest: one (row, direction) per picker, one picker per (row, direction), at any time."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def activity_intervals(trace: DataFrame, max_gap, by=("field_id", "session", "cart_id"), t: str = "t_us", row: str = "row_idx", direction: str = "direction", tie=("src_id",)) -> DataFrame:
    """Stretches in which a cart works one row in one direction without a longer pause."""
    w = Window.partitionBy(*by).orderBy(t, *tie)
    cut = (F.col(row) != F.lag(row).over(w)) | (F.col(direction) != F.lag(direction).over(w)) | (F.col(t) - F.lag(t).over(w) > max_gap)
    marked = trace.withColumn("_cut", F.coalesce(cut.cast("int"), F.lit(1)))
    marked = marked.withColumn("_no", F.sum("_cut").over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    return marked.groupBy(*by, "_no", row, direction).agg(F.min(t).alias("t1"), F.max(t).alias("t2")).drop("_no")


def max_concurrent(intervals: DataFrame, by, t1: str = "t1", t2: str = "t2") -> DataFrame:
    """Most intervals open at once per key, by a sweep over starts and ends (never a self-join). Touching ends don't overlap."""
    ends = intervals.select(*by, F.inline(F.array(F.struct(F.col(t1).alias("t"), F.lit(1).alias("d")), F.struct(F.col(t2).alias("t"), F.lit(-1).alias("d")))))
    sweep = Window.partitionBy(*by).orderBy("t", "d").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return ends.withColumn("open", F.sum("d").over(sweep)).groupBy(*by).agg(F.max("open").alias("max_concurrent"))


def row_completion_violations(intervals: DataFrame) -> DataFrame:
    """Carts that are in more than one (row, direction) at some time."""
    return max_concurrent(intervals, ("field_id", "session", "cart_id")).where("max_concurrent > 1")


def row_occupancy_violations(intervals: DataFrame) -> DataFrame:
    """(row, direction) with more than one cart at some time; opposite directions are legal."""
    return max_concurrent(intervals, ("field_id", "session", "row_idx", "direction")).where("max_concurrent > 1")
