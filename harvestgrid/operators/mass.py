"""Cleaning of the load signal: range, rate, stability, moving median."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

BY = ("cart_id", "session")


def in_range(df: DataFrame, w_min: float = 0.55, w_max: float = 5.0, w: str = "w") -> DataFrame:
    """Loads strictly between the empty and the full tray: a plain filter that reaches the scan."""
    return df.where((F.col(w) > w_min) & (F.col(w) < w_max))


def rate(df: DataFrame, by=BY, t: str = "t_us", w: str = "w", per_us: float = 1e6, tie=("src_id",)) -> DataFrame:
    """+ rate: forward difference over time; the last sample of a group has none."""
    order = Window.partitionBy(*by).orderBy(t, *tie)
    step = F.lead(t).over(order) - F.col(t)
    return df.withColumn("rate", F.when(step > 0, (F.lead(w).over(order) - F.col(w)) / (step / F.lit(per_us))))


def stable(rated: DataFrame, max_rate: float, strict_positive: bool = True) -> DataFrame:
    """Samples whose load rises, but no faster than picking can; with strict_positive off, plateaus stay too."""
    low = F.col("rate") > 0 if strict_positive else F.col("rate") >= 0
    return rated.where(low & (F.col("rate") <= max_rate))


def median_smooth(df: DataFrame, half_window: int = 2, by=BY, t: str = "t_us", w: str = "w", tie=("src_id",)) -> DataFrame:
    order = Window.partitionBy(*by).orderBy(t, *tie).rowsBetween(-half_window, half_window)
    return df.withColumn("w_smooth", F.percentile(w, F.lit(0.5)).over(order))


def clean(df: DataFrame, w_min=0.55, w_max=5.0, max_rate=0.5, half_window=2, by=BY, per_us=1e6, strict_positive: bool = True) -> DataFrame:
    """The whole step: both windows share one distribution and one sort."""
    return median_smooth(stable(rate(in_range(df, w_min, w_max), by, per_us=per_us), max_rate, strict_positive), half_window, by)
