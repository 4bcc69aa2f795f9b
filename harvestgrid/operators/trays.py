"""Separation of trays, by density clustering or by resets of the load."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import cluster


def separate(df: DataFrame, by=("cart_id",), dims: dict[str, float] | None = None, eps: float = 1.0, min_pts: int = 5, strategy: str = "auto", tie=("src_id",)) -> DataFrame:
    """+ tray_id: clusters over place, time, mass and row (noise: -1)."""
    dims = dims or {"t_us": 30e6, "y": 3.0, "w": 0.5, "row_idx": 0.5}
    return cluster.density_cluster(df, by, dims, eps, min_pts, strategy, tie=tie).withColumnRenamed("cluster_id", "tray_id").drop("is_core")


def by_mass_reset(df: DataFrame, drop_kg: float, by=("cart_id",), t: str = "t_us", w: str = "w", tie=("src_id",)) -> DataFrame:
    """+ tray_id: a new tray where the load falls by more than ``drop_kg``."""
    order = Window.partitionBy(*by).orderBy(t, *tie)
    fell = F.coalesce((F.lag(w).over(order) - F.col(w) > drop_kg).cast("long"), F.lit(0))
    return df.withColumn("_fell", fell).withColumn("tray_id", F.sum("_fell").over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow))).drop("_fell")
