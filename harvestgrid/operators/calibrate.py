"""Load calibration: one straight line per cart from known masses."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def fit_load_cells(cal: DataFrame, by=("cart_id",), min_points: int = 3) -> DataFrame:
    """slope, intercept, r2, n per cart; carts with fewer points are left out."""
    fit = cal.groupBy(*by).agg(
        F.regr_slope("known_mass", "reading").alias("slope"), F.regr_intercept("known_mass", "reading").alias("intercept"), F.regr_r2("known_mass", "reading").alias("r2"), F.count(F.lit(1)).alias("n")
    )
    return fit.where(F.col("n") >= min_points)


def apply_load_cells(trace: DataFrame, params: DataFrame, reading: str = "raw_load", as_of: bool = False, small: int = 100_000) -> DataFrame:
    """+ w. With ``as_of``, params carry valid_from_us and the latest set valid at a sample's time counts."""
    if as_of:
        sets = params.groupBy("cart_id").agg(F.array_sort(F.collect_list(F.struct("valid_from_us", "slope", "intercept"))).alias("_sets"))
        side = F.broadcast(sets) if sets.limit(small + 1).count() <= small else sets
        joined = trace.join(side, "cart_id", "left")
        good = F.element_at(F.filter("_sets", lambda s: s["valid_from_us"] <= F.col("t_us")), -1)
        return joined.withColumn("_set", good).withColumn("w", F.col("_set.slope") * F.col(reading) + F.col("_set.intercept")).drop("_set", "_sets")
    sets = params.select("cart_id", "slope", "intercept")
    side = F.broadcast(sets) if sets.limit(small + 1).count() <= small else sets
    return trace.join(side, "cart_id", "left").withColumn("w", F.col("slope") * F.col(reading) + F.col("intercept")).drop("slope", "intercept")


def needs_recalibration(cal: DataFrame, params: DataFrame, max_abs_resid: float, min_r2: float = 0.0) -> DataFrame:
    """Carts whose check readings miss the line by too much, or whose line explains too little."""
    resid = F.abs(F.col("slope") * F.col("reading") + F.col("intercept") - F.col("known_mass"))
    worst = cal.join(params, "cart_id").groupBy("cart_id").agg(F.max(resid).alias("max_resid"), F.first("r2").alias("r2"))
    return worst.where((F.col("max_resid") > max_abs_resid) | (F.col("r2") < min_r2))
