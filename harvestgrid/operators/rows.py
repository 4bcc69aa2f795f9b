"""Assignment of clusters to crop rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def nearest_row(x: Column, spacing: Column, n_rows: int | None = None) -> Column:
    """Row index of evenly spaced rows (row r at r * spacing), clamped: closed form."""
    k = F.greatest(F.lit(0), F.round(x / spacing).cast("int"))
    return F.least(F.lit(n_rows - 1), k) if n_rows else k


def assign_rows(clustered: DataFrame, rows: DataFrame | None = None, by=("field_id", "cart_id"), spacing: str | None = "spacing", noise: str = "null", max_dist: float | None = None, metric: str = "x") -> DataFrame:
    """cluster -> median_x, row_idx, distance.

    ``rows`` (field_id, row_idx, row_x) is packed to one array per field and
    broadcast; without it rows are evenly spaced. Noise keeps a null row or is dropped.
    ``metric="euclid"`` measures to the row's stretch (y_lo, y_hi in ``rows``) instead of along x only.
    """
    med = clustered.where("cluster_id >= 0").groupBy(*by, "cluster_id").agg(F.percentile("x", F.lit(0.5)).alias("median_x"), *([F.first(spacing).alias("spacing")] if rows is None else []))
    if rows is None:
        out = med.withColumn("row_idx", nearest_row(F.col("median_x"), F.col("spacing"))).withColumn("distance", F.abs(F.col("median_x") - F.col("row_idx") * F.col("spacing")))
    else:
        ends = ["y_lo", "y_hi"] if metric == "euclid" else []
        packed = rows.groupBy("field_id").agg(F.collect_list(F.struct("row_idx", "row_x", *ends)).alias("_rows"))
        if metric == "euclid":
            med = med.join(clustered.where("cluster_id >= 0").groupBy(*by, "cluster_id").agg(F.percentile("y", F.lit(0.5)).alias("median_y")), [*by, "cluster_id"])

        def distance(r):
            dx = F.abs(r["row_x"] - F.col("median_x"))
            return dx if metric == "x" else F.hypot(dx, F.greatest(F.lit(0.0), r["y_lo"] - F.col("median_y"), F.col("median_y") - r["y_hi"]))

        best = F.array_min(F.transform("_rows", lambda r: F.struct(distance(r).alias("distance"), r["row_idx"].alias("row_idx"))))
        out = med.join(F.broadcast(packed), "field_id").withColumn("_best", best).withColumns({"row_idx": F.col("_best.row_idx"), "distance": F.col("_best.distance")}).drop("_best", "_rows")
    if max_dist is not None:
        out = out.withColumn("row_idx", F.when(F.col("distance") <= max_dist, F.col("row_idx")))
    if noise == "null":
        lost = clustered.where("cluster_id < 0").select(*by, "cluster_id").distinct()
        out = out.unionByName(lost, allowMissingColumns=True)
    return out


def write_back(clustered: DataFrame, assigned: DataFrame, by=("field_id", "cart_id")) -> DataFrame:
    """Samples with their cluster's row: one map per cart, joined on the cart alone."""
    packed = assigned.where("row_idx is not null").groupBy(*by).agg(F.map_from_entries(F.collect_list(F.struct("cluster_id", "row_idx"))).alias("_rows"))
    return clustered.drop("row_idx").join(packed, list(by), "left").withColumn("row_idx", F.col("_rows")[F.col("cluster_id")]).drop("_rows")
