"""Field frame: row centres, transforms between geodetic and field coordinates, clipping, fix gate."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def rows_from_beds(beds: DataFrame, by=("field_id",)) -> DataFrame:
    """Row centres midway between neighbouring bed centres, numbered from 0, with the spacing to the next bed."""
    order = Window.partitionBy(*by).orderBy("bed_x")
    nxt = F.lead("bed_x").over(order)
    return beds.select(*by, (F.row_number().over(order) - 1).alias("row_idx"), ((F.col("bed_x") + nxt) / 2).alias("row_x"), (nxt - F.col("bed_x")).alias("spacing")).where(F.col("row_x").isNotNull())


def fit_transform(ctrl: DataFrame, kind: str = "affine") -> dict[str, float]:
    """Transform of (lat, lon) to (x, y) from control points, by one aggregate of moments.

    Geodetic coordinates are first centred and scaled to metres. rigid: rotation and shift; affine: any linear map.
    """
    o = ctrl.agg(F.avg("lat").alias("lat"), F.avg("lon").alias("lon"), F.avg("x").alias("x"), F.avg("y").alias("y")).first()
    k_lat, k_lon = 111_320.0, 111_320.0 * math.cos(math.radians(o.lat))
    u, v = (F.col("lon") - o.lon) * k_lon, (F.col("lat") - o.lat) * k_lat
    x, y = F.col("x") - o.x, F.col("y") - o.y
    m = ctrl.agg(*[F.sum(a * b).alias(n) for n, a, b in (("uu", u, u), ("uv", u, v), ("vv", v, v), ("ux", u, x), ("vx", v, x), ("uy", u, y), ("vy", v, y))]).first()
    if kind == "rigid":
        angle = math.atan2(m.uy - m.vx, m.ux + m.vy)
        a, b, c, d = math.cos(angle), -math.sin(angle), math.sin(angle), math.cos(angle)
    else:
        det = m.uu * m.vv - m.uv * m.uv
        a, b = (m.ux * m.vv - m.vx * m.uv) / det, (m.vx * m.uu - m.ux * m.uv) / det
        c, d = (m.uy * m.vv - m.vy * m.uv) / det, (m.vy * m.uu - m.uy * m.uv) / det
    return {"lat0": o.lat, "lon0": o.lon, "x0": o.x, "y0": o.y, "k_lat": k_lat, "k_lon": k_lon, "a": a, "b": b, "c": c, "d": d}


def to_field(df: DataFrame, p: dict[str, float]) -> DataFrame:
    u, v = (F.col("lon") - p["lon0"]) * p["k_lon"], (F.col("lat") - p["lat0"]) * p["k_lat"]
    return df.withColumns({"x": p["x0"] + p["a"] * u + p["b"] * v, "y": p["y0"] + p["c"] * u + p["d"] * v})


def to_geodetic(df: DataFrame, p: dict[str, float], x: str = "x", y: str = "y") -> DataFrame:
    det = p["a"] * p["d"] - p["b"] * p["c"]
    dx, dy = F.col(x) - p["x0"], F.col(y) - p["y0"]
    u, v = (p["d"] * dx - p["b"] * dy) / det, (p["a"] * dy - p["c"] * dx) / det
    return df.withColumns({"lon": p["lon0"] + u / p["k_lon"], "lat": p["lat0"] + v / p["k_lat"]})


def in_polygon(x: Column, y: Column, polygon: list[tuple[float, float]]) -> Column:
    """Even-odd rule as an unrolled expression; the bounding box first, which may reach the scan."""
    xs, ys = zip(*polygon)
    inside = F.lit(False)
    for (x1, y1), (x2, y2) in zip(polygon, polygon[1:] + polygon[:1]):
        if y1 != y2:
            crosses = ((F.lit(y1) > y) != (F.lit(y2) > y)) & (x < (F.lit(x2 - x1) * (y - F.lit(y1)) / F.lit(y2 - y1) + F.lit(x1)))
            inside = inside != crosses
    return x.between(min(xs), max(xs)) & y.between(min(ys), max(ys)) & inside


def clip_to_boundary(trace: DataFrame, polygon: list[tuple[float, float]], mode: str = "polygon") -> DataFrame:
    xs, ys = zip(*polygon)
    if mode == "box":
        return trace.where(F.col("x").between(min(xs), max(xs)) & F.col("y").between(min(ys), max(ys)))
    return trace.where(in_polygon(F.col("x"), F.col("y"), polygon))


def require_fix(trace: DataFrame, fix: str = "has_fix", by=("cart_id", "session")) -> DataFrame:
    """Samples from each cart-day's first corrected position on, and only corrected ones."""
    first = F.min(F.when(F.col(fix), F.col("t_us"))).over(Window.partitionBy(*by))
    return trace.withColumn("_first", first).where(F.col(fix) & (F.col("t_us") >= F.col("_first"))).drop("_first")
