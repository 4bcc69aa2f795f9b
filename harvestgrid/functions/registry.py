"""SQL functions and column builders for users who work in SQL."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from ..operators.geometry import in_polygon
from ..operators.gridmap import Grid, cell_index
from ..operators.interpolate import poly_at
from ..operators.occupancy import overlap_1d

BUILDERS = {"cell_index": cell_index, "overlap_1d": overlap_1d, "poly_eval": poly_at, "point_in_polygon": in_polygon}


class GridCells:
    """Table function: index and middle of every cell of a rectangle."""

    def eval(self, xmin: float, ymin: float, xmax: float, ymax: float, rx: float, ry: float) -> Iterator[tuple[int, int, float, float]]:
        g = Grid(xmin, ymin, xmax, ymax, rx, ry)
        for j in range(g.cells("x")):
            for k in range(g.cells("y")):
                x0, y0 = xmin + j * rx, ymin + k * ry
                yield j, k, (x0 + min(xmax, x0 + rx)) / 2, (y0 + min(ymax, y0 + ry)) / 2


class YSamples:
    """Table function: sample positions from ymin by step, up to ymax."""

    def eval(self, ymin: float, ymax: float, step: float) -> Iterator[tuple[int, float]]:
        i = 0
        while ymin + i * step <= ymax + 1e-9:
            yield i, ymin + i * step
            i += 1


@F.pandas_udf(DoubleType())
def poly_score(y: pd.Series, w: pd.Series, degree: pd.Series) -> float:
    """Aggregate: share of the spread of w that a polynomial of the given degree in y explains (null with too few positions)."""
    d = int(degree.iloc[0])
    if y.nunique() <= d:
        return None
    spread = float(((w - w.mean()) ** 2).sum())
    if spread <= 1e-12:
        return 1.0
    u = (y - y.mean()) / (y.std(ddof=0) or 1.0)
    return 1.0 - float(((w - np.polyval(np.polyfit(u, w, d), u)) ** 2).sum()) / spread


@F.pandas_udf(DoubleType())
def poly_value(y: pd.Series, coef: pd.Series) -> pd.Series:
    """Column: value of a polynomial (coefficients lowest first) at y, in Arrow batches."""
    return pd.Series([float(np.polyval(c[::-1], v)) for c, v in zip(coef, y)], dtype="float64")


def register(spark: SparkSession) -> None:
    """SQL functions overlap_1d, nearest_row, yield_class, poly_score (aggregate), poly_value; table functions grid_cells and y_samples."""
    spark.udf.register("poly_score", poly_score)
    spark.udf.register("poly_value", poly_value)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION overlap_1d(a_lo DOUBLE, a_hi DOUBLE, b_lo DOUBLE, b_hi DOUBLE) RETURNS DOUBLE RETURN greatest(0.0D, least(a_hi, b_hi) - greatest(a_lo, b_lo))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION nearest_row(x DOUBLE, spacing DOUBLE) RETURNS INT RETURN cast(greatest(0, round(x / spacing)) AS INT)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION yield_class(mass DOUBLE, mu DOUBLE, sd DOUBLE) RETURNS STRING RETURN CASE WHEN mass <= mu - sd THEN 'very_low' WHEN mass <= mu THEN 'below' WHEN mass <= mu + sd THEN 'above' ELSE 'very_high' END")
    spark.udtf.register("grid_cells", F.udtf(GridCells, returnType="j int, k int, x double, y double"))
    spark.udtf.register("y_samples", F.udtf(YSamples, returnType="i int, y double"))


def poly_eval(y: Column) -> Column:
    return poly_at(y)
