"""Field grids: closed-form cell lookup, daily maps, dense and coarser maps."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Grid:
    """A rectangle cut to cells; the last cell of an axis ends at the field's edge and may be short."""

    x_min: float
    y_min: float
    x_max: float
    y_max: float
    res_x: float
    res_y: float | None = None

    @property
    def step_y(self) -> float:
        return self.res_y or self.res_x

    def cells(self, axis: str) -> int:
        low, high, r = (self.x_min, self.x_max, self.res_x) if axis == "x" else (self.y_min, self.y_max, self.step_y)
        n = (high - low) / r
        whole = int(n)
        return max(1, whole + (1 if n - whole > 1e-9 else 0))


def cell_index(v: Column, low: float, high: float, r: float, n: int) -> Column:
    """Nearest cell middle: ties to the lower index, values outside clamped, the short last cell has its own middle."""
    k = F.greatest(F.lit(0), F.least(F.lit(n - 1), (F.ceil((v - F.lit(low)) / F.lit(r)) - 1).cast("int")))
    if n == 1:
        return F.lit(0)
    last_mid = ((low + r * (n - 1)) + high) / 2
    before_mid = low + r * (n - 2) + r / 2
    edge = (before_mid + last_mid) / 2
    return F.when(v > F.lit(edge), n - 1).when(k == n - 1, n - 2).otherwise(k).cast("int")


def locate(points: DataFrame, grid: Grid, x: str = "row_x", y: str = "y_int") -> DataFrame:
    """+ j, k: constant work per point, no search over middles, no shuffle."""
    j = cell_index(F.col(x), grid.x_min, grid.x_max, grid.res_x, grid.cells("x"))
    k = cell_index(F.col(y), grid.y_min, grid.y_max, grid.step_y, grid.cells("y"))
    return points.withColumns({"j": j, "k": k})


def daily_map(points: DataFrame, grid: Grid, by=("field_id", "day")) -> DataFrame:
    """Mass per cell and day over all carts: one partial aggregate, a shuffle of cells only."""
    return locate(points, grid).groupBy(*by, "j", "k").agg(F.sum("dmass").alias("mass"))


def all_cells(grid: Grid) -> Column:
    """array<struct<j, k>> of every cell, to be exploded onto the keys that need them."""
    js = F.sequence(F.lit(0), F.lit(grid.cells("x") - 1))
    ks = F.sequence(F.lit(0), F.lit(grid.cells("y") - 1))
    return F.flatten(F.transform(js, lambda j: F.transform(ks, lambda k: F.struct(j.alias("j"), k.alias("k")))))


def densify(cells: DataFrame, grid: Grid, by=("field_id",)) -> DataFrame:
    """Every cell of the grid for every key, with zero where nothing was picked."""
    full = cells.select(*by).distinct().select(*by, F.inline(all_cells(grid)))
    return full.join(cells, [*by, "j", "k"], "left").withColumn("mass", F.coalesce("mass", F.lit(0.0)))


def coarsen(cells: DataFrame, factor: int, by=("field_id",)) -> DataFrame:
    """A map at ``factor`` times the cell side, from the finer map."""
    return cells.groupBy(*by, F.floor(F.col("j") / factor).cast("int").alias("j"), F.floor(F.col("k") / factor).cast("int").alias("k")).agg(F.sum("mass").alias("mass"))


def cell_middle(grid: Grid) -> dict[str, Column]:
    """x and y of the middle of cell (j, k), short last cells included."""
    x0, x1 = grid.x_min + F.col("j") * grid.res_x, F.least(F.lit(grid.x_max), grid.x_min + (F.col("j") + 1) * grid.res_x)
    y0, y1 = grid.y_min + F.col("k") * grid.step_y, F.least(F.lit(grid.y_max), grid.y_min + (F.col("k") + 1) * grid.step_y)
    return {"cell_x": (x0 + x1) / 2, "cell_y": (y0 + y1) / 2}


def export_features(cells: DataFrame, grid: Grid) -> DataFrame:
    """One text feature (point geometry, mass) per cell, for map viewers."""
    mid = cells.withColumns(cell_middle(grid))
    geometry = F.struct(F.lit("Point").alias("type"), F.array("cell_x", "cell_y").alias("coordinates"))
    return mid.select(F.to_json(F.struct(F.lit("Feature").alias("type"), geometry.alias("geometry"), F.struct("j", "k", "mass").alias("properties"))).alias("feature"))
