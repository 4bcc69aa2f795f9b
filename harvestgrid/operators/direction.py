"""Travel direction along a row: outlier filter, turning points, sign per stretch."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .grouped import add_columns


def hampel(df: DataFrame, col: str, half_window: int, by, order, n_sigma: float = 3.0, mad_floor: float = 0.0, impl: str = "native") -> DataFrame:
    """+ {col}_h: the window's median where a value is further from it than n_sigma scaled absolute deviations.

    ``impl="arrow"`` does the same in numpy per group, which is quicker for wide windows.
    """
    if impl == "arrow":
        return _hampel_arrow(df, col, half_window, by, order, n_sigma, mad_floor)
    w = Window.partitionBy(*by).orderBy(*order).rowsBetween(-half_window, half_window)
    out = df.withColumn("_win", F.array_sort(F.collect_list(col).over(w)))

    def median(a):
        n = F.size(a)
        return (F.element_at(a, F.floor((n + 1) / 2).cast("int")) + F.element_at(a, F.floor((n + 2) / 2).cast("int"))) / 2

    out = out.withColumn("_med", median(F.col("_win")))
    out = out.withColumn("_mad", median(F.array_sort(F.transform("_win", lambda v: F.abs(v - F.col("_med"))))))
    limit = F.greatest(F.lit(mad_floor), n_sigma * 1.4826 * F.col("_mad"))
    return out.withColumn(f"{col}_h", F.when(F.abs(F.col(col) - F.col("_med")) > limit, F.col("_med")).otherwise(F.col(col))).drop("_win", "_med", "_mad")


def _hampel_arrow(df, col, half_window, by, order, n_sigma, mad_floor):
    schema = df.drop(f"{col}_h").schema.add(f"{col}_h", T.DoubleType())

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(list(order), kind="stable").reset_index(drop=True)
        pdf[f"{col}_h"] = hampel_values(pdf[col].to_numpy(dtype=float), half_window, n_sigma, mad_floor)
        return pdf[schema.names]

    return df.drop(f"{col}_h").groupBy(*by).applyInPandas(run, schema)


def dominant_sign(df: DataFrame, by, order, y: str = "y") -> DataFrame:
    """Per group: the sign in which more steps went (+1 on ties), whatever their length; a few long jumps don't decide."""
    step = F.signum(F.col(y) - F.lag(y).over(Window.partitionBy(*by).orderBy(*order)))
    return df.withColumn("_step", step).groupBy(*by).agg(F.when(F.coalesce(F.sum("_step"), F.lit(0.0)) >= 0, 1).otherwise(-1).alias("direction"))


def turning_points(y: np.ndarray, prominence: float = 0.0, distance: int = 1) -> np.ndarray:
    """Indices of alternating peaks and valleys: a turn counts once y has come back by ``prominence``.

    Plateaus count once (their first sample); of close turns of one kind the more extreme stays, so kinds alternate.
    """
    turns: list[int] = []
    high = low = 0
    way = 0
    for i in range(1, len(y)):
        if y[i] > y[high]:
            high = i
        if y[i] < y[low]:
            low = i
        if way >= 0 and y[high] - y[i] > max(prominence, 1e-12):
            if way > 0:  # before the first way is known, no extreme stands out on both sides
                turns.append(high)
            way, low = -1, i
            high = i
        elif way <= 0 and y[i] - y[low] > max(prominence, 1e-12):
            if way < 0:
                turns.append(low)
            way, high = 1, i
            low = i
    if distance > 1:
        k = 0
        while k + 1 < len(turns):
            if turns[k + 1] - turns[k] < distance:
                del turns[k : k + 2]
            else:
                k += 1
    return np.array([t for t in turns if 0 < t < len(y) - 1], dtype=int)


def signs(y: np.ndarray, turns: np.ndarray) -> np.ndarray:
    """+1 or -1 per sample: the sign of the displacement of its stretch, ends included; no displacement is +1."""
    cuts = np.unique(np.concatenate([[0], turns, [len(y) - 1]]))
    out = np.ones(len(y), dtype=np.int32)
    for a, b in zip(cuts, cuts[1:]):
        out[a : b + 1] = 1 if y[b] >= y[a] else -1
    return out


def travel_direction(df: DataFrame, by, order, y: str = "y", prominence: float = 5.0, distance: int = 50) -> DataFrame:
    """+ direction per sample, by hysteresis turning points within each (cart, row)."""
    added = T.StructType().add("direction", T.IntegerType())
    return add_columns(df, by, order, [y], added, lambda v: (signs(v, turning_points(v, prominence, distance)),))


def hampel_values(v: np.ndarray, half_window: int, n_sigma: float = 3.0, mad_floor: float = 0.0) -> np.ndarray:
    """Outliers of a series replaced by their window's median."""
    padded = np.concatenate([np.full(half_window, np.nan), v, np.full(half_window, np.nan)])
    win = np.lib.stride_tricks.sliding_window_view(padded, 2 * half_window + 1)
    med = np.nanmedian(win, axis=1)
    mad = np.nanmedian(np.abs(win - med[:, None]), axis=1)
    return np.where(np.abs(v - med) > np.maximum(mad_floor, n_sigma * 1.4826 * mad), med, v)


def filtered_direction(df: DataFrame, by, order, y: str = "y", half_window: int = 25, n_sigma: float = 3.0, mad_floor: float = 0.0, prominence: float = 5.0, distance: int = 50) -> DataFrame:
    """+ {y}_h, direction per sample: outlier filter and turning points in one Python node per (cart, row)."""
    added = T.StructType().add(f"{y}_h", T.DoubleType()).add("direction", T.IntegerType())

    def step(v):
        v = hampel_values(v, half_window, n_sigma, mad_floor)
        return v, signs(v, turning_points(v, prominence, distance))

    return add_columns(df, by, order, [y], added, step)


def simple_direction(df: DataFrame, by, order, y: str = "y") -> DataFrame:
    """Per group: sign of last minus first; no displacement is +1."""
    key = F.struct(*order)
    ends = df.groupBy(*by).agg(F.min_by(y, key).alias("_a"), F.max_by(y, key).alias("_b"))
    return ends.withColumn("direction", F.when(F.col("_b") >= F.col("_a"), 1).otherwise(-1)).drop("_a", "_b")


def turns_native(df: DataFrame, by, order, y: str = "y") -> DataFrame:
    """Stretches, first and last sign per group without prominence: plateaus compressed, then sign changes counted."""
    w = Window.partitionBy(*by).orderBy(*order)
    step = df.withColumn("_d", F.signum(F.col(y) - F.lag(y).over(w)).cast("int")).where(F.coalesce(F.col("_d"), F.lit(0)) != 0)
    turn = step.withColumn("_t", F.coalesce((F.col("_d") != F.lag("_d").over(w)).cast("int"), F.lit(0)))
    key = F.struct(*order)
    found = turn.groupBy(*by).agg((F.sum("_t") + 1).alias("stretches"), F.min_by("_d", key).alias("first_dir"), F.max_by("_d", key).alias("last_dir"))
    every = df.select(*by).distinct()
    return every.join(found, list(by), "left").fillna({"stretches": 1, "first_dir": 1, "last_dir": 1})
