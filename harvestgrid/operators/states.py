"""Picker states: runs, transitions, dwell; activity intervals per row."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: The ten states of a picker.
STATES = ("setup", "enter_row", "picking", "exit_row", "transport", "deliver", "return", "wait", "idle", "finish")


def runs(df: DataFrame, by, order, state: str = "state") -> DataFrame:
    """One row per run of equal states: run number, length."""
    w = Window.partitionBy(*by).orderBy(*order)
    new = F.coalesce((F.col(state) != F.lag(state).over(w)).cast("int"), F.lit(1))
    marked = df.withColumn("_new", new).withColumn("run_no", F.sum("_new").over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    return marked.groupBy(*by, "run_no", state).agg(F.count(F.lit(1)).alias("len"))


def dwell(run: DataFrame, state: str = "state") -> DataFrame:
    return run.groupBy(state).agg(F.count(F.lit(1)).alias("runs"), F.avg("len").alias("mean_len"), F.max("len").alias("max_len"))


def transitions(df: DataFrame, by, order, state: str = "state") -> DataFrame:
    nxt = F.lead(state).over(Window.partitionBy(*by).orderBy(*order))
    return df.select(F.col(state).alias("from_state"), nxt.alias("to_state")).groupBy("from_state", "to_state").agg(F.count(F.lit(1)).alias("n"))


def pick_label(state: Column) -> Column:
    return F.when(state == "picking", "Pick").otherwise("NoPick")


def section_of(y: Column, y_center: float) -> Column:
    """Upper or lower section of the field, as crews split it."""
    return F.when(y >= y_center, "upper").otherwise("lower")
