"""Accuracy and agreement measures; each is one aggregation over pairs (gt, est)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def relative_error(gt: str = "gt", est: str = "est") -> Column:
    """Null where the truth is 0."""
    return F.try_divide(F.abs(F.col(gt) - F.col(est)), F.col(gt))


def row_level(pairs: DataFrame, tray: str = "tray_id") -> DataFrame:
    """1 - mean relative error over (tray, row) segments; the printed form divides by the number of trays."""
    per = pairs.where("gt > 0").groupBy(tray).agg(F.sum(relative_error()).alias("e"), F.count(F.lit(1)).alias("n"))
    return per.agg(
        (1 - F.sum("e") / F.count(F.lit(1))).alias("acc_printed"), (1 - F.sum("e") / F.sum("n")).alias("acc_segments"),
        F.count(F.lit(1)).alias("n_trays"), F.sum("n").alias("n_segments"),
    )


def tray_level(pairs: DataFrame, tray: str = "tray_id") -> DataFrame:
    """Segments summed per tray first, then the mean relative error over trays."""
    per = pairs.groupBy(tray).agg(F.sum("gt").alias("gt"), F.sum("est").alias("est")).where("gt > 0").select((1 - relative_error()).alias("acc"))
    return per.agg(F.avg("acc").alias("accuracy"), F.stddev_samp("acc").alias("sd"), F.min("acc").alias("min_acc"), F.max("acc").alias("max_acc"), F.count(F.lit(1)).alias("n"))


def count_from_mass(df: DataFrame, by, mass: str = "mass", tray_net: float = 4.25) -> DataFrame:
    """Estimated trays per cart and day: mass over the mean net tray."""
    return df.groupBy(*by).agg((F.sum(mass) / tray_net).alias("est"))


def summary(pairs: DataFrame) -> DataFrame:
    """Totals, accuracy (mean over pairs), MAE, RMSE, Pearson r."""
    d = F.col("est") - F.col("gt")
    return pairs.agg(
        F.sum("gt").alias("total_gt"), F.sum("est").alias("total_est"), (1 - F.avg(relative_error())).alias("accuracy"), F.avg(F.abs(d)).alias("mae"),
        F.sqrt(F.avg(d * d)).alias("rmse"), F.try_divide(F.covar_pop("gt", "est"), F.stddev_pop("gt") * F.stddev_pop("est")).alias("pearson_r"), F.count(F.lit(1)).alias("n"),
    )


def agreement(pairs: DataFrame, z: float = 1.96) -> DataFrame:
    """Bias (estimate minus truth), spread, limits, the farther limit from zero, share of pairs inside the limits."""
    d = (F.col("est") - F.col("gt")).alias("d")
    stats = pairs.agg(F.avg(d).alias("bias"), F.stddev_samp(d).alias("sd"))
    stats = stats.withColumns({"lo": F.col("bias") - z * F.col("sd"), "hi": F.col("bias") + z * F.col("sd"), "far_limit": F.abs("bias") + z * F.col("sd")})
    inside = pairs.select(d).join(F.broadcast(stats)).agg(F.avg(F.col("d").between(F.col("lo"), F.col("hi")).cast("double")).alias("share_inside"))
    return stats.join(F.broadcast(inside))


def agreement_points(pairs: DataFrame) -> DataFrame:
    return pairs.select(((F.col("gt") + F.col("est")) / 2).alias("mean"), (F.col("est") - F.col("gt")).alias("diff"))


def box_plot(values: DataFrame, column: str, by=()) -> DataFrame:
    """Quartiles, mean, spread, and the whiskers at most 1.5 quartile ranges beyond the box."""
    q = lambda p: F.percentile(column, F.lit(p))
    stats = values.groupBy(*by).agg(q(0.25).alias("q1"), q(0.5).alias("median"), q(0.75).alias("q3"), F.avg(column).alias("mean"), F.stddev_samp(column).alias("sd"))
    reach = 1.5 * (F.col("q3") - F.col("q1"))
    with_box = values.join(F.broadcast(stats), list(by)) if by else values.join(F.broadcast(stats))
    ends = with_box.where((F.col(column) >= F.col("q1") - reach) & (F.col(column) <= F.col("q3") + reach)).groupBy(*by).agg(F.min(column).alias("lo"), F.max(column).alias("hi"))
    return stats.join(F.broadcast(ends), list(by)) if by else stats.join(F.broadcast(ends))


def confusion(df: DataFrame, truth: Column, predicted: Column, by=()) -> DataFrame:
    """Counts, precision, recall, F1, accuracy of a binary prediction; also per class and averaged F1."""
    cell = lambda t, p: F.count_if((truth == t) & (predicted == p))
    out = df.groupBy(*by).agg(cell(1, 1).alias("tp"), cell(0, 1).alias("fp"), cell(1, 0).alias("fn"), cell(0, 0).alias("tn"))
    tp, fp, fn, tn = (F.col(c) for c in ("tp", "fp", "fn", "tn"))
    div = F.try_divide
    f1, f0 = div(2 * tp, 2 * tp + fp + fn), div(2 * tn, 2 * tn + fp + fn)
    n = tp + fp + fn + tn
    return out.withColumns({
        "precision": div(tp, tp + fp), "recall": div(tp, tp + fn), "f1": f1, "accuracy": div(tp + tn, n),
        "f1_macro": (f1 + f0) / 2, "f1_weighted": div(f1 * (tp + fn) + f0 * (tn + fp), n),
    })


def identity_residual(pairs: DataFrame) -> DataFrame:
    """Mean distance of the scatter from the line of a perfect estimator."""
    return pairs.agg(F.avg(F.abs(F.col("est") - F.col("gt")) / F.sqrt(F.lit(2.0))).alias("mean_distance"))


def step_effect(steps: list[tuple[str, DataFrame, DataFrame]]) -> DataFrame:
    """Samples in and out of each step."""
    out = None
    for name, before, after in steps:
        one = before.agg(F.count(F.lit(1)).alias("rows_in")).join(F.broadcast(after.agg(F.count(F.lit(1)).alias("rows_out")))).select(F.lit(name).alias("step"), "rows_in", "rows_out")
        out = one if out is None else out.unionByName(one)
    return out


def gap_report(trace: DataFrame, by=("field_id", "cart_id", "session"), cap_s: float = 5.0) -> DataFrame:
    """Share of each cart-day's time that has no samples (signal or power lost)."""
    from pyspark.sql import Window

    step = (F.lead("t_us").over(Window.partitionBy(*by).orderBy("t_us")) - F.col("t_us")) / 1e6
    return trace.withColumn("step", step).groupBy(*by).agg(F.try_divide(F.sum(F.when(F.col("step") > cap_s, F.col("step") - cap_s)), F.sum("step")).alias("gap_share"), F.count(F.lit(1)).alias("n"))
