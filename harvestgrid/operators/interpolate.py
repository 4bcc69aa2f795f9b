"""Yield along a row: least-squares polynomials from one pass of moments, adaptive degree, increments.

Positions are centred and scaled per group before sums of powers are taken,
which keeps the normal equations of degree 3 well conditioned; all three degrees come
from the same sums, so a group's samples are shuffled as a few numbers.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.shared import keep


def _staged_solve(df: DataFrame, degree: int, s: list[str], r: list[str]) -> DataFrame:
    """+ c{degree} (array of coefficients, lowest first). Each elimination column is a projection, which keeps expressions small."""
    n = degree + 1
    a = [[f"_a{degree}_{i}_{j}" for j in range(n)] for i in range(n)]
    b = [f"_b{degree}_{i}" for i in range(n)]
    df = df.withColumns({a[i][j]: F.col(s[i + j]) for i in range(n) for j in range(n)} | {b[i]: F.col(r[i]) for i in range(n)})
    for p in range(n):
        new = {}
        for q in range(p + 1, n):
            f = F.try_divide(F.col(a[q][p]), F.col(a[p][p]))
            for c in range(p + 1, n):
                new[a[q][c]] = F.col(a[q][c]) - f * F.col(a[p][c])
            new[b[q]] = F.col(b[q]) - f * F.col(b[p])
        if new:
            df = df.withColumns(new)
    x = {}
    for p in range(n - 1, -1, -1):
        rest = F.col(b[p])
        for c in range(p + 1, n):
            rest = rest - F.col(a[p][c]) * F.col(x[c])
        x[p] = f"_x{degree}_{p}"
        df = df.withColumn(x[p], F.try_divide(rest, F.col(a[p][p])))
    df = df.withColumn(f"c{degree}", F.array(*[F.col(x[p]) for p in range(n)]))
    return df.drop(*[c for row in a for c in row], *b, *x.values())


def fit_polynomials(df: DataFrame, by, y: str = "y", w: str = "w", max_degree: int = 3) -> DataFrame:
    """Per group: y_min, y_max, centre, half, n, distinct positions, and coefficients c1..c3 with scores r1..r3.

    A degree needs more distinct positions than itself; constant mass scores 1 with degree 1.
    """
    by = list(by)
    # Extent and mean ride along as window columns, so the samples are computed and shuffled once and never joined to anything.
    whole = Window.partitionBy(*by)
    rows = df.select(*by, y, w).withColumns({"y_min": F.min(y).over(whole), "y_max": F.max(y).over(whole), "w_mean": F.avg(w).over(whole)})
    rows = rows.withColumns({"centre": (F.col("y_min") + F.col("y_max")) / 2, "half": (F.col("y_max") - F.col("y_min")) / 2})
    u = F.when(F.col("half") > 0, (F.col(y) - F.col("centre")) / F.col("half")).otherwise(0.0)
    v = F.col(w) - F.col("w_mean")
    rows = rows.withColumns({"_u": u, "_v": v})
    power = lambda k: F.lit(1.0) if k == 0 else F.pow("_u", F.lit(float(k)))
    sums = [F.sum(power(k)).alias(f"s{k}") for k in range(2 * max_degree + 1)]
    mixed = [F.sum(power(k) * F.col("_v")).alias(f"m{k}") for k in range(max_degree + 1)]
    held = ("y_min", "y_max", "centre", "half", "w_mean")
    counts = [F.count(F.lit(1)).alias("n"), F.count_distinct(F.col(y)).alias("n_distinct")]
    fits = rows.groupBy(*by).agg(*sums, *mixed, F.sum(F.col("_v") * F.col("_v")).alias("vv"), *counts, *[F.first(c).alias(c) for c in held])
    s, r = [f"s{k}" for k in range(2 * max_degree + 1)], [f"m{k}" for k in range(max_degree + 1)]
    for d in range(1, max_degree + 1):
        fits = _staged_solve(fits, d, s, r)
        # Explained part of the squared spread; equals R^2 at the least-squares solution.
        explained = sum((F.col(f"c{d}")[k] * F.col(f"m{k}") for k in range(d + 1)), F.lit(0.0))
        score = F.when(F.col("n_distinct") <= d, None).when(F.col("vv") <= 1e-12, F.lit(1.0)).otherwise(F.least(F.lit(1.0), explained / F.col("vv")))
        fits = fits.withColumn(f"r{d}", score)
    # One row per group: written once, as the elimination's expressions would grow with every use.
    return keep(fits.drop(*s, *r, "vv"))


def choose_degree(fits: DataFrame, score: float = 0.94, max_degree: int = 3, fixed: int | None = None) -> DataFrame:
    """+ degree, score, coef: the lowest degree above ``score``, else the best (lowest on ties); ``fixed`` takes one degree where it exists."""
    rs = [F.col(f"r{d}") for d in range(1, max_degree + 1)]
    best = F.greatest(*rs) if max_degree > 1 else rs[0]
    degree = F.lit(None).cast("int")
    if fixed is not None:
        for d in range(1, fixed + 1):
            degree = F.when(rs[d - 1].isNotNull(), d).otherwise(degree)
    else:
        for d in range(max_degree, 0, -1):
            degree = F.when(rs[d - 1] == best, d).otherwise(degree)
        for d in range(max_degree, 0, -1):
            degree = F.when(rs[d - 1] > score, d).otherwise(degree)
    out = fits.withColumn("degree", degree)
    pick = lambda name: F.coalesce(*[F.when(F.col("degree") == d, F.col(f"{name}{d}")) for d in range(1, max_degree + 1)])
    return out.withColumns({"score": pick("r"), "coef": pick("c")})


def poly_at(y: Column, max_degree: int = 3) -> Column:
    """Mass at a position, by Horner's rule on the centred and scaled variable; plain arithmetic, so it stays in generated code."""
    u = F.when(F.col("half") > 0, (y - F.col("centre")) / F.col("half")).otherwise(0.0)
    value = F.lit(0.0)
    for d in range(max_degree, -1, -1):
        value = value * u + F.coalesce(F.get("coef", F.lit(d)), F.lit(0.0))
    return F.col("w_mean") + value


def increments(fits: DataFrame, step: float = 0.3048, anchor: str = "lower", tail: str = "drop", clip: float | None = None) -> DataFrame:
    """+ y_int, dmass: absolute difference of the curve between neighbouring sample positions.

    Both ends are evaluated in one row, so nothing is shuffled. ``tail='keep'`` adds
    the stretch shorter than a step; ``clip`` limits predictions to [0, clip].
    """
    span = (F.col("y_max") - F.col("y_min")) / step
    n = F.floor(span + 1e-9).cast("int")
    last = n - 1 if tail == "drop" else F.ceil(span - 1e-9).cast("int") - 1
    rows = fits.where(F.col("coef").isNotNull()).withColumn("i", F.explode(F.when(last >= 0, F.sequence(F.lit(0), last)).otherwise(F.array().cast("array<int>"))))
    a = F.col("y_min") + F.col("i") * step
    b = F.least(F.col("y_max"), a + step) if tail != "drop" else a + step
    value = lambda y: poly_at(y) if clip is None else F.least(F.lit(clip), F.greatest(F.lit(0.0), poly_at(y)))
    at = {"lower": a, "upper": b, "mid": (a + b) / 2}[anchor]
    return rows.withColumns({"y_int": at, "dmass": F.abs(value(b) - value(a))})
