"""Density clustering with one contract and several strategies.

A point with at least ``min_pts`` points within ``eps`` (itself included) is a core; cores
within eps of each other share a cluster; other points within eps of a core join
the nearest core's cluster (ties: the smaller cluster), the rest is noise (-1).
Clusters are numbered per group by their first core in order of the first
dimension given.

line   one dimension, exact: range frames only, stays on the group's distribution
group  any dimensions, exact, in numpy per bounded group (a cart-day)
grid   any dimensions, exact, for unbounded groups: cells of side eps / sqrt(d), joins of neighbouring cells
chain  cheap approximation: cuts where consecutive samples are further apart than eps
"""

from __future__ import annotations

import itertools
import math

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .grouped import add_columns


def line(df: DataFrame, by, dim: str, eps, min_pts: int, tie=("src_id",)) -> DataFrame:
    """+ is_core, cluster_id. The dimension is integral (microseconds, centimetres); cores further apart than eps start a cluster."""
    by = list(by)
    group = Window.partitionBy(*by)
    near = group.orderBy(dim).rangeBetween(-eps, eps)
    order = group.orderBy(dim, *tie)
    upto, after = order.rowsBetween(Window.unboundedPreceding, -1), order.rowsBetween(1, Window.unboundedFollowing)
    out = df.withColumn("is_core", F.count(F.lit(1)).over(near) >= min_pts)
    here = F.when(F.col("is_core"), F.col(dim))
    out = out.withColumn("_before", F.last(here, ignorenulls=True).over(upto)).withColumn("_after", F.first(here, ignorenulls=True).over(after))
    starts = F.col("is_core") & (F.col("_before").isNull() | (F.col(dim) - F.col("_before") > eps))
    out = out.withColumn("_number", F.sum(starts.cast("long")).over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow)) - 1)
    to_before = F.when(F.col(dim) - F.col("_before") <= eps, F.col(dim) - F.col("_before"))
    to_after = F.when(F.col("_after") - F.col(dim) <= eps, F.col("_after") - F.col(dim))
    joins = F.when(to_before.isNotNull() & (to_after.isNull() | (to_before <= to_after)), F.col("_number")).when(to_after.isNotNull(), F.col("_number") + 1)
    # The next core opens a new cluster only if it is further than eps from the previous one.
    same = F.col("_before").isNotNull() & F.col("_after").isNotNull() & (F.col("_after") - F.col("_before") <= eps)
    label = F.when(F.col("is_core") | (same & joins.isNotNull()), F.col("_number")).otherwise(F.coalesce(joins, F.lit(-1)))
    return out.withColumn("cluster_id", label).drop("_before", "_after", "_number")


def _near_all(points: np.ndarray, eps: float):
    """Index pairs within eps (each point with itself too) of a few points, compared at once."""
    return np.nonzero(((points[:, None] - points[None]) ** 2).sum(axis=2) <= eps * eps * (1 + 1e-12))


def _near_cells(points: np.ndarray, eps: float):
    """The same of many points, by cells of side eps."""
    n, d = points.shape
    cell = np.floor(points / eps).astype(np.int64)
    cell -= cell.min(axis=0)
    width = cell.max(axis=0) + 3
    key = np.ravel_multi_index(tuple((cell + 1).T), tuple(width)) if np.prod(width.astype(float)) < 2**62 else np.unique(cell, axis=0, return_inverse=True)[1]
    order = np.argsort(key, kind="stable")
    sorted_key = key[order]
    pairs_i, pairs_j = [], []
    if np.prod(width.astype(float)) < 2**62:
        strides = np.array([int(np.prod(width[k + 1 :])) for k in range(d)])
        for offset in itertools.product((-1, 0, 1), repeat=d):
            other = key + int(np.dot(strides, offset))
            low, high = np.searchsorted(sorted_key, other, "left"), np.searchsorted(sorted_key, other, "right")
            counts = high - low
            i = np.repeat(np.arange(n), counts)
            j = order[np.repeat(low - np.concatenate([[0], np.cumsum(counts)[:-1]]), counts) + np.arange(counts.sum())]
            near = ((points[i] - points[j]) ** 2).sum(axis=1) <= eps * eps * (1 + 1e-12)
            pairs_i.append(i[near])
            pairs_j.append(j[near])
    else:
        for a in range(n):
            j = np.nonzero(((points - points[a]) ** 2).sum(axis=1) <= eps * eps * (1 + 1e-12))[0]
            pairs_i.append(np.full(len(j), a))
            pairs_j.append(j)
    return np.concatenate(pairs_i), np.concatenate(pairs_j)


def cluster_points(points: np.ndarray, eps: float, min_pts: int) -> tuple[np.ndarray, np.ndarray]:
    """Labels and core flags of points in the order given (numbering follows that order). Cells of side eps bound the search."""
    n = len(points)
    if not n:
        return np.empty(0, int), np.empty(0, bool)
    i, j = _near_all(points, eps) if n <= 64 else _near_cells(points, eps)
    core = np.bincount(i, minlength=n) >= min_pts
    both = core[i] & core[j]
    root = np.arange(n)
    while True:
        low = root.copy()
        np.minimum.at(low, i[both], root[j[both]])
        low = np.minimum(low, low[low])
        if np.array_equal(low, root):
            break
        root = low
    label = np.full(n, -1)
    heads = np.unique(root[core])
    label[core] = np.searchsorted(heads, root[core])
    edge = ~core[i] & core[j]
    if edge.any():
        bi, bj = i[edge], j[edge]
        dist = ((points[bi] - points[bj]) ** 2).sum(axis=1)
        pick = np.lexsort((label[bj], dist, bi))
        first = np.concatenate([[True], bi[pick][1:] != bi[pick][:-1]])
        label[bi[pick][first]] = label[bj[pick][first]]
    return label, core


def group(df: DataFrame, by, dims: dict[str, float], eps: float = 1.0, min_pts: int = 10, tie=("src_id",)) -> DataFrame:
    """+ is_core, cluster_id, per group in one Python node. Groups are cart-days (at most a few hundred thousand rows)."""
    names, scales = list(dims), np.array(list(dims.values()), dtype=float)
    added = T.StructType().add("is_core", T.BooleanType()).add("cluster_id", T.LongType())

    def step(*values):
        label, core = cluster_points(np.stack(values, axis=1) / scales, eps, min_pts)
        return core, label

    return add_columns(df, by, [names[0], *tie], names, added, step)


def grid(df: DataFrame, by, dims: dict[str, float], eps: float = 1.0, min_pts: int = 10, id_col: str = "src_id", max_rounds: int = 60) -> DataFrame:
    """+ is_core, cluster_id for groups too large for one task.

    Points meet only points of cells within reach, by an equi-join on cells; cores are
    linked cell by cell, and labels spread over the graph of cells. ``id_col`` is unique in a group.
    Cells hold at most as many compared points as their neighbourhood; cells of at
    least min_pts points are all core and enter the joins once per cell instead.
    """
    from ..plans.shared import keep

    by, names = list(by), list(dims)
    d = len(names)
    side = eps / math.sqrt(d)
    p = [f"_p{k}" for k in range(d)]
    c = [f"_c{k}" for k in range(d)]
    pts = df.select(*by, id_col, *[(F.col(n) / F.lit(float(s))).alias(q) for (n, s), q in zip(dims.items(), p)], F.col(names[0]).alias("_order"))
    pts = keep(pts.withColumns({x: F.floor(F.col(q) / side).cast("long") for x, q in zip(c, p)}))
    reach = math.ceil(math.sqrt(d))
    offsets = [o for o in itertools.product(range(-reach, reach + 1), repeat=d) if sum(max(0, abs(x) - 1) ** 2 for x in o) <= d]
    shifted = F.array(*[F.struct(*[(F.col(x) + v).alias(x) for x, v in zip(c, o)]) for o in offsets])
    cell_n = keep(pts.groupBy(*by, *c).agg(F.count(F.lit(1)).alias("_n")))
    full = cell_n.where(F.col("_n") >= min_pts)
    loose = pts.join(full.select(*by, *c), [*by, *c], "left_anti")
    square = lambda a, b: sum(((F.col(f"{a}.{q}") - F.col(f"{b}.{q}")) ** 2 for q in p), F.lit(0.0)) <= eps * eps * (1 + 1e-12)
    ask = loose.select(*by, F.struct(id_col, *p).alias("a"), F.inline(shifted))
    found = ask.join(pts.select(*by, *c, F.struct(id_col, *p).alias("b")), [*by, *c]).where(square("a", "b"))
    counted = found.groupBy(*by, F.col(f"a.{id_col}").alias(id_col)).agg(F.count(F.lit(1)).alias("_near")).where(F.col("_near") >= min_pts)
    core = keep(pts.join(full.select(*by, *c), [*by, *c], "left_semi").unionByName(pts.join(counted, [*by, id_col], "left_semi").select(*pts.columns)))
    # Cells with cores are nodes: all cores of a cell are within eps of each other.
    node = F.struct(*[F.col(x) for x in c])
    core_cells = core.select(*by, *c).distinct().withColumn("label", node)
    other = core.select(*by, F.struct(*[F.col(x) for x in c]).alias("from_cell"), F.struct(id_col, *p).alias("a"), F.inline(shifted))
    links = other.join(core.select(*by, *c, F.struct(id_col, *p).alias("b")), [*by, *c]).where(square("a", "b"))
    links = keep(links.select(*by, "from_cell", F.struct(*[F.col(x) for x in c]).alias("to_cell")).distinct())
    labels = keep(core_cells.select(*by, node.alias("cell"), "label"))
    for _ in range(max_rounds):
        offered = links.join(labels.withColumnRenamed("cell", "to_cell"), [*by, "to_cell"]).groupBy(*by, F.col("from_cell").alias("cell")).agg(F.min("label").alias("offer"))
        grown = labels.join(offered, [*by, "cell"], "left").select(*by, "cell", F.least("label", "offer").alias("label"), (F.col("offer") < F.col("label")).alias("moved"))
        grown = keep(grown)
        changed = grown.where("moved").limit(1).count()
        head = grown.select(*by, F.col("cell").alias("label"), F.col("label").alias("jump"))
        labels = keep(grown.join(head, [*by, "label"]).select(*by, "cell", F.least("label", "jump").alias("label")))
        if not changed:
            break
    core = core.withColumn("cell", node).join(labels, [*by, "cell"])
    first = core.groupBy(*by, "label").agg(F.min(F.struct("_order", id_col)).alias("_first"))
    number = first.withColumn("cluster_id", F.row_number().over(Window.partitionBy(*by).orderBy("_first")).cast("long") - 1).select(*by, "label", "cluster_id")
    core = keep(core.join(number, [*by, "label"]).select(*by, id_col, *p, *c, "cluster_id"))
    rest = loose.join(core.select(*by, id_col), [*by, id_col], "left_anti").select(*by, F.struct(id_col, *p).alias("a"), F.inline(shifted))
    dist = sum(((F.col(f"a.{q}") - F.col(f"b.{q}")) ** 2 for q in p), F.lit(0.0))
    border = rest.join(core.select(*by, *c, F.struct(id_col, *p, "cluster_id").alias("b")), [*by, *c]).where(square("a", "b"))
    border = border.groupBy(*by, F.col(f"a.{id_col}").alias(id_col)).agg(F.min(F.struct(dist.alias("d"), F.col("b.cluster_id").alias("cluster_id"))).alias("m")).select(*by, id_col, F.col("m.cluster_id").alias("cluster_id"))
    named = core.select(*by, id_col, F.lit(True).alias("is_core"), "cluster_id").unionByName(border.withColumn("is_core", F.lit(False)))
    return df.drop("is_core", "cluster_id").join(named, [*by, id_col], "left").fillna({"is_core": False, "cluster_id": -1})


def chain(df: DataFrame, by, gap, t: str = "t_us", reach: float | None = None, xy=("x", "y"), tie=("src_id",)) -> DataFrame:
    """+ chain_id: a new one where time or distance to the previous sample exceeds the limits."""
    order = Window.partitionBy(*by).orderBy(t, *tie)
    cut = (F.col(t) - F.lag(t).over(order)) > gap
    if reach is not None:
        moved = sum(((F.col(v) - F.lag(v).over(order)) ** 2 for v in xy), F.lit(0.0))
        cut = cut | (moved > reach * reach)
    return df.withColumn("_cut", F.coalesce(cut.cast("long"), F.lit(0))).withColumn("chain_id", F.sum("_cut").over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow))).drop("_cut")


def density_cluster(df: DataFrame, by, dims: dict[str, float], eps: float = 1.0, min_pts: int = 10, strategy: str = "auto", group_rows: int = 1_000_000, tie=("src_id",)) -> DataFrame:
    """Dispatch: line for one dimension, group while the largest group is bounded, else grid."""
    if strategy == "auto":
        if len(dims) == 1:
            strategy = "line"
        else:
            most = df.groupBy(*by).count().agg(F.max("count")).first()[0] or 0
            strategy = "group" if most <= group_rows else "grid"
    if strategy == "line":
        (name, scale), = dims.items()
        return line(df, by, name, eps * scale, min_pts, tie)
    if strategy == "group":
        return group(df, by, dims, eps, min_pts, tie)
    if strategy == "grid":
        return grid(df, by, dims, eps, min_pts, tie[0])
    raise ValueError(f"unknown strategy {strategy}")
