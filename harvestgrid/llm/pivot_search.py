"""Exact top-k by inner product over a pivot-distance index.

Vectors are quantised to integers. With M the largest norm, a vector v gets the
extra component sqrt(M^2 - |v|^2) and a query gets 0; then the squared distance is
|q|^2 + M^2 - 2 q.v, so the largest inner products are the nearest vectors and the
triangle inequality holds.

Index: every vector is keyed by its nearest pivot and its distance to it,
sorted by both, and packed into blocks ("annuli" of one pivot: at most
``block_rows`` consecutive vectors) that know their least and greatest distance. Only vectors of one
length have inner products with each other, so each length has pivots of its own, numbered through; their number
grows with the root of the rows.
Search, for all queries at once, in groups of similar queries:

1. each group visits, per pivot, the annulus nearest its own distance, and takes the
   ``k``-th best score found as a bound for each query;
2. a query's bound gives a radius; by the triangle inequality an annulus [lo, hi]
   of pivot p can hold a better vector only if it meets
   [d(q,p) - r, d(q,p) + r]. Groups visit the annuli that meet it for any member; the
   others are never opened.

Blocks and query groups meet in two steps: first their bounds alone, by an equi-join on the pivot with a range
condition, then the vectors, by the numbers of the group and of the block; so no join of vectors has few keys.
A block's scores are one integer matrix product. Scores are exact: they are
computed in double precision only while all sums stay below 2^52, else in Python
integers (scores beyond a long are held at its ends).

Defined results: vectors that are null, empty, or that hold null or non-finite components take no part; null ids take no
part; a query's candidates are the vectors of its own length; repeated rows are candidates of their own, except that
a query never meets a row of its own id.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import slices, spool, uniform

#: Vectors that the pivots are fitted on, in all; least and most pivots of a length; vectors of a block and of a group of queries.
SAMPLE, PIVOTS, MOST_PIVOTS, BLOCK_ROWS, GROUP_ROWS = 4096, 16, 256, 2048, 256
#: Scores whose bound stays below this are exact in double precision.
EXACT = float(1 << 52)


def quantised(vectors: DataFrame, scale: float = 256.0) -> DataFrame:
    """vec_id and v (array of double holding integers) of the rows that take part."""
    v = F.transform(F.col("embedding"), lambda x: F.floor(F.lit(scale) * x.cast("double")).cast("double"))
    good = F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x.cast("double")) < F.lit(float("inf"))))
    rows = vectors.where(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & (F.size("embedding") > 0) & good)
    return rows.select(F.col("vec_id").cast("long").alias("vec_id"), v.alias("v"))


def spread_points(x: np.ndarray, pivots: int) -> np.ndarray:
    """Up to ``pivots`` points of a sample: far apart first, then means of their neighbours."""
    x = np.unique(x, axis=0)
    chosen, far = [0], np.linalg.norm(x - x[0], axis=1)
    while len(chosen) < min(pivots, len(x)):
        chosen.append(int(far.argmax()))
        far = np.minimum(far, np.linalg.norm(x - x[chosen[-1]], axis=1))
    centres = x[chosen]
    for _ in range(8):
        near = _distances(x, centres).argmin(axis=1)
        centres = np.array([x[near == p].mean(axis=0) if (near == p).any() else centres[p] for p in range(len(centres))])
    return centres


@dataclass
class Pivots:
    """Pivots of one length: points with the extra component, number of the first, largest squared norm of the vectors."""

    points: np.ndarray
    first: int
    top: float


def fit_pivots(rows: DataFrame, asks: DataFrame, pivots: int = PIVOTS, sample: int = SAMPLE) -> dict[int, Pivots]:
    """Pivots by length of vector, for the lengths that queries have, from a bounded sample (rows of lowest hash, ``sample`` in all)."""
    square, size = F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x), F.size("v").alias("width")
    held = rows.select(F.lit(1).alias("n"), size, square.alias("square")).unionByName(asks.select(F.lit(0).alias("n"), size, square.alias("square")))
    held = held.groupBy("width").agg(F.sum("n").alias("n"), F.sum(1 - F.col("n")).alias("asked"), F.max("square").alias("top"))
    widths = {r.width: r for r in held.where("n > 0 and asked > 0").collect()}
    if not widths:
        return {}
    each = max(64, sample // len(widths))
    order = Window.partitionBy("width").orderBy(uniform(F.col("vec_id"), salt="pivot"), "vec_id")
    got: dict[int, list] = {w: [] for w in widths}
    picked = rows.select("vec_id", "v", size).where(F.col("width").isin(list(widths)))
    for r in picked.withColumn("place", F.row_number().over(order)).where(F.col("place") <= each).select("width", "v").toLocalIterator():
        got[r.width].append(r.v)
    out, first = {}, 0
    for w in sorted(widths):
        wanted = min(MOST_PIVOTS, max(pivots, math.isqrt(widths[w].n) // 8))
        out[w] = Pivots(_lifted(spread_points(np.array(got[w], dtype=float), wanted), widths[w].top, False), first, widths[w].top)
        first += len(out[w].points)
    return out


def _lifted(x: np.ndarray, top: float, query: bool) -> np.ndarray:
    last = np.zeros(len(x)) if query else np.sqrt(np.maximum(0.0, top - (x**2).sum(axis=1)))
    return np.concatenate([x, last[:, None]], axis=1)


def _distances(x: np.ndarray, pivots: np.ndarray) -> np.ndarray:
    out = np.empty((len(x), len(pivots)))
    for p, point in enumerate(pivots):
        out[:, p] = np.sqrt(((x - point) ** 2).sum(axis=1))
    return out


def _key_batches(index: dict[int, Pivots], query: bool):
    """vec_id, pivot, dist, v of vectors, by length."""

    def run(batches):
        for batch in slices(batches, 4096):
            column = batch.column(1)
            width = pc.list_value_length(column).to_numpy(zero_copy_only=False)
            for w in np.unique(width):
                if int(w) not in index:
                    continue
                at = pa.array(np.nonzero(width == w)[0])
                x = column.take(at).flatten().to_numpy(zero_copy_only=False).reshape(len(at), int(w))
                of = index[int(w)]
                d = _distances(_lifted(x, of.top, query), of.points)
                near = d.argmin(axis=1)
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).take(at), pa.array((near + of.first).astype(np.int32)), pa.array(d[np.arange(len(x)), near]), pa.array([r.tobytes() for r in x], pa.binary()), pa.array(np.full(len(at), w, np.int32))],
                    names=["vec_id", "pivot", "dist", "v", "width"],
                )

    return run


def _pack_batches(rows: int):
    """Runs of at most ``rows`` sorted vectors of one pivot, packed."""
    kinds = [("pivot", pa.int32()), ("width", pa.int32()), ("lo", pa.float64()), ("hi", pa.float64()), ("ids", pa.list_(pa.int64())), ("vs", pa.binary())]

    def packed(held):
        ids = [h[0] for h in held]
        row = (held[0][1], held[0][4], held[0][2], held[-1][2], ids, b"".join(h[3] for h in held))
        return pa.RecordBatch.from_arrays([pa.array([c], t) for c, (_, t) in zip(row, kinds)], names=[k for k, _ in kinds])

    def run(batches):
        held = []
        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns)):
                if held and (row[1] != held[0][1] or len(held) == rows):
                    yield packed(held)
                    held = []
                held.append(row)
        if held:
            yield packed(held)

    return run


def _packed(keyed: DataFrame, rows: int, tag: str) -> DataFrame:
    ordered = keyed.repartitionByRange("pivot", "dist", "vec_id").sortWithinPartitions("pivot", "dist", "vec_id")
    shape = "pivot int, width int, lo double, hi double, ids array<long>, vs binary"
    return spool(ordered.mapInArrow(_pack_batches(rows), shape).withColumn("block", F.monotonically_increasing_id()), tag)


def _reach_batches(index: dict[int, Pivots]):
    """One row per query group and pivot of its length: the range of distances in which members may find better vectors (without bounds: the members' mean distance)."""
    kinds = [("group", pa.int64()), ("of", pa.int32()), ("near", pa.float64()), ("far", pa.float64())]

    def run(batches):
        for batch in batches:
            for group, width, vs, bounds in zip(*(batch.column(c).to_pylist() for c in ("block", "width", "vs", "bounds"))):
                of = index[width]
                q = np.frombuffer(vs).reshape(-1, width)
                d = _distances(_lifted(q, of.top, True), of.points)
                if bounds is None:
                    low = high = d.mean(axis=0)
                else:
                    both = (q**2).sum(axis=1) + of.top
                    # Slack for rounding: the root of a difference of squares is only good to about 1e-8 of their size.
                    reach = np.sqrt(np.maximum(0.0, both - 2 * np.frombuffer(bounds))) + 1e-6 * np.sqrt(both) + 1e-9
                    low, high = (d - reach[:, None]).min(axis=0), (d + reach[:, None]).max(axis=0)
                columns = (np.full(len(low), group), np.arange(len(low)) + of.first, low, high)
                yield pa.RecordBatch.from_arrays([pa.array(c).cast(t) for c, (_, t) in zip(columns, kinds)], names=[k for k, _ in kinds])

    return run


def _score_batches(index: dict[int, Pivots], k: int):
    """The k best of one block for each query of one group, as far as they reach the query's bound."""

    def run(batches):
        for batch in batches:
            for width, ids, vs, bounds, cand_ids, cand in zip(*(c.to_pylist() for c in batch.columns)):
                q, v = np.frombuffer(vs).reshape(-1, width), np.frombuffer(cand).reshape(-1, width)
                qi, vi = np.array(ids), np.array(cand_ids)
                exact_all = index[width].top * 1.01 < EXACT
                if exact_all:
                    s = q @ v.T
                else:
                    s = np.array([[int(x) for x in r] for r in q], dtype=object) @ np.array([[int(x) for x in r] for r in v], dtype=object).T
                    s = np.clip(s, -(2**63), 2**63 - 1)
                bound = np.full(len(q), -np.inf) if bounds is None else np.frombuffer(bounds)
                bound = bound if exact_all else bound - np.abs(bound) * 1e-15
                open_ = (s >= bound[:, None]) & (qi[:, None] != vi[None, :])
                out = ([], [], [])
                for r in np.nonzero(open_.any(axis=1))[0]:
                    c = np.nonzero(open_[r])[0]
                    if len(c) > k:
                        least = np.partition(s[r, c], len(c) - k)[len(c) - k] if exact_all else sorted(s[r, c])[-k]
                        c = c[s[r, c] >= least]
                        c = np.array(sorted(c, key=lambda j: (-s[r, j], vi[j]))[:k])
                    out[0].extend([qi[r]] * len(c))
                    out[1].extend(vi[c])
                    out[2].extend(int(x) for x in s[r, c])
                if out[0]:
                    yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in out], names=["query_id", "vec_id", "score"])

    return run


_SCORED = "query_id long, vec_id long, score long"


def _best(scored: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return scored.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def _bounded(groups: DataFrame, first: DataFrame, k: int) -> DataFrame:
    """Groups with each member's k-th best score so far (minus infinity where fewer were found)."""
    kth = first.where(F.col("rank") == k).select("query_id", "score")
    member = groups.select("block", F.posexplode("ids").alias("pos", "query_id"))
    bound = F.struct("pos", F.coalesce(F.col("score").cast("double"), F.lit(float("-inf"))).alias("b"))
    bounds = member.join(kth, "query_id", "left").groupBy("block").agg(F.array_sort(F.collect_list(bound)).alias("bs"))
    return groups.join(bounds.select("block", F.col("bs.b").alias("bs")), "block")


def top_k(
    vectors: DataFrame, queries: DataFrame, k: int = 5, scale: float = 256.0, pivots: int = PIVOTS, sample: int = SAMPLE,
    block_rows: int = BLOCK_ROWS, group_rows: int = GROUP_ROWS,
) -> DataFrame:
    """query_id, rank, vec_id, score: the k vectors of largest inner product, ties to the smaller id, for every query."""
    spark = vectors.sparkSession
    rows, asks = quantised(vectors, scale), quantised(queries, scale)
    index = fit_pivots(rows, asks, pivots, sample)
    if not index:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    keys = "vec_id long, pivot int, dist double, v binary, width int"
    blocks = _packed(rows.mapInArrow(_key_batches(index, False), keys), block_rows, "blocks")
    groups = _packed(asks.mapInArrow(_key_batches(index, True), keys), group_rows, "groups")

    score, columns = _score_batches(index, k), ["width", "ids", "vs", "bounds", "cand_ids", "cand"]
    cand = blocks.select(F.col("block").alias("pick"), F.col("ids").alias("cand_ids"), F.col("vs").alias("cand"))
    rings = blocks.select(F.col("block").alias("pick"), "pivot", "lo", "hi")
    shape = "group long, of int, near double, far double"

    # 1. The nearest annulus of each pivot bounds every member.
    start = groups.withColumn("bounds", F.lit(None).cast("binary"))
    gap = F.greatest(F.col("lo") - F.col("near"), F.col("near") - F.col("hi"), F.lit(0.0))
    nearest = start.mapInArrow(_reach_batches(index), shape).join(rings, F.col("of") == F.col("pivot"))
    nearest = nearest.groupBy("group", "of").agg(F.min(F.struct(gap.alias("gap"), "lo", "pick")).alias("b")).select("group", F.col("b.pick").alias("pick"))
    home = spool(nearest, "home").join(cand, "pick").join(start.withColumnRenamed("block", "group"), "group")
    first = spool(_best(home.select(*columns).mapInArrow(score, _SCORED), k), "first")

    # 2. Annuli that the bounds don't exclude.
    bounded = spool(_bounded(groups.select("block", "width", "ids", "vs"), first, k).mapInArrow(_pack_bounds, "block long, width int, ids array<long>, vs binary, bounds binary"), "bounded")
    reach = spool(bounded.mapInArrow(_reach_batches(index), shape), "reach")
    meet = spool(reach.join(rings, (F.col("of") == F.col("pivot")) & (F.col("hi") >= F.col("near")) & (F.col("lo") <= F.col("far"))).select("group", "pick"), "meet")
    open_ = meet.join(cand, "pick").join(bounded.withColumnRenamed("block", "group"), "group")
    scored = open_.select(*columns).mapInArrow(score, _SCORED)
    return _best(scored, k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def _pack_bounds(batches):
    for batch in batches:
        bounds = pa.array([np.array(b, dtype=float).tobytes() for b in batch.column("bs").to_pylist()], pa.binary())
        held = [batch.column(c) for c in ("block", "width", "ids", "vs")]
        yield pa.RecordBatch.from_arrays([*held, bounds], names=["block", "width", "ids", "vs", "bounds"])
