"""Row occupancy: two carts whose stretches of a row overlap can't both be right."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def overlap_1d(a_lo: Column, a_hi: Column, b_lo: Column, b_hi: Column) -> Column:
    return F.greatest(F.lit(0.0), F.least(a_hi, b_hi) - F.greatest(a_lo, b_lo))


def overlaps(seg: DataFrame, by=("session",), respect_time: bool = False, respect_direction: bool = False, keep=("n", "moved_flag")) -> DataFrame:
    """Pairs of carts in one row whose extents overlap: an equi-join of segments (never samples) on day and row."""
    side = lambda p: seg.select(*by, "row_idx", *[F.col(c).alias(f"{p}_{c}") for c in seg.columns if c not in (*by, "row_idx")])
    pairs = side("a").join(side("b"), [*by, "row_idx"]).where("a_cart_id < b_cart_id")
    if respect_time:
        pairs = pairs.where("a_t_lo <= b_t_hi and b_t_lo <= a_t_hi")
    if respect_direction:
        pairs = pairs.where("a_direction = b_direction")
    metres = overlap_1d(F.col("a_y_min"), F.col("a_y_max"), F.col("b_y_min"), F.col("b_y_max"))
    extra = [f"{p}_{c}" for p in "ab" for c in keep if c in seg.columns]
    return pairs.select(*by, "row_idx", F.col("a_cart_id").alias("cart_a"), F.col("b_cart_id").alias("cart_b"), metres.alias("overlap_m"), *extra).where("overlap_m > 0")


def conflicts(seg: DataFrame, min_overlap_m: float = 5.0, **options) -> DataFrame:
    return overlaps(seg, **options).where(F.col("overlap_m") > min_overlap_m)


def count_conflicts(seg: DataFrame, min_overlap_m: float = 5.0, by=("session",)) -> DataFrame:
    """One row x: the number of rows of ``conflicts``, counted without making a pair; each cart once per row, with its extent."""
    groups = [*by, "row_idx"]

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"x": [overlapping_pairs(pdf["y_min"].to_numpy(float), pdf["y_max"].to_numpy(float), min_overlap_m)]})

    counts = seg.select(*groups, "y_min", "y_max").groupBy(*groups).applyInPandas(run, "x long")
    return counts.agg(F.coalesce(F.sum("x"), F.lit(0)).cast("long").alias("x"))


def overlapping_pairs(lo: np.ndarray, hi: np.ndarray, least: float) -> int:
    """Pairs of intervals with min(hi) - max(lo) > least, by sorting: those that began before, less those that have ended."""
    long = hi - lo > least
    lo, hi = np.sort(lo[long]), hi[long]
    ends, times = np.unique(hi, return_counts=True)
    # Ends with end - lo <= least; the sum may round, so the place found is moved until the difference itself agrees.
    k = np.searchsorted(ends, lo + least, "right")
    for _ in range(len(ends)):
        up = (k < len(ends)) & (np.append(ends, np.inf)[np.minimum(k, len(ends))] - lo <= least)
        down = (k > 0) & (ends[np.maximum(k, 1) - 1] - lo > least) if len(ends) else up
        if not (up | down).any():
            break
        k = k + up - (down & ~up)
    ended = np.concatenate([[0], np.cumsum(times)])[k]
    return int((np.arange(len(lo)) - ended).sum())


def choose_loser(pairs: DataFrame, weight: str = "n") -> DataFrame:
    """+ loser: the cart moved in the step before if exactly one was, else the one with less time in the row (tie: the second)."""
    by_time = F.when(F.col(f"a_{weight}") < F.col(f"b_{weight}"), F.col("cart_a")).otherwise(F.col("cart_b"))
    if "a_moved_flag" in pairs.columns:
        one = F.col("a_moved_flag") != F.col("b_moved_flag")
        by_time = F.when(one, F.when(F.col("a_moved_flag") == 1, F.col("cart_a")).otherwise(F.col("cart_b"))).otherwise(by_time)
    return pairs.withColumn("loser", by_time)


def resolve_day(segs: list[dict], min_overlap: float, weight: str, rows: set[int] | None, max_rounds: int) -> dict[tuple[int, int], tuple[int, str]]:
    """Sequential repair of one field-day on its segments: (cart, row) -> (final row, status).

    Conflicts go in order of row and carts and are checked again before each move,
    as moves change who is where. Candidates: the cart's second-largest row, the rows beside the
    conflict row, the rows beside that second row; the first where the cart would conflict with nobody. A segment with
    ``second_idx`` (where most of its moved samples came from) takes that for the second row. A segment without extent conflicts with nobody.
    Time grows as the square of the carts in a row, in numpy only; a segment is tried once per row and round.
    """
    of = {(s["cart_id"], s["row_idx"]): s for s in segs}
    keys = sorted(of)
    segments = [of[k] for k in keys]
    column = lambda c, kind=float: np.array([s[c] for s in segments], dtype=kind)
    cart, lo, hi, load = column("cart_id", np.int64), column("y_min"), column("y_max"), column(weight)
    flag = np.array([s.get("moved_flag", 0) for s in segments])
    place, status = [k[1] for k in keys], ["kept"] * len(keys)
    shares: dict[int, list[int]] = {}
    for s in sorted(segs, key=lambda s: (-s[weight], s["row_idx"])):
        two = shares.setdefault(s["cart_id"], [])
        if len(two) < 2 and s["row_idx"] not in two:  # a second row that isn't the conflict row is among the first two
            two.append(s["row_idx"])
    in_row: dict[int, _Row] = {}
    for k, row in enumerate(place):
        in_row.setdefault(row, _Row()).add(k, cart[k], lo[k], hi[k])

    def free(k, row):
        if row < 0 or rows is not None and row not in rows:
            return False
        return row not in in_row or not in_row[row].clashes(cart[k], lo[k], hi[k], min_overlap)

    def move(k, row) -> bool:
        """Moves segment k out of a row, if one of its candidates is free."""
        came = segments[k].get("second_idx")
        second = int(came) if came is not None and came == came else next((r for r in shares[keys[k][0]] if r != row), None)
        wish = [second, row - 1, row + 1, *([second - 1, second + 1] if second is not None else [])]
        target = next((r for r in wish if r is not None and r != row and free(k, r)), None)
        if target is None:
            status[k] = "unresolved"
            return False
        in_row[row].drop(k)
        in_row.setdefault(target, _Row()).add(k, cart[k], lo[k], hi[k])
        place[k], status[k] = target, "moved"
        return True

    for _ in range(max_rounds):
        moved = False
        for row in sorted(in_row):
            here = np.array(sorted(in_row[row].at), dtype=int)
            c, a, b, w, f = cart[here], lo[here], hi[here], load[here], flag[here]
            # While a row is worked on, the other rows only fill up: a segment that found no place needn't be tried again.
            there, stuck = np.ones(len(here), dtype=bool), np.zeros(len(here), dtype=bool)
            for i in range(len(here) - 1):
                if not there[i]:
                    continue
                after = slice(i + 1, None)
                meets = (np.minimum(b[after], b[i]) - np.maximum(a[after], a[i]) > min_overlap) & there[after]
                j = np.nonzero(meets if not stuck[i] else meets & ~stuck[after])[0] + i + 1
                j = j[c[j] != c[i]]
                if not len(j):
                    continue
                loses = np.where(f[j] != f[i], bool(f[i]), w[i] < w[j])
                for k, own in zip(j[(loses & ~stuck[i]) | (~loses & ~stuck[j])].tolist(), loses[(loses & ~stuck[i]) | (~loses & ~stuck[j])].tolist()):
                    lost = i if own else k
                    if stuck[lost]:
                        continue
                    if move(here[lost], row):
                        there[lost], moved = False, True
                        if own:
                            break
                    else:
                        stuck[lost] = True
        if not moved:
            break
    return {k: (place[n], status[n]) for n, k in enumerate(keys)}


class _Row:
    """Segments in one row: who is there, and their extents as arrays that grow by doubling."""

    def __init__(self):
        self.at: dict[int, int] = {}
        self.n = 0
        self.cart, self.lo, self.hi = np.zeros(8, np.int64), np.zeros(8), np.zeros(8)

    def add(self, k, cart, lo, hi):
        if self.n == len(self.lo):
            self.cart, self.lo, self.hi = (np.concatenate([x, np.zeros_like(x)]) for x in (self.cart, self.lo, self.hi))
        self.at[k], self.cart[self.n], self.lo[self.n], self.hi[self.n] = self.n, cart, lo, hi
        self.n += 1

    def drop(self, k):
        at = self.at.pop(k)
        self.lo[at], self.hi[at] = np.inf, -np.inf  # overlaps nothing

    def clashes(self, cart, lo, hi, least) -> bool:
        n = self.n
        meets = np.minimum(self.hi[:n], hi) - np.maximum(self.lo[:n], lo) > least
        return bool((meets & (self.cart[:n] != cart)).any())


def resolve(seg: DataFrame, by=("session",), min_overlap_m: float = 5.0, weight: str = "n", rows: list[int] | None = None, max_rounds: int = 3) -> DataFrame:
    """by, cart_id, row_idx, row_idx_final, status. One Python call per field-day, on its segments (carts x rows), never on samples."""
    by = list(by)
    fields = [seg.schema[c] for c in by]
    schema = ", ".join([*(f"{f.name} {f.dataType.simpleString()}" for f in fields), "cart_id long, row_idx int, row_idx_final int, status string"])
    known = set(rows) if rows is not None else None
    cols = ["cart_id", "row_idx", "y_min", "y_max", weight, *[c for c in ("moved_flag", "second_idx") if c in seg.columns]]

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        found = resolve_day(pdf[cols].to_dict("records"), min_overlap_m, weight, known, max_rounds)
        out = pd.DataFrame([(c, r, f, s) for (c, r), (f, s) in found.items()], columns=["cart_id", "row_idx", "row_idx_final", "status"])
        for k, name in enumerate(by):
            out.insert(k, name, pdf[name].iloc[0])
        return out

    # A number of partitions of its own: adaptive execution would put all field-days, small as tables go, into one task.
    days = seg.select(*by, *cols).repartition(max(64, int(seg.sparkSession.conf.get("spark.sql.shuffle.partitions"))), *by)
    return days.groupBy(*by).applyInPandas(run, schema)


def apply(trace: DataFrame, final: DataFrame, by=("session", "cart_id")) -> DataFrame:
    """Samples with row_idx replaced by the final row, through one map per cart-day."""
    packed = final.groupBy(*by).agg(F.map_from_entries(F.collect_list(F.struct("row_idx", "row_idx_final"))).alias("_map"))
    return trace.join(packed, list(by), "left").withColumn("row_idx", F.coalesce(F.col("_map")[F.col("row_idx")], F.col("row_idx"))).drop("_map")
