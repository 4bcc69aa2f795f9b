"""Row completion: a picker finishes a row before the next, so neighbouring rows worked in one direction at once are mis-assignments."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def segments(trace: DataFrame, by=("cart_id", "session"), order=("t",), y: str = "y", t: str | None = None, gap_cap: float | None = None, signed: str | None = None) -> DataFrame:
    """Per cart, day and row: samples, dwell, extent of y, direction (sign of displacement, or the run-compressed signature of ``signed``)."""
    key = F.struct(*order)
    group = [*by, "row_idx"]
    aggs = [F.count(F.lit(1)).alias("n"), F.min(y).alias("y_min"), F.max(y).alias("y_max"), F.min_by(y, key).alias("_a"), F.max_by(y, key).alias("_b")]
    if t is not None:
        step = F.lead(t).over(Window.partitionBy(*by).orderBy(*order)) - F.col(t)
        trace = trace.withColumn("_step", F.least(step, F.lit(gap_cap)) if gap_cap is not None else step)
        aggs += [F.sum("_step").alias("dwell_s"), F.min(t).alias("t_lo"), F.max(t).alias("t_hi")]
    if signed is not None:
        w = Window.partitionBy(*group).orderBy(*order)
        trace = trace.withColumn("_turn", F.when(F.coalesce(F.col(signed) != F.lag(signed).over(w), F.lit(True)), F.col(signed)))
        aggs.append(F.transform(F.array_sort(F.collect_list(F.when(F.col("_turn").isNotNull(), F.struct(key.alias("k"), F.col("_turn").alias("s"))))), lambda z: z["s"]).alias("direction_sig"))
    out = trace.groupBy(*group).agg(*aggs)
    return out.withColumn("direction", F.when(F.col("_b") >= F.col("_a"), 1).otherwise(-1)).drop("_a", "_b")


def adjacent_groups(seg: DataFrame, by=("cart_id", "session"), direction: str = "direction", weight: str = "n", interleaving: bool = False) -> DataFrame:
    """Pairs and triplets of neighbouring rows of a cart: first row, size, whether directions agree, dominant row.

    ``interleaving`` asks in addition that the rows' times overlap (rows picked one after the other are then legal).
    """
    w = Window.partitionBy(*by).orderBy("row_idx")
    times = ["t_lo", "t_hi"] if interleaving else []
    cols = [F.struct("row_idx", F.col(direction).alias("d"), F.col(weight).alias("w"), *times)]
    lead = lambda k: F.lead(cols[0], k).over(w)
    s = seg.select(*by, "row_idx", F.col(direction).alias("_d"), cols[0].alias("_a"), lead(1).alias("_b"), lead(2).alias("_c"))

    def shared(*names):
        if not interleaving:
            return F.lit(True)
        return F.greatest(*[F.col(f"{n}.t_lo") for n in names]) <= F.least(*[F.col(f"{n}.t_hi") for n in names])

    # Most weight wins; ties go to the lower row.
    best = lambda *names: F.array_max(F.array(*[F.struct(F.col(f"{n}.w").alias("w"), (-F.col(f"{n}.row_idx")).alias("r")) for n in names]))["r"] * -1
    two = F.col("_b.row_idx") == F.col("row_idx") + 1
    three = two & (F.col("_c.row_idx") == F.col("row_idx") + 2)
    pair = F.when(two, F.struct(F.lit(2).alias("size"), ((F.col("_b.d") == F.col("_d")) & shared("_a", "_b")).alias("same_direction"), best("_a", "_b").alias("dominant")))
    trio = F.when(three, F.struct(F.lit(3).alias("size"), ((F.col("_b.d") == F.col("_d")) & (F.col("_c.d") == F.col("_d")) & shared("_a", "_b", "_c")).alias("same_direction"), best("_a", "_b", "_c").alias("dominant")))
    return s.select(*by, "row_idx", F.inline(F.filter(F.array(pair, trio), lambda g: g.isNotNull())))


def violations(groups: DataFrame) -> DataFrame:
    """Groups whose rows are all worked in the same direction; opposite directions are legal."""
    return groups.where("same_direction")


def remap(seg: DataFrame, by=("cart_id", "session"), **options) -> DataFrame:
    """by, row_idx, row_idx_new, moved_flag for every segment.

    Each violating group sends its rows to its dominant row. A triplet beats a pair,
    a later group beats an earlier one of its size; a target that itself moves on is followed once.
    """
    bad = violations(adjacent_groups(seg, by, **options))
    moves = bad.select(*by, F.col("row_idx").alias("_start"), "size", "dominant", F.explode(F.sequence(F.lit(0), F.col("size") - 1)).alias("_k"))
    moves = moves.select(*by, (F.col("_start") + F.col("_k")).alias("row_idx"), "size", "_start", "dominant")
    # The winning group of each row decides, whether it moves the row or names it the target.
    target = moves.groupBy(*by, "row_idx").agg(F.max_by("dominant", F.struct("size", "_start")).alias("_to"))
    packed = target.groupBy(*by).agg(F.map_from_entries(F.collect_list(F.struct("row_idx", "_to"))).alias("_map"))
    go = lambda row: F.coalesce(F.col("_map")[row], row)
    once = seg.select(*by, "row_idx").join(packed, list(by), "left").withColumn("_to", go(F.col("row_idx"))).withColumn("_next", go(F.col("_to")))
    new = F.when(F.col("_next") == F.col("row_idx"), F.col("_to")).otherwise(F.col("_next"))
    return once.select(*by, "row_idx", new.cast("int").alias("row_idx_new")).withColumn("moved_flag", (F.col("row_idx_new") != F.col("row_idx")).cast("int"))


def merged(seg: DataFrame, moves: DataFrame, by=("cart_id", "session"), weight: str = "dwell_s") -> DataFrame:
    """Segments after the repair, from those before it: no second pass over samples.

    second_idx is the row that most of a segment's moved samples came from (null where none moved).
    """
    rows = seg.join(moves, [*by, "row_idx"])
    came = F.when(F.col("row_idx") != F.col("row_idx_new"), F.struct(F.coalesce(weight, F.lit(0)).alias("w"), (-F.col("row_idx")).alias("r")))
    out = rows.groupBy(*by, F.col("row_idx_new").alias("row_idx")).agg(
        F.sum("n").alias("n"), F.min("y_min").alias("y_min"), F.max("y_max").alias("y_max"), F.coalesce(F.sum(weight), F.lit(0)).alias(weight),
        F.max("moved_flag").alias("moved_flag"), F.max(came).alias("_came"),
    )
    return out.withColumn("second_idx", -F.col("_came.r")).drop("_came")


def write_back(trace: DataFrame, mapping: DataFrame, by=("cart_id", "session"), new: str = "row_idx_new") -> DataFrame:
    """+ row_idx_new, moved_flag on samples: the mapping packed to one map per cart-day and joined on exactly that key."""
    packed = mapping.groupBy(*by).agg(F.map_from_entries(F.collect_list(F.struct("row_idx", new))).alias("_map"))
    out = trace.join(packed, list(by), "left").withColumn(new, F.coalesce(F.col("_map")[F.col("row_idx")], F.col("row_idx")))
    return out.withColumn("moved_flag", (F.col(new) != F.col("row_idx")).cast("int")).drop("_map")
