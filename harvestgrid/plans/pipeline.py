"""The whole chain from samples to season maps; every stage's table by name.

Only logical plans are built, except where a strategy must write a small table. One
exchange by (field, session, cart) serves the steps on samples; conflicts are resolved
on segments, which are thousands of times fewer.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import activity, cluster, completion, direction, geometry, gridmap, interpolate, mass, occupancy, rows, season, trays
from ..params import DEFAULT, Params
from .shared import keep

STEPS = ("activity", "cluster", "rows", "completion", "occupancy", "mass", "trays", "yield", "daily", "season")


def run(trace: DataFrame, grid: gridmap.Grid, params: Params = DEFAULT, upto: str = "season", skip: tuple[str, ...] = (), model=None, polygon=None, row_map: DataFrame | None = None, strategy: str = "group") -> dict[str, DataFrame]:
    """Stage tables by name. For ablations ``skip`` leaves out activity, cluster, completion, occupancy, stable (the rate bound of the
    load) or interpolation, or takes trays by resets of the load (trays) instead of clusters.

    ``model`` scores windows (fit, transform); without it samples of the state picking are kept, if there is a state.
    """
    cart = ("field_id", "session", "cart_id")
    out: dict[str, DataFrame] = {}
    df = geometry.clip_to_boundary(trace, polygon) if polygon else trace
    if "activity" not in skip:
        if model is not None:
            windows = activity.make_windows(activity.with_velocity(df, cart).withColumn("label", F.lit("Pick")), params.window_size, by=cart)
            df = activity.keep_picking(model.transform(windows), df)
        elif "state" in df.columns:
            df = df.where("state = 'picking'")
    df = out["activity"] = df.repartition(*cart)
    if upto == "activity":
        return out
    if "cluster" in skip:
        df = df.withColumn("row_idx", rows.nearest_row(F.col("x"), F.col("spacing")))
    else:
        dims = {"t_us": params.scale_t * 1e6, "x": params.scale_x, "y": params.scale_y}
        clustered = out["cluster"] = cluster.density_cluster(df, cart, dims, params.eps, params.min_pts, strategy)
        df = rows.write_back(clustered, rows.assign_rows(clustered, row_map, cart, noise="drop"), cart).where("row_idx is not null")
    # Clustering runs once; its rows feed the directions, the repairs and the load.
    df = out["rows"] = keep(df) if upto not in ("cluster", "rows") and not {"completion", "occupancy"} <= set(skip) else df
    if upto in ("cluster", "rows"):
        return out
    if "completion" not in skip or "occupancy" not in skip:
        order = ("t_us", "src_id")
        cap = int(params.gap_cap_s * 1e6)
        if "completion" not in skip:
            # Written once: the repair, its map and the segments after it all start from these few rows.
            seg = out["segments"] = keep(completion.segments(travel(df, cart, params), cart, order, t="t_us", gap_cap=cap, signed="direction"))
            moves = out["moves"] = keep(completion.remap(seg, cart, direction="direction_sig", weight="dwell_s", interleaving=params.require_interleaving))
            df = completion.write_back(df, moves, cart).withColumn("row_idx", F.col("row_idx_new")).drop("row_idx_new")
            seg = out["segments_repaired"] = completion.merged(seg, moves, cart)
        else:
            seg = out["segments"] = keep(completion.segments(df, cart, order, t="t_us", gap_cap=cap).withColumn("dwell_s", F.coalesce("dwell_s", F.lit(0))))
        out["completion"] = df
        if "occupancy" not in skip:
            final = out["final"] = keep(occupancy.resolve(seg, ("field_id", "session"), params.overlap_m, "dwell_s"))
            df = occupancy.apply(df, final, cart)
        out["occupancy"] = df
    if upto in ("completion", "occupancy"):
        return out
    if "stable" in skip:
        df = mass.median_smooth(mass.in_range(df, params.w_min, params.w_max), params.median_half, cart)
    else:
        df = mass.clean(df, params.w_min, params.w_max, params.max_rate, params.median_half, cart, strict_positive=not params.keep_plateaus)
    df = out["mass"] = df.withColumn("w", F.col("w_smooth"))
    if "trays" in skip:
        df = trays.by_mass_reset(df, 1.0, cart)
    else:
        dims = {"t_us": params.tray_scale_t * 1e6, "y": params.tray_scale_y, "w": params.tray_scale_w, "row_idx": params.tray_scale_row}
        df = trays.separate(df, cart, dims, params.eps, params.tray_min_pts, strategy).where("tray_id >= 0")
    out["trays"] = df
    keys = (*cart, "tray_id", "row_idx", "spacing")
    if "interpolation" in skip:
        from ..operators.baselines import staircase_yield

        points = staircase_yield(df, keys, ("t_us", "src_id")).where("dmass is not null").withColumn("y_int", F.col("y"))
    else:
        fits = interpolate.choose_degree(interpolate.fit_polynomials(df, keys, max_degree=params.max_degree), params.min_score, params.max_degree)
        points = interpolate.increments(fits, params.step_m, tail="keep")
    points = out["yield"] = points.withColumn("row_x", F.col("row_idx") * F.col("spacing"))
    daily = out["daily"] = gridmap.daily_map(points, grid, ("field_id", "session")).withColumnRenamed("session", "day")
    out["season"] = season.classify(season.accumulate(daily))
    return out


def travel(df: DataFrame, cart=("field_id", "session", "cart_id"), params: Params = DEFAULT) -> DataFrame:
    """Samples with outlier-filtered y and the direction of travel, per row of a cart."""
    return direction.filtered_direction(df, [*cart, "row_idx"], ["t_us", "src_id"], "y", params.hampel_half, params.hampel_sigma, params.mad_floor, params.prominence_m, params.peak_distance)


def effects(out: dict[str, DataFrame], params: Params = DEFAULT) -> DataFrame:
    """step, samples_in, samples_out, moved, violations_before, violations_after of the steps that ran.

    Violations of step 3 are neighbouring rows of a cart worked in one direction, those of step 4 pairs of carts that overlap in a row.
    """
    cart = ("field_id", "session", "cart_id")
    count = lambda df, what=F.lit(1): df.agg(F.count(what).cast("long").alias("x"))
    rows = []
    chain = [k for k in ("activity", "rows", "completion", "occupancy", "mass", "trays") if k in out]
    for before, after in zip(chain, chain[1:]):
        rows += [(after, "samples_in", count(out[before])), (after, "samples_out", count(out[after]))]
    if "moves" in out:
        groups = lambda seg: count(completion.violations(completion.adjacent_groups(seg, cart, direction="direction_sig", weight="dwell_s")))
        moved = out["segments"].join(out["moves"], [*cart, "row_idx"]).where("moved_flag = 1")
        again = completion.segments(travel(out["completion"], cart, params), cart, ("t_us", "src_id"), t="t_us", gap_cap=int(params.gap_cap_s * 1e6), signed="direction")
        rows += [("completion", "moved", moved.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("x"))), ("completion", "violations_before", groups(out["segments"])), ("completion", "violations_after", groups(again))]
    if "final" in out:
        seg = out.get("segments_repaired", out["segments"])
        moved = seg.join(out["final"].where("status = 'moved'"), [*cart, "row_idx"])
        clash = lambda s: occupancy.count_conflicts(s, params.overlap_m, by=("field_id", "session"))
        new = seg.join(out["final"], [*cart, "row_idx"]).groupBy(*cart, F.col("row_idx_final").alias("row_idx")).agg(F.min("y_min").alias("y_min"), F.max("y_max").alias("y_max"))
        rows += [("occupancy", "moved", moved.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("x"))), ("occupancy", "violations_before", clash(seg)), ("occupancy", "violations_after", clash(new))]
    long = None
    for step, what, one in rows:
        one = one.select(F.lit(step).alias("step"), F.lit(what).alias("what"), "x")
        long = one if long is None else long.unionByName(one)
    return long.groupBy("step").pivot("what", ["samples_in", "samples_out", "moved", "violations_before", "violations_after"]).agg(F.first("x"))
