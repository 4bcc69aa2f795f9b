"""DuckDB SQL for the workload queries, over the same tables. Shared parts are CTEs in front."""

from __future__ import annotations

TRACE = """
trace AS (
 SELECT (user_id % 2)::INTEGER AS field_id, ((day(ts) - 1) // 10)::INTEGER AS session, user_id AS cart_id, epoch_us(ts) AS t_us, spacing,
   ((7 * user_id) % 40)::DOUBLE * spacing + (((37 * event_id) % 101 - 50)::DOUBLE / 100.0::DOUBLE) * 1.2::DOUBLE * spacing AS x,
   0.5::DOUBLE * json_extract_string(props, '$.k')::DOUBLE AS y, 0.05::DOUBLE * value AS w,
   CASE WHEN event_type IN ('view', 'click') THEN 'picking' WHEN event_type = 'purchase' THEN 'transport' WHEN event_type = 'signup' THEN 'setup' ELSE 'idle' END AS state,
   event_id AS src_id, ((7 * user_id) % 40)::INTEGER AS row_base, event_type
 FROM (SELECT *, CASE WHEN user_id % 2 = 0 THEN 1.63::DOUBLE ELSE 1.22::DOUBLE END AS spacing FROM events))"""

LINES = """
tl AS (
 SELECT l_suppkey AS cart_id, (year(l_shipdate) * 4 + quarter(l_shipdate))::INTEGER AS session, year(l_shipdate)::INTEGER AS year,
   (4 * l_suppkey + l_linenumber)::INTEGER AS row_idx, 0.5::DOUBLE * (l_partkey % 100) AS y, 0.1::DOUBLE * l_quantity AS m,
   (l_shipdate::DATE - DATE '1970-01-01')::BIGINT * 86400 + (7 * l_orderkey + l_linenumber) % 86400 AS t,
   l_orderkey AS ok, l_linenumber AS ln, l_partkey AS pk, l_quantity AS quantity FROM lineitem)"""

SEG = LINES + """,
seg AS (
 SELECT cart_id, session, row_idx, count(*) AS n, min(y) AS y_min, max(y) AS y_max, min(t) AS t1, max(t) AS t2,
   CASE WHEN arg_max(y, (t, ok, ln, pk)) >= arg_min(y, (t, ok, ln, pk)) THEN 1 ELSE -1 END AS direction
 FROM tl GROUP BY ALL)"""

OVER = SEG + """,
ov AS (
 SELECT a.session, a.row_idx, a.cart_id AS cart_a, b.cart_id AS cart_b, a.n AS na, b.n AS nb,
   greatest(0.0::DOUBLE, least(a.y_max, b.y_max) - greatest(a.y_min, b.y_min)) AS overlap_m
 FROM seg a JOIN seg b ON a.session = b.session AND a.row_idx = b.row_idx AND a.cart_id < b.cart_id),
conf AS (SELECT * FROM ov WHERE overlap_m > 5)"""


def _cell(v: str, high: str, res: str, n: int) -> str:
    last = f"(({res}::DOUBLE * {n - 1}) + {high}) / 2"
    before = f"({res}::DOUBLE * {n - 2} + {res}::DOUBLE / 2)"
    k = f"greatest(0, least({n - 1}, ceil({v} / {res}::DOUBLE)::INTEGER - 1))"
    return f"(CASE WHEN {v} > ({before} + {last}) / 2 THEN {n - 1} WHEN {k} = {n - 1} THEN {n - 2} ELSE {k} END)::INTEGER"


_HX, _HY = "(50 * 1.63::DOUBLE)", "(8 * 1.63::DOUBLE)"

POINTS = f"""
pt0 AS (
 SELECT l_suppkey AS cart_id, l_shipdate::DATE AS day, (l_partkey % 50)::INTEGER AS row_idx, ((l_partkey // 50) % 40)::DOUBLE * 0.3048::DOUBLE AS y_int,
   0.1::DOUBLE * l_quantity AS dmass, l_orderkey AS tray_id, l_linenumber AS segment, l_returnflag, s_nationkey AS field_id, n_name, r_name,
   ((l_partkey % 50)::DOUBLE + 0.5::DOUBLE) * 1.63::DOUBLE AS row_x
 FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey),
pt AS (SELECT *, date_trunc('month', day)::DATE AS month, {_cell("row_x", _HX, "1.63", 50)} AS j, {_cell("y_int", _HY, "1.63", 8)} AS k FROM pt0)"""

SEASON = POINTS + ", smap AS (SELECT field_id, j, k, sum(dmass) AS mass FROM pt GROUP BY ALL), mmap AS (SELECT field_id, month, j, k, sum(dmass) AS mass FROM pt GROUP BY ALL)"

COUNTS = "cnt AS (SELECT l_suppkey AS cart_id, date_trunc('month', l_shipdate)::DATE AS month, count(*)::DOUBLE AS gt, sum(l_quantity) / 25.5::DOUBLE AS est FROM lineitem GROUP BY ALL)"
TRUTH = "tr AS (SELECT l_orderkey AS tray_id, l_linenumber AS segment, sum(l_quantity) AS gt, sum(l_quantity * (1 - l_discount) * (1 + l_tax)) AS est FROM lineitem GROUP BY ALL)"


def _curve(by: str) -> str:
    return LINES + f", cv AS (SELECT *, sum(0.01::DOUBLE * quantity) OVER (PARTITION BY {by} ORDER BY y, t, ok, ln, pk ROWS UNBOUNDED PRECEDING) AS w FROM tl)"


def _fit(by: str) -> str:
    """Degrees 1 and 2 by Cramer's rule on centred and scaled positions."""
    return _curve(by) + f""",
sc AS (SELECT {by}, min(y) AS y_min, max(y) AS y_max, avg(w) AS wm, count(DISTINCT y) AS nd FROM cv GROUP BY ALL),
uv AS (SELECT {by}, (y - (y_min + y_max) / 2) / nullif((y_max - y_min) / 2, 0) AS u, w - wm AS v FROM cv JOIN sc USING ({by})),
mo AS (SELECT {by}, count(*)::DOUBLE AS s0, sum(u) AS s1, sum(u*u) AS s2, sum(u*u*u) AS s3, sum(u*u*u*u) AS s4, sum(v) AS m0, sum(u*v) AS m1, sum(u*u*v) AS m2, sum(v*v) AS vv FROM uv GROUP BY ALL),
de AS (SELECT *, s0*s2 - s1*s1 AS d1, s0*(s2*s4 - s3*s3) - s1*(s1*s4 - s3*s2) + s2*(s1*s3 - s2*s2) AS d2 FROM mo),
co AS (SELECT *, (m0*s2 - s1*m1) / d1 AS a0, (s0*m1 - s1*m0) / d1 AS a1,
  (m0*(s2*s4 - s3*s3) - s1*(m1*s4 - s3*m2) + s2*(m1*s3 - s2*m2)) / d2 AS b0, (s0*(m1*s4 - m2*s3) - m0*(s1*s4 - s3*s2) + s2*(s1*m2 - m1*s2)) / d2 AS b1,
  (s0*(s2*m2 - m1*s3) - s1*(s1*m2 - m1*s2) + m0*(s1*s3 - s2*s2)) / d2 AS b2 FROM de),
ft AS (SELECT co.*, y_min, y_max, wm, nd, least(1, (a0*m0 + a1*m1) / vv) AS r1, least(1, (b0*m0 + b1*m1 + b2*m2) / vv) AS r2 FROM co JOIN sc USING ({by}))"""


def _increments(deg: str) -> str:
    """Mass at both ends of every step, for the degree given as an expression."""
    u = lambda y: f"(({y} - (y_min + y_max) / 2) / ((y_max - y_min) / 2))"
    at = lambda y: f"(CASE WHEN {deg} = 1 THEN a0 + a1 * {u(y)} ELSE b0 + b1 * {u(y)} + b2 * {u(y)} * {u(y)} END)"
    a = "(y_min + i * 0.3048::DOUBLE)"
    b = f"({a} + 0.3048::DOUBLE)"
    return f"SELECT cart_id, year, abs({at(b)} - {at(a)}) AS dm FROM (SELECT *, unnest(range(0, floor((y_max - y_min) / 0.3048::DOUBLE + 1e-9)::BIGINT)) AS i FROM ft)"


_STAIR = "st AS (SELECT cart_id, year, sum(abs(w - lw)) AS m0 FROM (SELECT *, lag(w) OVER (PARTITION BY cart_id, year ORDER BY y, t, ok, ln, pk) AS lw FROM cv) GROUP BY ALL)"


def _line(hours: int, min_pts: int) -> str:
    eps = hours * 3_600_000_000
    return TRACE + f""",
c1 AS (SELECT *, count(*) OVER (PARTITION BY cart_id ORDER BY t_us RANGE BETWEEN {eps} PRECEDING AND {eps} FOLLOWING) >= {min_pts} AS is_core FROM trace),
c2 AS (SELECT *, max(CASE WHEN is_core THEN t_us END) OVER (PARTITION BY cart_id ORDER BY t_us, src_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS bef,
                 min(CASE WHEN is_core THEN t_us END) OVER (PARTITION BY cart_id ORDER BY t_us, src_id ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING) AS aft FROM c1),
c3 AS (SELECT *, sum(CASE WHEN is_core AND (bef IS NULL OR t_us - bef > {eps}) THEN 1 ELSE 0 END) OVER (PARTITION BY cart_id ORDER BY t_us, src_id ROWS UNBOUNDED PRECEDING) - 1 AS no FROM c2),
cl AS (SELECT *, (CASE WHEN is_core THEN no WHEN t_us - bef <= {eps} AND (aft IS NULL OR aft - t_us > {eps} OR t_us - bef <= aft - t_us) THEN no
   WHEN aft - t_us <= {eps} THEN CASE WHEN aft - bef <= {eps} THEN no ELSE no + 1 END ELSE -1 END)::BIGINT AS cluster_id FROM c3)"""


_GROUPS = SEG + """,
nb AS (SELECT *, lead(row_idx) OVER w AS r2, lead(row_idx, 2) OVER w AS r3, lead(direction) OVER w AS d2, lead(direction, 2) OVER w AS d3, lead(n) OVER w AS n2, lead(n, 2) OVER w AS n3
       FROM seg WINDOW w AS (PARTITION BY cart_id, session ORDER BY row_idx)),
gr AS (
 SELECT cart_id, session, row_idx, 2 AS size, (direction = d2)::INTEGER AS same_direction, CASE WHEN n2 > n THEN r2 ELSE row_idx END AS dominant FROM nb WHERE r2 = row_idx + 1
 UNION ALL
 SELECT cart_id, session, row_idx, 3, (direction = d2 AND direction = d3)::INTEGER, CASE WHEN n >= n2 AND n >= n3 THEN row_idx WHEN n2 >= n3 THEN r2 ELSE r3 END FROM nb WHERE r2 = row_idx + 1 AND r3 = row_idx + 2)"""

_REMAP = _GROUPS + """,
mv AS (SELECT cart_id, session, row_idx + i AS row_idx, size, row_idx AS start, dominant FROM (SELECT *, unnest(range(0, size)) AS i FROM gr WHERE same_direction = 1)),
tg AS (SELECT cart_id, session, row_idx, arg_max(dominant, (size, start)) AS target FROM mv GROUP BY ALL),
o1 AS (SELECT seg.cart_id, seg.session, seg.row_idx, coalesce(target, seg.row_idx) AS target FROM seg LEFT JOIN tg USING (cart_id, session, row_idx)),
rm AS (SELECT o1.cart_id, o1.session, o1.row_idx, (CASE WHEN o2.target IS NULL OR o2.target = o1.row_idx THEN o1.target ELSE o2.target END)::INTEGER AS row_idx_new
       FROM o1 LEFT JOIN o1 o2 ON o1.cart_id = o2.cart_id AND o1.session = o2.session AND o1.target = o2.row_idx)"""


def _sweep(keys: str) -> str:
    return f"""WITH {SEG},
ends AS (SELECT {keys}, t1 AS t, 1 AS d FROM seg UNION ALL SELECT {keys}, t2, -1 FROM seg),
sw AS (SELECT {keys}, sum(d) OVER (PARTITION BY {keys} ORDER BY t, d ROWS UNBOUNDED PRECEDING) AS o FROM ends)
SELECT {keys}, max(o)::BIGINT AS max_concurrent FROM sw GROUP BY ALL"""


def _runs(source: str, by: str, order: str, state: str) -> str:
    return f"""r1 AS (SELECT *, CASE WHEN {state} = lag({state}) OVER (PARTITION BY {by} ORDER BY {order}) THEN 0 ELSE 1 END AS nw FROM {source}),
r2 AS (SELECT *, sum(nw) OVER (PARTITION BY {by} ORDER BY {order} ROWS UNBOUNDED PRECEDING) AS no FROM r1),
r3 AS (SELECT {by}, no, {state}, count(*) AS len FROM r2 GROUP BY ALL)"""


def _poly(points) -> str:
    xs, ys = zip(*points)
    parts = []
    for (x1, y1), (x2, y2) in zip(points, points[1:] + points[:1]):
        if y1 != y2:
            parts.append(f"(CASE WHEN (({y1}::DOUBLE > y) <> ({y2}::DOUBLE > y)) AND x < ({x2 - x1}::DOUBLE * (y - {y1}::DOUBLE) / {y2 - y1}::DOUBLE + {x1}::DOUBLE) THEN 1 ELSE 0 END)")
    return f"(x BETWEEN {min(xs)} AND {max(xs)} AND y BETWEEN {min(ys)} AND {max(ys)} AND ({' + '.join(parts)}) % 2 = 1)"


_IN = _poly([(0.0, 0.0), (60.0, 0.0), (60.0, 30.0), (30.0, 45.0), (0.0, 30.0)])


def _agreement(cte: str, name: str) -> str:
    return f"""WITH {cte}, d AS (SELECT est - gt AS d FROM {name}), s AS (SELECT avg(d) AS bias, stddev_samp(d) AS sd FROM d)
SELECT round(bias, 4) AS bias, round(sd, 4) AS sd, round(bias - 1.96::DOUBLE * sd, 4) AS lo, round(bias + 1.96::DOUBLE * sd, 4) AS hi, round(abs(bias) + 1.96::DOUBLE * sd, 4) AS far_limit,
  round((SELECT avg((d BETWEEN bias - 1.96::DOUBLE * sd AND bias + 1.96::DOUBLE * sd)::INTEGER) FROM d), 4) AS share_inside FROM s"""


def _box(cte: str, source: str, col: str, by: str = "") -> str:
    g, j = (f"{by},", f"AND v.{by} = b.{by}") if by else ("", "")
    return f"""WITH {cte}
v AS (SELECT {g} {col} AS v FROM {source}),
b AS (SELECT {g} quantile_cont(v, 0.25) AS q1, quantile_cont(v, 0.5) AS median, quantile_cont(v, 0.75) AS q3, avg(v) AS mean, stddev_samp(v) AS sd FROM v GROUP BY ALL),
e AS (SELECT {f"v.{by}," if by else ""} min(v) AS lo, max(v) AS hi FROM v, b WHERE v BETWEEN q1 - 1.5::DOUBLE * (q3 - q1) AND q3 + 1.5::DOUBLE * (q3 - q1) {j} GROUP BY ALL)
SELECT {f"b.{by}," if by else ""} round(q1, 4) AS q1, round(median, 4) AS median, round(q3, 4) AS q3, round(mean, 4) AS mean, round(sd, 4) AS sd, round(lo, 4) AS lo, round(hi, 4) AS hi
FROM b, e {f"WHERE b.{by} = e.{by}" if by else ""}"""


_WIN = TRACE + ", nw AS (SELECT *, (row_number() OVER (PARTITION BY cart_id ORDER BY t_us, src_id) - 1) AS i FROM trace), wn AS (SELECT *, i // 10 AS win_no, i % 10 AS pos FROM nw)"
_REG = POINTS + ", rg AS (SELECT r_name AS region, n_name AS nation, year(day)::INTEGER AS year, dmass, l_returnflag FROM pt)"
_RATE = TRACE + """,
rt AS (SELECT *, CASE WHEN nt > t_us THEN (nwt - w) / ((nt - t_us) / 3600000000.0::DOUBLE) END AS rate FROM (
  SELECT *, lead(t_us) OVER o AS nt, lead(w) OVER o AS nwt FROM trace WHERE w > 0.55::DOUBLE AND w < 5 WINDOW o AS (PARTITION BY cart_id, session ORDER BY t_us, src_id)))"""


def _sweep_res() -> str:
    out = []
    for res, nx, ny in ((0.61, 134, 22), (1.22, 67, 11), (1.63, 50, 8), (3.26, 25, 4)):
        out.append(f"SELECT {res}::DOUBLE AS res, field_id, {_cell('row_x', _HX, str(res), nx)} AS cj, {_cell('y_int', _HY, str(res), ny)} AS ck, sum(dmass) AS mass FROM pt GROUP BY ALL")
    return " UNION ALL ".join(out)


ORACLE = {
    "deployment_per_day": f"WITH {LINES} SELECT session, count(DISTINCT cart_id) AS carts FROM tl GROUP BY ALL",
    "trays_per_cart_day_stats": f"WITH {COUNTS} SELECT count(*) AS sessions, round(avg(gt), 4) AS mean_trays, min(gt) AS min_trays, max(gt) AS max_trays, sum(gt) AS total_trays FROM cnt",
    "load_cell_calibration": "SELECT l_suppkey AS cart_id, round(regr_slope(l_quantity, l_extendedprice / 1000), 4) AS slope, round(regr_intercept(l_quantity, l_extendedprice / 1000), 4) AS intercept, round(regr_r2(l_quantity, l_extendedprice / 1000), 4) AS r2, count(*) AS n FROM lineitem GROUP BY ALL HAVING count(*) >= 3",
    "calibrated_mass": "WITH p AS (SELECT l_suppkey, regr_slope(l_quantity, l_extendedprice / 1000) AS s, regr_intercept(l_quantity, l_extendedprice / 1000) AS i FROM lineitem GROUP BY ALL HAVING count(*) >= 3) SELECT l_suppkey AS cart_id, count(*) AS samples, round(avg(abs(s * (l_extendedprice / 1000) + i - l_quantity)), 4) AS mean_abs_residual FROM lineitem JOIN p USING (l_suppkey) GROUP BY ALL",
    "recalibration_due": "WITH p AS (SELECT l_suppkey, regr_slope(l_quantity, l_extendedprice / 1000) AS s, regr_intercept(l_quantity, l_extendedprice / 1000) AS i, regr_r2(l_quantity, l_extendedprice / 1000) AS r2 FROM lineitem GROUP BY ALL HAVING count(*) >= 3), m AS (SELECT l_suppkey AS cart_id, max(abs(s * (l_extendedprice / 1000) + i - l_quantity)) AS mr, any_value(r2) AS r2 FROM lineitem JOIN p USING (l_suppkey) GROUP BY ALL) SELECT cart_id, round(mr, 4) AS max_resid, round(r2, 4) AS r2 FROM m WHERE mr > 25.5 OR r2 < 0",
    "activity_windows": f"WITH {_WIN} SELECT cart_id, win_no, count(*) AS n, round((avg(w))::DECIMAL(28, 9), 4)::DOUBLE AS mean_w, round((stddev_samp(w))::DECIMAL(28, 9), 4)::DOUBLE AS sd_w, round((arg_min(w, pos))::DECIMAL(28, 9), 4)::DOUBLE AS first_w, round((arg_max(w, pos))::DECIMAL(28, 9), 4)::DOUBLE AS last_w FROM wn GROUP BY ALL",
    "window_majority_label": f"WITH {_WIN}, p AS (SELECT cart_id, win_no, avg((state = 'picking')::INTEGER) AS p FROM wn GROUP BY ALL) SELECT cart_id, win_no, CASE WHEN p > 0.5 THEN 'Pick' ELSE 'NoPick' END AS label, round(greatest(p, 1 - p), 4) AS share FROM p",
    "rising_mass_rule": f"WITH {_WIN} SELECT cart_id, win_no, (CASE WHEN count(*) > 1 THEN regr_slope(w, pos::DOUBLE) > 0 ELSE false END)::INTEGER AS predicted FROM wn GROUP BY ALL",
    "activity_confusion": "WITH d AS (SELECT quality AS t, (n_chars >= 500)::INTEGER AS p FROM labels JOIN documents USING (doc_id)), c AS (SELECT count(*) FILTER (t=1 AND p=1) AS tp, count(*) FILTER (t=0 AND p=1) AS fp, count(*) FILTER (t=1 AND p=0) AS fn, count(*) FILTER (t=0 AND p=0) AS tn FROM d), f AS (SELECT *, 2*tp/(2*tp+fp+fn) AS f1, 2*tn/(2*tn+fp+fn) AS f0, tp+fp+fn+tn AS n FROM c) SELECT tp, fp, fn, tn, round(tp/(tp+fp), 4) AS precision, round(tp/(tp+fn), 4) AS recall, round(f1, 4) AS f1, round((tp+tn)/n, 4) AS accuracy, round((f1+f0)/2, 4) AS f1_macro, round((f1*(tp+fn)+f0*(tn+fp))/n, 4) AS f1_weighted FROM f",
    "velocity_stats": f"WITH {TRACE}, v AS (SELECT cart_id, CASE WHEN t_us > lt THEN sqrt((x-lx)*(x-lx) + (y-ly)*(y-ly)) / ((t_us - lt) / 1e6::DOUBLE) ELSE 0 END AS vel FROM (SELECT *, lag(x) OVER o AS lx, lag(y) OVER o AS ly, lag(t_us) OVER o AS lt FROM trace WINDOW o AS (PARTITION BY cart_id, session ORDER BY t_us, src_id))) SELECT cart_id, round(max(vel) * 1e6::DOUBLE, 2) AS max_um_s, count(*) FILTER (vel > 0) AS moving FROM v GROUP BY ALL",
    "state_transitions": f"WITH {TRACE}, n AS (SELECT event_type AS from_state, lead(event_type) OVER (PARTITION BY cart_id ORDER BY t_us, src_id) AS to_state FROM trace) SELECT from_state, to_state, count(*) AS n FROM n GROUP BY ALL",
    "state_dwell": f"WITH {TRACE}, {_runs('trace', 'cart_id', 't_us, src_id', 'state')} SELECT state, count(*) AS runs, round(avg(len), 4) AS mean_len, max(len) AS max_len FROM r3 GROUP BY ALL",
    "conversation_state_runs": f"WITH {_runs('conversations', 'conv_id', 'turn', 'role')} SELECT role, count(*) AS runs, round(avg(len), 4) AS mean_len FROM r3 GROUP BY ALL",
    "section_share": f"WITH {TRACE} SELECT field_id, CASE WHEN y >= 25 THEN 'upper' ELSE 'lower' END AS section, count(*) AS n FROM trace GROUP BY ALL",
    "bed_midpoint_rows": "WITH b AS (SELECT p_partkey * 1.63::DOUBLE + (p_size - 25) / 1000 AS x FROM part), n AS (SELECT row_number() OVER (ORDER BY x) - 1 AS row_idx, x, lead(x) OVER (ORDER BY x) AS nx FROM b) SELECT row_idx, round((x + nx) / 2, 4) AS row_x, round(nx - x, 4) AS spacing FROM n WHERE nx IS NOT NULL",
    "boundary_clip": f"WITH {TRACE} SELECT cart_id, count(*) FILTER ({_IN}) AS kept, count(*) FILTER (NOT {_IN}) AS dropped FROM trace GROUP BY ALL",
    "density_cluster_time": f"WITH {_line(12, 4)} SELECT cart_id, cluster_id, count(*) AS n, count(*) FILTER (is_core) AS n_core, min(t_us) AS t_lo, max(t_us) AS t_hi FROM cl GROUP BY ALL",
    "trajectory_chain": f"WITH {TRACE}, g AS (SELECT *, CASE WHEN t_us - lag(t_us) OVER (PARTITION BY cart_id ORDER BY t_us, src_id) > 43200000000 THEN 1 ELSE 0 END AS c FROM trace), h AS (SELECT cart_id, sum(c) OVER (PARTITION BY cart_id ORDER BY t_us, src_id ROWS UNBOUNDED PRECEDING)::BIGINT AS chain_id FROM g) SELECT cart_id, chain_id, count(*) AS n FROM h GROUP BY ALL",
    "cluster_row_assignment": f"WITH {_line(12, 4)}, m AS (SELECT cart_id, cluster_id, quantile_cont(x, 0.5) AS mx, any_value(spacing) AS sp FROM cl WHERE cluster_id >= 0 GROUP BY ALL), r AS (SELECT *, greatest(0, round(mx / sp)::INTEGER) AS row_idx FROM m) SELECT cart_id, cluster_id, round(mx, 4) AS median_x, row_idx, round(abs(mx - row_idx * sp), 4) AS distance FROM r",
    "snap_pointwise": f"WITH {TRACE} SELECT (greatest(0, round(x / spacing)::INTEGER) - row_base)::INTEGER AS row_offset, count(*) AS n FROM trace GROUP BY ALL",
    "cluster_snap_offsets": f"WITH {_line(12, 4)}, m AS (SELECT cart_id, cluster_id, greatest(0, round(quantile_cont(x, 0.5) / any_value(spacing))::INTEGER) AS r FROM cl WHERE cluster_id >= 0 GROUP BY ALL) SELECT (r - row_base)::INTEGER AS row_offset, count(*) AS n FROM cl LEFT JOIN m USING (cart_id, cluster_id) GROUP BY ALL",
    "row_segments": f"WITH {SEG} SELECT cart_id, session, row_idx, n, round(y_min, 4) AS y_min, round(y_max, 4) AS y_max, direction FROM seg",
    "travel_direction_simple": f"WITH {LINES} SELECT cart_id, session, CASE WHEN arg_max(y, (t, ok, ln, pk)) >= arg_min(y, (t, ok, ln, pk)) THEN 1 ELSE -1 END AS direction FROM tl GROUP BY ALL",
    "travel_direction_turns": f"WITH {LINES}, s AS (SELECT *, sign(y - lag(y) OVER (PARTITION BY cart_id, session ORDER BY t, ok, ln, pk))::INTEGER AS d FROM tl), q AS (SELECT *, CASE WHEN d <> lag(d) OVER (PARTITION BY cart_id, session ORDER BY t, ok, ln, pk) THEN 1 ELSE 0 END AS c FROM s WHERE d <> 0), f AS (SELECT cart_id, session, sum(c) + 1 AS st, arg_min(d, (t, ok, ln, pk)) AS fd, arg_max(d, (t, ok, ln, pk)) AS ld FROM q GROUP BY ALL) SELECT cart_id, session, coalesce(st, 1)::BIGINT AS stretches, coalesce(fd, 1) AS first_dir, coalesce(ld, 1) AS last_dir FROM (SELECT DISTINCT cart_id, session FROM tl) LEFT JOIN f USING (cart_id, session)",
    "hampel_outliers": f"WITH {TRACE}, w AS (SELECT *, list(y) OVER (PARTITION BY cart_id ORDER BY t_us, src_id ROWS BETWEEN 3 PRECEDING AND 3 FOLLOWING) AS win FROM trace), m AS (SELECT *, list_median(win) AS med FROM w), k AS (SELECT *, list_median(list_transform(win, lambda v: abs(v - med))) AS mad FROM m), h AS (SELECT cart_id, y, CASE WHEN abs(y - med) > 1.0::DOUBLE * 1.4826::DOUBLE * mad THEN med ELSE y END AS yh FROM k) SELECT cart_id, count(*) FILTER (yh <> y) AS replaced, round(sum(yh), 4) AS total FROM h GROUP BY ALL",
    "adjacent_row_groups": f"WITH {_GROUPS} SELECT cart_id, session, row_idx, size, same_direction FROM gr",
    "row_completion_repair": f"WITH {_REMAP} SELECT cart_id, session, row_idx, row_idx_new, (row_idx <> row_idx_new)::INTEGER AS moved_flag FROM rm",
    "row_completion_check": _sweep("cart_id, session"),
    "row_occupancy_check": _sweep("session, row_idx, direction"),
    "activity_interval_counts": f"WITH {SEG}, j AS (SELECT tl.*, direction FROM tl JOIN seg USING (cart_id, session, row_idx)), c AS (SELECT *, CASE WHEN row_idx = lag(row_idx) OVER o AND direction = lag(direction) OVER o AND t - lag(t) OVER o <= 432000 THEN 0 ELSE 1 END AS cut FROM j WINDOW o AS (PARTITION BY cart_id, session ORDER BY t, ok, ln, pk)), n AS (SELECT *, sum(cut) OVER (PARTITION BY cart_id, session ORDER BY t, ok, ln, pk ROWS UNBOUNDED PRECEDING) AS no FROM c), iv AS (SELECT cart_id, session, no, min(t) AS a, max(t) AS b FROM n GROUP BY ALL) SELECT cart_id, session, count(*) AS intervals, max(b - a) AS longest FROM iv GROUP BY ALL",
    "row_overlaps": f"WITH {OVER} SELECT session, row_idx, cart_a, cart_b, round(overlap_m, 4) AS overlap_m FROM ov WHERE overlap_m > 0",
    "row_conflicts": f"WITH {OVER} SELECT session, count(*) AS conflicts, round(avg(overlap_m), 4) AS mean_overlap FROM conf GROUP BY ALL",
    "conflict_loser": f"WITH {OVER} SELECT session, row_idx, cart_a, cart_b, CASE WHEN na < nb THEN cart_a ELSE cart_b END AS loser FROM conf",
    "mass_in_range": f"WITH {TRACE} SELECT cart_id, count(*) FILTER (w > 0.55::DOUBLE AND w < 5) AS kept, count(*) FILTER (NOT (w > 0.55::DOUBLE AND w < 5)) AS dropped FROM trace GROUP BY ALL",
    "filter_mass_band": f"WITH {TRACE} SELECT src_id, cart_id, round(w, 4) AS w FROM trace WHERE w > 0.55::DOUBLE AND w < 5",
    "mass_rate_stable": f"WITH {_RATE} SELECT cart_id, session, count(*) AS stable_n, round(avg(rate), 4) AS mean_rate FROM rt WHERE rate > 0 AND rate <= 0.2::DOUBLE GROUP BY ALL",
    "mass_median_smooth": f"WITH {TRACE}, s AS (SELECT src_id, quantile_cont(w, 0.5) OVER (PARTITION BY cart_id ORDER BY t_us, src_id ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS q FROM trace) SELECT src_id, round(q::DECIMAL(28, 9), 4)::DOUBLE AS w_smooth FROM s",
    "mass_clean": f"WITH {_RATE}, s AS (SELECT cart_id, quantile_cont(w, 0.5) OVER (PARTITION BY cart_id, session ORDER BY t_us, src_id ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS q FROM rt WHERE rate > 0 AND rate <= 0.2::DOUBLE) SELECT cart_id, count(*) AS n, round((sum(q))::DECIMAL(28, 9), 4)::DOUBLE AS total FROM s GROUP BY ALL",
    "tray_clusters_1d": f"WITH {_line(6, 3)} SELECT cart_id, cluster_id AS tray_id, count(*) AS n, round(min(w), 4) AS mass_min, round(max(w), 4) AS mass_max FROM cl GROUP BY ALL",
    "tray_mass_reset": f"WITH {TRACE}, g AS (SELECT *, CASE WHEN lag(w) OVER (PARTITION BY cart_id ORDER BY t_us, src_id) - w > 1 THEN 1 ELSE 0 END AS c FROM trace) SELECT cart_id, sum(c)::BIGINT + 1 AS trays FROM g GROUP BY ALL",
    "poly_fit_degree1": f"WITH {_curve('cart_id, year')} SELECT cart_id, year, round(regr_slope(w, y), 4) AS slope, round(regr_intercept(w, y), 4) AS intercept, round(regr_r2(w, y), 4) AS score FROM cv GROUP BY ALL",
    "poly_fit_adaptive": f"WITH {_fit('cart_id, year')} SELECT cart_id, year, CASE WHEN r1 > 0.94::DOUBLE THEN 1 ELSE 2 END AS degree, round(CASE WHEN r1 > 0.94::DOUBLE THEN r1 ELSE r2 END, 4) AS score FROM ft",
    "yield_increments": f"WITH {_fit('cart_id, year')}, inc AS ({_increments('(CASE WHEN r1 > 0.94::DOUBLE THEN 1 ELSE 2 END)')}) SELECT cart_id, year, count(*) AS points, round(sum(dm), 4) AS total_dmass FROM inc GROUP BY ALL",
    "staircase_yield": f"WITH {_curve('cart_id, year')}, {_STAIR} SELECT cart_id, year, round(m0, 4) AS total_dmass FROM st",
    "container_average_yield": f"WITH {POINTS}, a AS (SELECT cart_id, count(DISTINCT tray_id) AS trays FROM pt GROUP BY ALL), c AS (SELECT cart_id, count(DISTINCT (j, k)) AS cells FROM pt GROUP BY ALL) SELECT cart_id, cells, round(trays * 4.25::DOUBLE / cells, 4) AS mass_per_cell FROM a JOIN c USING (cart_id)",
    "ablate_interpolation": f"WITH {_fit('cart_id, year')}, {_STAIR}, x0 AS ({_increments('(CASE WHEN r1 > 0.94::DOUBLE THEN 1 ELSE 2 END)')}), x1 AS ({_increments('1')}), x2 AS ({_increments('(CASE WHEN nd > 2 THEN 2 ELSE 1 END)')}), "
    "u AS (SELECT 'adaptive' AS variant, * FROM x0 UNION ALL SELECT 'degree1', * FROM x1 UNION ALL SELECT 'degree2', * FROM x2), g AS (SELECT variant, cart_id, year, sum(dm) AS m FROM u GROUP BY ALL) SELECT variant, round(sum(m), 4) AS total_mass, round(avg(abs(m - m0)), 4) AS mean_abs_diff FROM g JOIN st USING (cart_id, year) GROUP BY ALL",
    "daily_yield_map": f"WITH {POINTS} SELECT field_id, day, j, k, round(sum(dmass), 4) AS mass FROM pt GROUP BY ALL",
    "season_yield_map": f"WITH {SEASON} SELECT field_id, j, k, round(mass, 4) AS mass FROM smap",
    "season_yield_class": f"WITH {SEASON}, s AS (SELECT field_id, avg(mass) AS mu, coalesce(stddev_samp(mass), 0) AS sd FROM smap GROUP BY ALL) SELECT field_id, j, k, round(mass, 4) AS mass, CASE WHEN mass <= mu - sd THEN 'very_low' WHEN mass <= mu THEN 'below' WHEN mass <= mu + sd THEN 'above' ELSE 'very_high' END AS yield_class FROM smap JOIN s USING (field_id)",
    "running_season_mass": f"WITH {SEASON}, m AS (SELECT field_id, month, sum(mass) AS mass FROM mmap GROUP BY ALL) SELECT field_id, month, round(mass, 4) AS mass, round(sum(mass) OVER (PARTITION BY field_id ORDER BY month ROWS UNBOUNDED PRECEDING), 4) AS cumulative_mass FROM m",
    "yield_histogram": f"WITH {SEASON} SELECT (CASE WHEN round(mass, 6) < 0 THEN 0 WHEN round(mass, 6) >= 60 THEN 25 ELSE floor(round(mass, 6) / 2.5::DOUBLE) + 1 END)::BIGINT AS bin, count(*) AS cells FROM smap GROUP BY ALL",
    "yield_density": f"WITH {SEASON}, d AS (SELECT field_id, avg(mass) AS a, stddev_samp(mass) AS s, sum(mass) / (count(*) * (1.63::DOUBLE * 1.63::DOUBLE)) AS q FROM smap GROUP BY ALL) SELECT field_id, round((a)::DECIMAL(28, 9), 4)::DOUBLE AS mean_mass, round((s)::DECIMAL(28, 9), 4)::DOUBLE AS sd_mass, round((q)::DECIMAL(28, 9), 4)::DOUBLE AS kg_m2, round(q / 0.45359237::DOUBLE * 0.3048::DOUBLE * 0.3048::DOUBLE, 4) AS lb_ft2 FROM d",
    "zero_yield_share": f"WITH {SEASON}, e AS (SELECT field_id, month, 1 - count(*) FILTER (mass > 0) / 400.0::DOUBLE AS s FROM mmap GROUP BY ALL) SELECT field_id, round(avg(s), 4) AS mean_zero_share, count(*) AS months FROM e GROUP BY ALL",
    "dense_season_map": f"WITH {SEASON} SELECT field_id, 400::BIGINT AS cells, 400 - count(*) FILTER (mass <> 0) AS empty FROM smap GROUP BY ALL",
    "coarsened_map": f"WITH {SEASON} SELECT field_id, (j // 2)::INTEGER AS j, (k // 2)::INTEGER AS k, round(sum(mass), 4) AS mass FROM (SELECT field_id, j, k, mass FROM smap) GROUP BY field_id, j // 2, k // 2",
    "resolution_sweep": f"WITH {POINTS}, c AS ({_sweep_res()}) SELECT res, count(*) AS cells, round(avg(mass), 4) AS mean_mass, round(stddev_samp(mass), 4) AS sd_mass FROM c GROUP BY ALL",
    "cell_temporal_trend": f"WITH {SEASON} SELECT field_id, j, k, CASE WHEN count(*) > 1 THEN round((regr_slope(mass, (year(month) * 12 + month(month))::DOUBLE))::DECIMAL(28, 9), 4)::DOUBLE END AS slope, round((stddev_samp(mass) / avg(mass))::DECIMAL(28, 9), 4)::DOUBLE AS cv FROM mmap GROUP BY ALL",
    "exported_features": f"WITH {SEASON} SELECT 'Point' AS kind, j, k, round((j * 1.63::DOUBLE + least((j + 1) * 1.63::DOUBLE, 50 * 1.63::DOUBLE)) / 2, 4) AS x, round((k * 1.63::DOUBLE + least((k + 1) * 1.63::DOUBLE, 8 * 1.63::DOUBLE)) / 2, 4) AS y, round((mass)::DECIMAL(28, 9), 4)::DOUBLE AS mass FROM smap",
    "row_level_accuracy": f"WITH {TRUTH}, e AS (SELECT tray_id, sum(abs(gt - est) / gt) AS e, count(*) AS n FROM tr WHERE gt > 0 GROUP BY ALL) SELECT round(1 - sum(e) / count(*), 4) AS acc_printed, round(1 - sum(e) / sum(n), 4) AS acc_segments, count(*) AS n_trays, sum(n)::BIGINT AS n_segments FROM e",
    "tray_level_accuracy": f"WITH {TRUTH}, e AS (SELECT tray_id, sum(gt) AS gt, sum(est) AS est FROM tr GROUP BY ALL), a AS (SELECT 1 - abs(gt - est) / gt AS a FROM e WHERE gt > 0) SELECT round(avg(a), 4) AS accuracy, round(stddev_samp(a), 4) AS sd, round(min(a), 4) AS min_acc, round(max(a), 4) AS max_acc, count(*) AS n FROM a",
    "row_level_boxplot": _box(TRUTH + ",", "tr", "round(1 - abs(gt - est) / gt, 9)"),
    "row_level_agreement": _agreement(TRUTH, "tr"),
    "tray_count_agreement": _agreement(COUNTS, "cnt"),
    "tray_count_summary": f"WITH {COUNTS} SELECT round(sum(gt), 4) AS total_gt, round(sum(est), 4) AS total_est, round(1 - avg(abs(gt - est) / gt), 4) AS accuracy, round(avg(abs(est - gt)), 4) AS mae, round(sqrt(avg((est - gt) * (est - gt))), 4) AS rmse, round(corr(gt, est), 4) AS pearson_r, count(*) AS n FROM cnt",
    "tray_count_scatter": f"WITH {COUNTS} SELECT gt, floor(round(est, 6))::BIGINT AS est_bin, count(*) AS n FROM cnt GROUP BY ALL",
    "identity_line_distance": f"WITH {COUNTS} SELECT round(avg(abs(est - gt) / sqrt(2::DOUBLE)), 4) AS mean_distance FROM cnt",
    "estimated_tray_counts": f"WITH {POINTS} SELECT cart_id, round(sum(dmass) / 4.25::DOUBLE, 4) AS est FROM pt GROUP BY ALL",
    "gap_shares": f"WITH {TRACE}, s AS (SELECT cart_id, session, (lead(t_us) OVER (PARTITION BY cart_id, session ORDER BY t_us) - t_us) / 1e6::DOUBLE AS st FROM trace) SELECT cart_id, session, round(sum(CASE WHEN st > 21600 THEN st - 21600 END) / sum(st), 4) AS gap_share, count(*) AS n FROM s GROUP BY ALL",
    "step_effects": f"WITH {_RATE}, a AS (SELECT count(*) AS n, count(*) FILTER ({_IN}) AS k, count(*) FILTER (w > 0.55::DOUBLE AND w < 5) AS r FROM trace), b AS (SELECT count(*) AS s FROM rt WHERE rate > 0 AND rate <= 0.2::DOUBLE) SELECT 'clip' AS step, n AS rows_in, k AS rows_out FROM a UNION ALL SELECT 'range', n, r FROM a UNION ALL SELECT 'stable', r, s FROM a, b",
    "payroll_reconcile": "WITH c AS (SELECT l_suppkey AS cart_id, count(DISTINCT l_orderkey) AS c FROM lineitem GROUP BY ALL), p AS (SELECT o_custkey AS cart_id, count(*) AS p FROM orders GROUP BY ALL) SELECT cart_id, coalesce(c, 0) AS counted, coalesce(p, 0) AS paid, coalesce(c, 0) - coalesce(p, 0) AS diff FROM c FULL JOIN p USING (cart_id)",
    "ablate_completion": f"WITH {_REMAP}, b AS (SELECT 'without' AS variant, cart_id, session, row_idx AS r FROM rm UNION ALL SELECT 'with', cart_id, session, row_idx_new FROM rm), c AS (SELECT variant, session, r, count(DISTINCT cart_id) AS n FROM b GROUP BY ALL), u AS (SELECT variant, count(*) AS rows_used FROM (SELECT DISTINCT * FROM b) GROUP BY ALL) SELECT variant, any_value(rows_used) AS rows_used, max(n) AS max_carts_per_row FROM c JOIN u USING (variant) GROUP BY variant",
    "cart_productivity": f"WITH {POINTS}, p AS (SELECT cart_id, round(sum(dmass), 4) AS kg, count(DISTINCT day) AS active_days FROM pt GROUP BY ALL) SELECT cart_id, kg, active_days, round(kg / active_days, 4) AS kg_per_day, rank() OVER (ORDER BY kg DESC)::INTEGER AS rank FROM p",
    "unvisited_rows": f"WITH {POINTS}, e AS (SELECT field_id, month, unnest(range(0, 50)) AS row_idx FROM (SELECT DISTINCT field_id, month FROM pt)) SELECT field_id, count(*) AS unvisited FROM e ANTI JOIN pt USING (field_id, month, row_idx) GROUP BY ALL",
    "carts_with_conflict": f"WITH {OVER} SELECT s_suppkey AS cart_id, s_name FROM supplier WHERE s_suppkey IN (SELECT cart_a FROM conf UNION SELECT cart_b FROM conf)",
    "asof_state": f"WITH {TRACE}, a AS (SELECT *, last_value(CASE WHEN event_type <> 'purchase' THEN event_type END IGNORE NULLS) OVER (PARTITION BY cart_id ORDER BY t_us, src_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_state FROM trace) SELECT src_id, cart_id, last_state FROM a WHERE event_type = 'purchase'",
    "interval_overlap": f"WITH {SEG} SELECT a.session, count(*) AS pairs, sum(least(a.t2, b.t2) - greatest(a.t1, b.t1))::BIGINT AS shared_s FROM seg a JOIN seg b ON a.session = b.session AND a.row_idx = b.row_idx AND a.cart_id < b.cart_id AND a.t1 <= b.t2 AND b.t1 <= a.t2 GROUP BY ALL",
    "yield_rollup": f"WITH {_REG} SELECT region, nation, year, round(sum(dmass), 4) AS mass, grouping_id(region, nation, year)::BIGINT AS grouping_id FROM rg GROUP BY ROLLUP (region, nation, year)",
    "yield_cube": f"WITH {_REG} SELECT region, year, round(sum(dmass), 4) AS mass, grouping_id(region, year)::BIGINT AS grouping_id FROM rg GROUP BY CUBE (region, year)",
    "yield_grouping_sets": f"WITH {_REG} SELECT region, year, round(sum(dmass), 4) AS mass, grouping_id(region, year)::BIGINT AS grouping_id FROM rg GROUP BY GROUPING SETS ((region), (year), ())",
    "yield_pivot_returnflag": f"""WITH {_REG} SELECT region, round(sum(dmass) FILTER (l_returnflag = 'A'), 4) AS "A", round(sum(dmass) FILTER (l_returnflag = 'N'), 4) AS "N", round(sum(dmass) FILTER (l_returnflag = 'R'), 4) AS "R" FROM rg GROUP BY region""",
    "rank_carts_per_field": f"WITH {POINTS}, g AS (SELECT field_id, cart_id, round(sum(dmass), 4) AS kg FROM pt GROUP BY ALL) SELECT field_id, cart_id, kg, rank() OVER w::INTEGER AS rank, dense_rank() OVER w::INTEGER AS dense_rank FROM g WINDOW w AS (PARTITION BY field_id ORDER BY kg DESC)",
    "top_cells": f"WITH {SEASON} SELECT field_id, j, k, round(mass, 4) AS mass FROM smap ORDER BY 4 DESC, field_id, j, k LIMIT 20",
    "top_rows_per_field": f"WITH {POINTS}, g AS (SELECT field_id, row_idx, round(sum(dmass), 4) AS mass FROM pt GROUP BY ALL), r AS (SELECT *, row_number() OVER (PARTITION BY field_id ORDER BY mass DESC, row_idx)::INTEGER AS rank FROM g) SELECT * FROM r WHERE rank <= 3",
    "rows_both_months": f"WITH {POINTS} SELECT field_id, row_idx FROM pt WHERE month = DATE '1995-03-01' INTERSECT SELECT field_id, row_idx FROM pt WHERE month = DATE '1995-04-01'",
    "rows_only_first": f"WITH {POINTS}, a AS (SELECT field_id, row_idx, count(*) AS n FROM pt WHERE month = DATE '1995-03-01' GROUP BY ALL), b AS (SELECT DISTINCT field_id, row_idx, 1 AS m FROM pt WHERE month = DATE '1995-04-01') SELECT field_id, row_idx FROM a LEFT JOIN b USING (field_id, row_idx) WHERE n - coalesce(m, 0) > 0",
    "props_histogram": "SELECT (json_extract_string(props, '$.k')::INTEGER // 10)::INTEGER AS bucket, count(*) AS n FROM events GROUP BY ALL",
    "page_host_counts": "SELECT regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, count(*) AS n FROM pages GROUP BY ALL",
    "doc_length_boxplot": _box("", "(SELECT coalesce(lang, 'none') AS lang, n_chars FROM documents)", "n_chars::DOUBLE", "lang"),
    "distinct_carts_exact": f"WITH {POINTS} SELECT field_id, count(DISTINCT cart_id) AS carts FROM pt GROUP BY ALL",
    "scan_pruned": "SELECT l_suppkey, count(*) AS n FROM lineitem WHERE l_quantity > 45 GROUP BY ALL",
    "benchmark_in_documents": "SELECT count(*) AS shared FROM (SELECT trim(text) FROM benchmark INTERSECT SELECT trim(text) FROM documents)",
    "sampled_cart_days": f"WITH {TRACE} SELECT cart_id, session, count(*) AS n FROM trace WHERE ('0x' || substr(md5(cart_id || '|' || session), 1, 8))::BIGINT / 4294967296 < 0.1::DOUBLE GROUP BY ALL",
    "sampled_per_state": "SELECT event_id, event_type, user_id FROM events QUALIFY row_number() OVER (PARTITION BY event_type ORDER BY substr(md5(event_id::VARCHAR), 1, 8), event_id) <= 20",
    "stream_window_mass": "SELECT strftime(ts, '%Y-%m-%d') AS day, (user_id % 2)::INTEGER AS field_id, round(sum(0.05::DOUBLE * value), 4) AS mass, count(*) AS n FROM events GROUP BY ALL",
    "stream_session_trays": "WITH g AS (SELECT *, epoch_us(ts) AS t, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) < 43200000000 THEN 0 ELSE 1 END AS c FROM events), h AS (SELECT *, sum(c) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS no FROM g) SELECT user_id AS cart_id, min(t) AS t_start, round(sum(0.05::DOUBLE * value), 4) AS mass, count(*) AS n FROM h GROUP BY user_id, no",
    "low_yield_zones": f"WITH RECURSIVE {SEASON}, st AS (SELECT field_id, avg(mass) AS mu, coalesce(stddev_samp(mass), 0) AS sd FROM smap GROUP BY ALL), low AS (SELECT field_id, j, k, mass FROM smap JOIN st USING (field_id) WHERE mass <= mu - sd), "
    "re AS (SELECT field_id, j, k, j * 1000 + k AS z FROM low UNION SELECT re.field_id, low.j, low.k, re.z FROM re JOIN low ON re.field_id = low.field_id AND abs(low.j - re.j) + abs(low.k - re.k) = 1), "
    "zo AS (SELECT field_id, j, k, min(z) AS z FROM re GROUP BY ALL) SELECT field_id, (z // 1000) || '_' || (z % 1000) AS zone, count(*) AS cells, round(sum(mass), 4) AS mass FROM zo JOIN low USING (field_id, j, k) GROUP BY field_id, z",
}
