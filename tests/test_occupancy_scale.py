"""The occupancy repair and the count of conflicts against plain versions, and on rows with many carts."""

import random
import time

import numpy as np

from harvestgrid.operators import occupancy


def plain_resolve(segs, min_overlap, weight, rows, max_rounds):
    """Every pair of every row in order, each move checked against everybody."""
    of = {(s["cart_id"], s["row_idx"]): s for s in segs}
    place, status, shares = {k: k[1] for k in of}, {k: "kept" for k in of}, {}
    for s in sorted(segs, key=lambda s: (-s[weight], s["row_idx"])):
        shares.setdefault(s["cart_id"], []).append(s["row_idx"])
    clash = lambda a, b: min(of[a]["y_max"], of[b]["y_max"]) - max(of[a]["y_min"], of[b]["y_min"]) > min_overlap
    for _ in range(max_rounds):
        moved = False
        for row in sorted(set(place.values())):
            here = sorted(k for k in place if place[k] == row)
            for i, a in enumerate(here):
                for b in here[i + 1 :]:
                    if a[0] == b[0] or place[a] != row or place[b] != row or not clash(a, b):
                        continue
                    fa, fb = of[a].get("moved_flag", 0), of[b].get("moved_flag", 0)
                    lost = (a if fa else b) if fa != fb else (a if of[a][weight] < of[b][weight] else b)
                    second = of[lost].get("second_idx")
                    if second is None:
                        second = next((r for r in shares[lost[0]] if r != row), None)
                    wish = [second, row - 1, row + 1] + ([second - 1, second + 1] if second is not None else [])
                    ok = lambda r: r is not None and r != row and r >= 0 and (rows is None or r in rows) and not any(q == r and o[0] != lost[0] and clash(o, lost) for o, q in place.items())  # noqa: B023, E731
                    target = next((r for r in wish if ok(r)), None)
                    if target is None:
                        status[lost] = "unresolved"
                    else:
                        place[lost], status[lost], moved = target, "moved", True
        if not moved:
            break
    return {k: (place[k], status[k]) for k in of}


def random_segments(rng, carts, rows, length):
    out = {}
    for cart in range(carts):
        for row in rng.sample(range(rows), rng.randrange(1, 4)):
            lo = 0.5 * rng.randrange(0, 100)
            s = {"cart_id": cart, "row_idx": row, "y_min": lo, "y_max": lo + 0.5 * rng.randrange(0, 2 * length), "n": rng.randrange(1, 6), "moved_flag": int(rng.random() < 0.3)}
            out[cart, row] = s | {"second_idx": rng.choice((None, None, rng.randrange(rows)))}
    return list(out.values())


def test_repair_equals_the_plain_one():
    rng = random.Random(6)
    seen = set()
    for k in range(120):
        rows = rng.randrange(3, 9)
        segs = random_segments(rng, rng.randrange(2, 28), rows, rng.choice((8, 20, 50)))
        known = set(range(rows)) if k % 2 else None
        got = occupancy.resolve_day(segs, 5.0, "n", known, 3)
        assert got == plain_resolve(segs, 5.0, "n", known, 3)
        seen |= {s for _, s in got.values()}
    assert seen == {"kept", "moved", "unresolved"}


def test_repair_of_full_rows_takes_seconds():
    """700 carts in each of a few rows, no free place: the plain form looks at millions of pairs, each with five candidates."""
    rng = random.Random(7)
    segs = [{"cart_id": c, "row_idx": r, "y_min": 0.0, "y_max": 30.0 + rng.random(), "n": rng.randrange(1, 99)} for c in range(1400) for r in rng.sample(range(4), 2)]
    began = time.time()
    got = occupancy.resolve_day(segs, 5.0, "n", set(range(4)), 3)
    assert {s for _, s in got.values()} == {"kept", "unresolved"} and time.time() - began < 10


def test_count_equals_the_joined_pairs(spark):
    rng = random.Random(9)
    for _ in range(60):
        n = rng.randrange(0, 40)
        lo = np.array([rng.choice((0.1, 0.3, 0.5)) * rng.randrange(60) for _ in range(n)])
        hi = lo + np.array([rng.choice((0.1, 0.7, 5.0)) * rng.randrange(12) for _ in range(n)])
        for least in (0.0, 0.3, 5.0):
            want = sum(min(hi[i], hi[j]) - max(lo[i], lo[j]) > least for i in range(n) for j in range(i))
            assert occupancy.overlapping_pairs(lo, hi, least) == want
    rows = [(s["cart_id"], f, s["row_idx"], s["y_min"], s["y_max"]) for f in (0, 1) for s in random_segments(rng, 40, 6, 50)]
    seg = spark.createDataFrame(rows, "cart_id long, session int, row_idx int, y_min double, y_max double")
    assert occupancy.count_conflicts(seg, 5.0).first().x == occupancy.conflicts(seg, 5.0, keep=()).count() > 0
    assert occupancy.count_conflicts(seg.limit(0), 5.0).first().x == 0
