import math
import random
import re

from harvestgrid.llm import mixing


def brute_targets(rows):
    sizes = {}
    for _, s, t in rows:
        sizes[s] = sizes.get(s, 0) + len(re.findall(r"[^\x20\x09-\x0d]+", t or ""))
    order = sorted(sizes, key=lambda s: (s is None, (s or "").encode("utf-32-be")))
    weight = {s: (1, 2, 3)[k % 3] for k, s in enumerate(order)}
    target, open_, left = {}, set(order), float(sum(sizes.values()))
    while open_:
        share = {s: left * weight[s] / sum(weight[x] for x in open_) for s in open_}
        over = [s for s in open_ if share[s] > 3 * sizes[s]]
        if not over:
            target |= share
            break
        for s in over:
            target[s] = 3.0 * sizes[s]
            left -= target[s]
            open_.discard(s)
    return sizes, target


def test_targets_copies_and_rows(spark):
    rows = []
    for k, (s, n, words) in enumerate([("a", 400, 5), ("b", 30, 3), ("Z", 200, 40), (None, 50, 10), ("é", 5, 2), ("empty", 3, 0)]):
        rows += [(1000 * k + i, s, " ".join(["w"] * (words + i % 7 if words else 0))) for i in range(n)]
    rows += [(None, "a", "x y"), (7000, "a", None), (7001, "a", ""), (7002, "a", "w " * 300), (3, "a", rows[3][2])]
    df = spark.createDataFrame(rows, "doc_id long, source string, text string").selectExpr("*", "1 AS size", "'k' AS key", "array(1) AS bin").repartition(5)
    sizes, target = brute_targets(rows)
    got = mixing.mixed(df).collect()
    assert len(got) == len(rows)
    taken = {}
    for r in got:
        assert r.source_size == sizes[r.source] and math.isclose(r.target, target[r.source], rel_tol=1e-9, abs_tol=1e-9)
        assert 0 <= r.copies <= 3
        taken[r.source] = taken.get(r.source, 0) + r.copies * r.size
    for s, t in target.items():
        rated = [r for r in got if r.source == s]
        assert math.isclose(sum(r.rate * r.size for r in rated), t, rel_tol=1e-5, abs_tol=1e-9)
        # No copy more, no copy less and no exchange of one for the other brings the source closer.
        gap, less, more = t - taken[s], {0} | {r.size for r in rated if r.copies > 0}, {0} | {r.size for r in rated if r.copies < 3}
        assert abs(gap) <= min(abs(gap + a - b) for a in less for b in more) + 1e-6, (s, taken[s], t)
        assert abs(gap) <= max(2, 0.001 * t), (s, taken[s], t)
    again = {(r.doc_id, r.source, r.size): r.copies for r in mixing.mixed(df.repartition(2)).collect()}
    assert all(again[(r.doc_id, r.source, r.size)] == r.copies for r in got)
    for small in (2000, 0):  # 0: the table of sources is not broadcast
        out = mixing.take_copies(df, small_sources=small)
        assert out.columns == df.columns
        assert out.count() == sum(r.copies for r in got)
    assert mixing.mixed(df.limit(0)).count() == 0 and mixing.take_copies(df.limit(0)).count() == 0


def test_rates_solve_the_dual(spark):
    """First-order conditions of the strictly convex dual, from the definition; languages lean differently in each source."""
    rng = random.Random(6)
    rows = []
    for k in range(900):
        source = "abcd"[min(3, int(rng.random() ** 2 * 4))]
        lang = rng.choice({"a": ["en"], "b": ["en", "de"], "c": ["de", "fr", None], "d": ["fr"]}[source])
        rows.append((k, source, lang, " ".join(["w"] * int(2 ** rng.uniform(0, 9)))))
    df = spark.createDataFrame(rows, "doc_id long, source string, lang string, text string").repartition(4)
    sizes = mixing.sized(df)
    goal = mixing.targets(sizes)
    tilt, state = mixing.balanced(sizes, goal)
    theta, target = {r.of: r.theta for r in state.collect()}, {r.source: r.target for r in goal.collect()}
    size = [len(t.split()) for *_, t in rows]
    total = sum(size)
    mean = sum(s * math.log1p(s) for s in size) / total
    spread = math.sqrt(sum(s * (math.log1p(s) - mean) ** 2 for s in size) / total)
    beta = dict(zip(tilt.languages, tilt.beta))
    assert set(beta) == {"en", "de", "fr", None} and any(abs(b) > 0.01 for b in beta.values())
    z = [(math.log1p(s) - mean) / spread for s in size]
    rate = [min(3.0, math.exp(theta[r[1]] + beta[r[2]] + tilt.nu * x)) for r, x in zip(rows, z)]
    for s, t in target.items():
        assert math.isclose(sum(n * q for r, n, q in zip(rows, size, rate) if r[1] == s), t, rel_tol=1e-5)
    for lang, b in beta.items():
        own = sum(n for r, n in zip(rows, size) if r[2] == lang)
        held = sum(n * q for r, n, q in zip(rows, size, rate) if r[2] == lang)
        assert abs(held - own / total * sum(target.values()) + mixing.RIDGE * total * b) <= 1e-5 * total
    assert abs(sum(n * q * x for n, q, x in zip(size, rate, z)) + mixing.RIDGE * total * tilt.nu) <= 1e-5 * total
    got = {r.doc_id: r.rate for r in mixing.mixed(df).collect()}
    assert all(math.isclose(got[r[0]], q, rel_tol=1e-5) for r, q in zip(rows, rate))


def test_query_on_given_tables(spark, sf):
    """Sizes and targets against SQL; every source within two words of its target, reruns agree."""
    import duckdb

    from harvestgrid.llm.queries import QUERIES

    got = QUERIES["op1_entropy_mix"](spark, sf).collect()
    sql = f"""
    WITH d AS (SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^ \\t-\\r]+')), 0)::BIGINT AS size FROM '{sf}/documents.parquet'),
    p AS (SELECT source, sum(size)::DOUBLE AS w FROM d GROUP BY source),
    r AS (SELECT *, ((row_number() OVER (ORDER BY source COLLATE "C" NULLS LAST) - 1) % 3 + 1)::DOUBLE AS k FROM p)
    SELECT d.doc_id, d.size, r.w::BIGINT AS source_size, r.k * (SELECT sum(w) / sum(k) FROM r) AS target, d.source FROM d JOIN r ON d.source IS NOT DISTINCT FROM r.source"""
    want = {x[0]: x for x in duckdb.sql(sql).fetchall()}
    assert len(got) == len(want) and all(x[3] <= 3 * x[2] for x in want.values())
    taken, goal = {}, {}
    for r in got:
        _, size, source_size, target, source = want[r.doc_id]
        assert (r.size, r.source_size) == (size, source_size) and math.isclose(r.target, target, rel_tol=1e-9) and r.taken <= 3 * r.size
        taken[source], goal[source] = taken.get(source, 0) + r.taken, target
    assert all(abs(taken[s] - t) <= 2 for s, t in goal.items())
    again = {r.doc_id: r.taken for r in QUERIES["op1_entropy_mix"](spark, sf).collect()}
    assert again == {r.doc_id: r.taken for r in got}
