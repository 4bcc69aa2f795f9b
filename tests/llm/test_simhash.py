import random
import re

import numpy as np
import xxhash

from harvestgrid.llm import simhash


def brute_print(text):
    words = re.findall(r"[^\x20\x09-\x0d]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def test_fingerprint():
    for t in [None, "", " \t\n", "A", "a b", "a b c", "a b c d É\x1cx \x85 y", "The the THE the the", "x " * 4000]:
        assert simhash.fingerprint(t.encode() if t is not None else None) == brute_print(t)


def brute_components(rows):
    fps = [brute_print(t) for _, t in rows]
    part = list(range(len(rows)))
    changed = True
    while changed:
        changed = False
        for i in range(len(rows)):
            for j in range(len(rows)):
                if part[j] != part[i] and bin(fps[i] ^ fps[j]).count("1") <= 3:
                    part[i] = part[j] = min(part[i], part[j])
                    changed = True
    least = {}
    for (i, _), p in zip(rows, part):
        if i is not None:
            least[p] = min(i, least.get(p, i))
    return sorted(((i, "%016x" % f, least.get(p)) for (i, _), f, p in zip(rows, fps, part)), key=str)


def test_components(spark):
    rng = random.Random(2)
    words = ["w%d" % k for k in range(400)]
    rows = []
    for k in range(40):
        base = [rng.choice(words) for _ in range(120)]
        rows.append((100 - k, " ".join(base)))
        for m in range(rng.randrange(4)):
            base[rng.randrange(120)] = "edit%d" % m
            rows.append((1000 + 10 * k + m, " ".join(base)))
    rows += [(7, None), (3, ""), (9, " "), (None, "lonely row"), (None, rows[0][1]), (5, "dup"), (5, "dup"), (6, "dup")]
    df = spark.createDataFrame([(i, t, "s", 1) for i, t in rows], "doc_id long, text string, fp string, component_id int").repartition(5)
    want = brute_components(rows)
    for tile in (2048, 4):  # 4: hot keys are dealt as pairs of tiles
        got = simhash.near_duplicates(df, tile_rows=tile).collect()
        assert sorted(((r.doc_id, "%016x" % (r.fp % (1 << 64)), r.component_id) for r in got), key=str) == want
    kept = simhash.keep_first(df)
    assert kept.columns == df.columns
    rows_kept = [r.doc_id for r in kept.collect()]
    assert sorted(i for i in rows_kept if i is not None) == sorted({c for i, _, c in want if c is not None and i == c})
    assert rows_kept.count(None) == len({f for i, f, c in want if i is None and c is None})
    assert simhash.near_duplicates(df.limit(0)).count() == 0


def test_hot_key_tiles_lose_no_link(spark):
    rng = np.random.default_rng(1)
    base = rng.integers(0, 1 << 63, dtype=np.uint64)
    fps = {int(base)}
    for _ in range(1500):  # many within a few bits of each other
        x = int(base)
        for b in rng.integers(0, 20, size=rng.integers(1, 7)):
            x ^= 1 << int(b)
        fps.add(x)
    fps = sorted(fps)
    signed = np.array(fps, dtype=np.uint64).view(np.int64).tolist()
    got = simhash.components(simhash.links(spark.createDataFrame([(x,) for x in signed], "fp long"), tile_rows=64)).collect()
    arr = np.array(fps, dtype=np.uint64)
    i, j = simhash.linked_pairs(arr, 3)
    near = np.bitwise_count(arr[:, None] ^ arr[None]) <= 3
    assert len(i) == (near.sum() - len(arr)) // 2
    root = simhash._roots(len(arr), i, j)
    groups = {}
    for k, r in enumerate(root):
        groups.setdefault(int(r), set()).add(signed[k])
    own = {}
    for r in got:
        own.setdefault(r.root, set()).add(r.node)
    assert sorted(map(sorted, own.values())) == sorted(sorted(g) for g in groups.values() if len(g) > 1)
