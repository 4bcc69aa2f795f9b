import random
from itertools import combinations

from pyspark.sql import functions as F

import corpus_pipeline
from harvestgrid.llm import common, simhash, similar


def shingles(text):
    words = (text or "").lower().split()
    return {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()


def jaccard(a, b):
    return len(a & b) / len(a | b) if a | b else 1.0


def brute_kept(rows):
    sets = [shingles(t) for _, t in rows]
    part = list(range(len(rows)))
    for i, j in combinations(range(len(rows)), 2):
        if part[i] != part[j] and jaccard(sets[i], sets[j]) >= 0.8:
            low, high = sorted((part[i], part[j]))
            part = [low if p == high else p for p in part]
    return sorted(min(i for (i, _), q in zip(rows, part) if q == p) for p in set(part))


def edited(words, k, rng):
    words = list(words)
    for at in rng.sample(range(len(words)), k):
        words[at] = "x%d" % rng.randrange(10**9)
    return words


def test_stage_keeps_what_brute_force_keeps(spark):
    """Edits from none to far below 0.8, chains, a group of near copies, and odd texts."""
    rng = random.Random(4)
    vocabulary = ["w%d" % k for k in range(900)]
    texts = []
    for k in range(60):
        base = [rng.choice(vocabulary) for _ in range(rng.choice((60, 200, 600)))]
        texts.append(base)
        texts += [edited(base, n, rng) for n in (1, len(base) // 60, len(base) // 45, len(base) // 30, len(base) // 20)]
    base = [rng.choice(vocabulary) for _ in range(300)]
    texts += [edited(base, 8, rng) for _ in range(80)]
    texts += [["a"], ["A"], [], [], ["one", "two", "three", "four", "five", "six"]]
    rng.shuffle(texts)
    rows = [(k, " ".join(t)) for k, t in enumerate(texts)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    kept = [r.doc_id for r in corpus_pipeline.drop_near_duplicates(spark, df, "").collect()]
    assert sorted(kept) == brute_kept(rows)


def test_stage_on_given_documents(spark, sf):
    """All pairs at 0.8 or more, found by an inverted index, end in one group; nothing else is dropped."""
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    sets, held, common = [shingles(t) for _, t in rows], {}, {}
    for k, s in enumerate(sets):
        for x in s:
            held.setdefault(x, []).append(k)
    for ks in held.values():
        for p in combinations(ks, 2):
            common[p] = common.get(p, 0) + 1
    part = list(range(len(rows)))
    empty = [k for k, s in enumerate(sets) if not s]
    near = [p for p, n in common.items() if n >= 0.8 * (len(sets[p[0]]) + len(sets[p[1]]) - n)] + list(zip(empty, empty[1:]))
    for i, j in near:
        low, high = sorted((part[i], part[j]))
        part = [low if p == high else p for p in part]
    least = {}
    for (i, _), p in zip(rows, part):
        least[p] = min(i, least.get(p, i))
    got = {r.doc_id: r.component_id for r in similar.similar_groups(spark.read.parquet(f"{sf}/documents.parquet")).collect()}
    assert got == {i: least[p] for (i, _), p in zip(rows, part)}


def test_rows_without_id_and_empty_table(spark):
    rows = [(3, "a b c d e f"), (None, "a b c d e f"), (None, "lonely row"), (None, "Lonely  row"), (5, "dup"), (5, "dup"), (6, "dup"), (None, None), (7, "")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted(((r.doc_id, (r.text or "").lower().split()) for r in similar.keep_first(df).collect()), key=str)
    assert got == sorted([(3, "a b c d e f".split()), (None, ["lonely", "row"]), (5, ["dup"]), (7, [])], key=str)
    assert similar.keep_first(df.limit(0)).count() == 0


def test_repeated_ids_with_different_texts(spark):
    """What is nobody's copy stays, even where rows share an id; with and without ids, with null texts."""
    words = lambda c: " ".join(f"{c}{k}" for k in range(40))
    rows = [(1, words("a")), (1, words("b")), (1, words("b")), (2, words("b")), (3, words("c")), (None, words("c")), (None, words("d")), (None, words("d")), (4, None), (4, ""), (5, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "'x' AS digest", "1 AS keep_id", "'y' AS keep_text", "2 AS fp").repartition(4)
    for keep in (similar.keep_first, simhash.keep_first):
        out = keep(df)
        assert out.columns == df.columns
        got = sorted(((r.doc_id, r.text or "") for r in out.collect()), key=str)
        assert got == sorted([(1, words("a")), (1, words("b")), (3, words("c")), (None, words("d")), (4, "")], key=str)


def test_large_block_of_passage_sharers_makes_few_pairs(spark):
    """Texts that share most of a passage and near copies with many edits: pairs that are verified grow with the rows, not with their square."""
    rng = random.Random(8)
    word = lambda: "w%d" % rng.randrange(10**7)
    passage = [word() for _ in range(90)]
    texts = [[word() for _ in range(15)] + passage + [word() for _ in range(15)] for _ in range(500)]
    base = [word() for _ in range(150)]
    texts += [edited(base, rng.choice((1, 2, 4, 6, 8)), rng) for _ in range(250)]
    rows = [(k, " ".join(t)) for k, t in enumerate(texts)]
    made = []
    plain, similar._verified = similar._verified, lambda pairs, sets: made.append(pairs.count()) or plain(pairs, sets)
    try:
        kept = [r.doc_id for r in similar.keep_first(spark.createDataFrame(rows, "doc_id long, text string").repartition(4)).collect()]
    finally:
        similar._verified = plain
    assert sorted(kept) == brute_kept(rows)
    assert sum(made) < 10 * len(rows)


def test_fingerprints_bear_the_method():
    """SimHash by a plain count of bits; tiles, slots and forms agree with all pairs; 0.8 stays within the radius."""
    import numpy as np

    rng = np.random.default_rng(5)
    sets = [np.unique(rng.integers(0, 1 << 63, n, dtype=np.uint64)) for n in (1, 4, 300)]
    for s in sets:
        one = similar.fingerprint(s)
        bits = np.stack([np.unpackbits(np.frombuffer(similar.fingerprint(s[k : k + 1]), np.uint8)) for k in range(len(s))])
        assert np.array_equal(np.unpackbits(np.frombuffer(one, np.uint8)), bits.sum(axis=0) * 2 > len(s))
    near = []
    for n in (5, 9, 45, 400, 900):
        for _ in range(60):
            both = rng.integers(0, 1 << 63, n, dtype=np.uint64)
            more = max(1, int(n / 0.8) - n)
            near.append((np.unique(both), np.unique(np.concatenate([both, rng.integers(0, 1 << 63, more, dtype=np.uint64)]))))
    for bits in (similar.BITS, similar.WIDE):
        for a, b in near:
            if len(a) >= 0.8 * len(b):
                apart = np.bitwise_count(np.frombuffer(similar.fingerprint(a, bits), np.uint64) ^ np.frombuffer(similar.fingerprint(b, bits), np.uint64)).sum()
                assert apart <= similar.radius(np.array([len(a)]), bits)[0]
    flat = [s for p in near for s in p]
    size = np.array([len(s) for s in flat])
    sim = np.stack([np.frombuffer(similar.fingerprint(s), np.uint64) for s in flat])
    root = np.arange(len(flat)) // 3
    apart = np.bitwise_count(sim[:, None] ^ sim[None]).sum(axis=2)
    low, high = np.minimum(size[:, None], size[None]), np.maximum(size[:, None], size[None])
    want = (apart <= similar.radius(low)) & (5 * low >= 4 * high) & (root[:, None] != root[None]) & np.tri(len(flat), k=-1, dtype=bool)
    got = set(zip(*(x.tolist() for x in similar.near_pairs(sim, size, size, root, "all"))))
    assert got == set(zip(*(x.tolist() for x in np.nonzero(want))))
    slot = rng.integers(0, 2, len(flat))
    across = set(zip(*(x.tolist() for x in similar.near_pairs(sim, size, size, root, "all", slot))))
    assert across == {(i, j) for i, j in got if slot[i] != slot[j]}
    for form in ("first", "nearest"):
        some = set(zip(*(x.tolist() for x in similar.near_pairs(sim, size, size, root, form))))
        assert some <= got and {i for p in some for i in p} == {i for p in got for i in p}


def test_large_blocks_dealt_to_several_tasks(spark, monkeypatch):
    rng = random.Random(3)
    base = ["w%d" % rng.randrange(10**6) for _ in range(200)]
    rows = [(k, " ".join(edited(base, rng.choice((1, 3, 6, 9)), rng))) for k in range(90)]
    monkeypatch.setattr(similar, "TILE_ROWS", 16)
    got = sorted(r.doc_id for r in similar.keep_first(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert got == brute_kept(rows)


def _shuffle_files(spark):
    found = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
    files = [found.apply(k) for k in range(found.size())]
    return {f.getName(): f.length() for f in files if f.getName().startswith("shuffle_") and f.getName().endswith(".data")}


def test_texts_that_stay_are_not_shuffled(spark, tmp_path):
    """What is nobody's copy goes from scan to result; only texts in doubt and hashes of candidates are dealt out."""
    rng = random.Random(12)
    texts = [["%08x" % rng.getrandbits(32) for _ in range(1500)] for _ in range(300)]
    texts += [edited(t, 5, rng) for t in texts[:20]]
    rows = [(k, " ".join(t)) for k, t in enumerate(texts)]
    spark.createDataFrame(rows, "doc_id long, text string").repartition(4).write.parquet(f"{tmp_path}/docs")
    before = _shuffle_files(spark)
    out = similar.keep_first(spark.read.parquet(f"{tmp_path}/docs"))
    out.write.parquet(f"{tmp_path}/out")
    moved = sum(n for name, n in _shuffle_files(spark).items() if name not in before)
    assert sorted(r.doc_id for r in spark.read.parquet(f"{tmp_path}/out").select("doc_id").collect()) == list(range(300))
    assert moved < sum(len(t) for _, t in rows) / 2


def test_sieve_loses_no_key(spark, monkeypatch):
    """All keys pass, few others do, the rest is the complement; with far too few words still no key is lost."""
    keys = spark.range(0, 30_000, 3).withColumnRenamed("id", "k")
    rows = spark.range(0, 60_000).select("id")
    for words, most in ((common.SIEVE_WORDS, 1500), (1, 50_000)):
        monkeypatch.setattr(common, "SIEVE_WORDS", words)
        passed = common.sieve(keys)
        got = {r.id for r in passed(rows, F.col("id")).collect()}
        rest = {r.id for r in passed(rows, F.col("id"), "left_anti").collect()}
        assert got >= set(range(0, 30_000, 3)) and len(got) - 10_000 <= most
        assert not got & rest and got | rest == set(range(60_000))
    assert common.sieve(keys.limit(0))(rows, F.col("id")).count() == 0


def test_sieves_that_let_all_pass_change_nothing(spark, monkeypatch):
    """Every sieve is followed by an exact step: copies, near copies, repeated rows and rows without id as by brute force."""
    rng = random.Random(6)
    base = [["w%d" % rng.randrange(10**5) for _ in range(120)] for _ in range(25)]
    texts = [edited(b, n, rng) for b in base for n in (0, 0, 2, 4, 30)]
    rows = [(k, " ".join(t)) for k, t in enumerate(texts)]
    rows += rows[:40] * 3
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(6)
    monkeypatch.setattr(common, "SIEVE_WORDS", 1)
    assert sorted(r.doc_id for r in similar.keep_first(docs).collect()) == brute_kept(rows[: len(texts)])
