import zlib

import numpy as np

from harvestgrid.llm import compress_quality as cq


def test_rows_and_held_out_accuracy(spark):
    # sf0.1: the smaller table has too few bad labels (about 40) to train a dictionary on
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    odd = spark.createDataFrame([(900001, None, "en", None, 1), (900002, "", None, "s", 0), (None, "a b", None, "s", 2), (900004, "the thing " * 90_000, None, "s", 9)], docs.schema)
    both = docs.unionByName(odd).unionByName(docs.limit(1)).withColumn("score", docs.doc_id).withColumn("quality", docs.doc_id)
    model = cq.fit(docs, labels.withColumn("text", labels.doc_id.cast("string")))
    got = cq.score(both, model).collect()
    assert len(got) == 10005 and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.5) for r in got)
    by = {r.doc_id: r for r in got}
    assert by[900001].score == by[900002].score
    truth = {r.doc_id: r.quality for r in labels.collect() if zlib.crc32(str(r.doc_id).encode()) % 3 == 1}
    right = [by[i].predicted == q for i, q in truth.items() if i in by]
    assert np.mean(right) > 0.98
    bad = [by[i].score for i, q in truth.items() if q == 0]
    good = [by[i].score for i, q in truth.items() if q == 1]
    assert np.mean([b < g for b in bad for g in good]) > 0.99
    assert cq.score(docs.limit(0), model).count() == 0
    assert {r.score for r in cq.score(docs.limit(3), cq.fit(docs, labels.limit(0))).collect()} == {0.5}
    assert {r.score for r in cq.score(docs.limit(3), cq.fit(docs, labels.where("quality = 1"))).collect()} == {1.0}


def test_blocks_keep_everything():
    assert cq.blocks(b"") == [b""] and b"".join(cq.blocks(b"x" * 1300)) == b"x" * 1300


def test_query_against_plain_version(spark):
    import math

    import zstandard

    from harvestgrid.llm.queries import QUERIES

    sf = "/root/testdata/sf0.01"
    docs, labels = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels"))
    got = {r.doc_id: r for r in QUERIES["op2_compression_quality"](spark, sf).collect()}
    model = cq.fit(docs, labels)

    def packed(text, content):
        d = zstandard.ZstdCompressionDict(content)
        d.precompute_compress(level=cq.LEVEL)
        packer = zstandard.ZstdCompressor(level=cq.LEVEL, dict_data=d, write_content_size=False, write_dict_id=False)
        return sum(len(packer.compress(text[a : a + cq.BLOCK])) for a in range(0, max(1, len(text)), cq.BLOCK))

    rows = docs.select("doc_id", "text").collect()
    assert len(got) == len(rows)
    for r in rows[::10]:  # a fresh packer a text is slow
        text = (r.text or "").encode()
        good, bad = packed(text, model.good), packed(text, model.bad)
        n = max(1, len(text))
        x = [(bad - good) / (bad + good), min(good / n, 4.0), min(bad / n, 4.0)]
        z = [max(-5.0, min(5.0, (v - c) / s)) for v, c, s in zip(x, model.centre, model.spread)]
        total = sum(w * v for w, v in zip(model.weights, [1.0, *z, *[v * v for v in z]]))
        want = 1 / (1 + math.exp(-max(-30.0, min(30.0, total))))
        assert abs(got[r.doc_id].score - want) < 1e-9 and got[r.doc_id].predicted == (got[r.doc_id].score >= 0.5)
        assert got[r.doc_id].held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1)


def test_bytes_to_train_on():
    texts = [(bytes([65 + k % 20]) * 400 + b" word" * 30, k % 2) for k in range(60)]
    assert cq.train(texts, train_bytes=600).good != cq.train(texts).good
