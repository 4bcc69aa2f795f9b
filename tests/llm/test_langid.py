import itertools
import zlib

import numpy as np

from harvestgrid.llm import langid_crf as crf


def test_forward_backward_is_exact():
    rng = np.random.default_rng(0)
    scores, trans = rng.normal(size=(4, 2, 3)), rng.normal(size=(3, 3))
    valid = np.array([[1, 1], [1, 1], [1, 1], [1, 0]], dtype=bool)
    post, pairs = crf.forward_backward(scores, valid, trans)
    want_pairs = np.zeros((3, 3))
    for c, n in enumerate((4, 3)):
        want, total = np.zeros((n, 3)), 0.0
        paths = {}
        for path in itertools.product(range(3), repeat=n):
            w = np.exp(sum(scores[k, c, y] for k, y in enumerate(path)) + sum(trans[a, b] for a, b in zip(path, path[1:])))
            paths[path] = w
            total += w
        for path, w in paths.items():
            for k, y in enumerate(path):
                want[k, y] += w / total
            for a, b in zip(path, path[1:]):
                want_pairs[a, b] += w / total
        assert np.allclose(post[:n, c], want)
    assert np.allclose(pairs, want_pairs)


def test_code_switched_words(spark, sf):
    rows = spark.read.parquet(f"{sf}/documents.parquet").where("lang in ('de', 'es')").orderBy("doc_id").limit(200).collect()
    model = crf.train([(r.text, r.lang) for r in rows[:150]])
    de, es = (next(crf.words_of(r.text) for r in rows[150:] if r.lang == x and r.n_chars > 600)[:40] for x in ("de", "es"))
    tags = [t for _, t in model.tag(" ".join(de + es + de))]
    assert np.mean([t == w for t, w in zip(tags, ["de"] * 40 + ["es"] * 40 + ["de"] * 40)]) > 0.9


def test_rows(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    odd = spark.createDataFrame([(9001, None, "en", None, 1), (9002, "", None, "s", 0), (9003, "123 !!", "en", "s", 1), (None, "the and of", None, "s", 2), (9004, "the thing " * 40_000, None, "s", 9)], docs.schema)
    both = docs.unionByName(odd).unionByName(docs.limit(1))
    got = crf.predict(both, crf.fit(docs)).collect()
    assert len(got) == 1006
    by = {r.doc_id: r for r in got}
    assert all(by[i].lang_pred == "und" and by[i].score == 0 for i in (9001, 9002, 9003)) and by[9004].lang_pred == "en"
    held = [(r.lang, by[r.doc_id].lang_pred) for r in docs.collect() if zlib.crc32(str(r.doc_id).encode()) % 4 == 2 and r.lang]
    assert np.mean([a == b for a, b in held]) > 0.97
    assert all(0 <= r.score <= 1 for r in got)
    kept = crf.keep_identified(both)
    assert kept.columns == both.columns and kept.count() == 1003
    assert crf.predict(docs.limit(0), crf.fit(docs.limit(0))).count() == 0
    assert {r.lang_pred for r in crf.predict(docs.limit(5), crf.fit(docs.limit(0))).collect()} == {"und"}


def plain_prediction(text, model, cache):
    """Word by word, gram by gram, in logarithms."""
    full = (1 << 64) - 1
    a, b = 0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F

    def emission(word):
        if word not in cache:
            marked = [ord(x) for x in f"\x02{word}\x03"]
            found = [crf.BUCKETS + model.lexicon[word]] if word in model.lexicon else []
            for n in (2, 3, 4, 5):
                for at in range(len(marked) - n + 1):
                    if n < 4 or at == 0 or at + n == len(marked):
                        code = marked[at] * a & full
                        for k in range(1, n):
                            code = (code * b + marked[at + k] * a + k + 1) & full
                        found.append((code * b & full) >> 40 & crf.BUCKETS - 1)
            cache[word] = model.weights[found].astype(float).sum(axis=0) / max(1, len(found)) ** 0.5
        return cache[word]

    words, marginals = crf.words_of(text), []
    if not words:
        return "und", 0.0
    for at in range(0, len(words), crf.CHAIN):
        e = [emission(w) for w in words[at : at + crf.CHAIN]]
        ahead = [e[0]]
        for x in e[1:]:
            ahead.append(np.logaddexp.reduce(ahead[-1][:, None] + model.trans, axis=0) + x)
        back = [np.zeros(len(model.labels))]
        for x in e[:0:-1]:
            back.append(np.logaddexp.reduce(model.trans + (x + back[-1])[None, :], axis=1))
        for f, g in zip(ahead, back[::-1]):
            p = np.exp(f + g - np.logaddexp.reduce(f + g))
            marginals.append(p)
    mean = np.mean(marginals, axis=0)
    return model.labels[int(mean.argmax())], float(mean.max())


def test_query_against_plain_version(spark):
    from harvestgrid.llm.queries import QUERIES

    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = {r.doc_id: r for r in QUERIES["op6_crf_language"](spark, sf).collect()}
    model, cache = crf.fit(docs), {}
    rows = docs.select("doc_id", "text").collect()
    assert len(got) == len(rows)
    for r in rows:
        lang, score = plain_prediction(r.text, model, cache)
        assert got[r.doc_id].lang_pred == lang and abs(got[r.doc_id].score - score) < 1e-4
        assert got[r.doc_id].held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2)
