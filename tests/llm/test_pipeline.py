"""The stages on a small corpus with odd rows, each against a plain version of its decision."""

import hashlib

import pytest

import corpus_pipeline
from harvestgrid.llm import bpe, langid_crf, mixing, pii


def brute_kept(rows):
    """Ids of the kept rows: the smallest id of each group (none only where no row of the group has one)."""
    words = [(t or "").lower().split() for _, t in rows]
    sets = [{tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set() for w in words]
    part = list(range(len(rows)))
    for i, a in enumerate(sets):
        for j in range(i):
            b = sets[j]
            if part[i] != part[j] and min(len(a), len(b)) >= 0.8 * max(len(a), len(b)) and len(a & b) >= 0.8 * len(a | b):
                part = [part[j] if p == part[i] else p for p in part]
    return [min((i for (i, _), q in zip(rows, part) if q == p), key=lambda i: (i is None, i or 0)) for p in set(part)]


@pytest.fixture(scope="module")
def corpus(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    first = docs.where("text is not null and n_chars > 300").orderBy("doc_id").first()
    odd = [
        (90001, None, "en", None, None), (90002, "", None, "s", 0), (90003, "123 456", "en", "s", 7), (None, "the and of the", None, "s", 14), (90004, first.text, "en", "src0", first.n_chars),
        (90005, "the thing and the other " * 4000, None, "s", 96_000), (90006, "write to ann@mail.example.org or +1 (415) 555-2671 for the thing and this", "en", None, 70),
    ]
    return docs.unionByName(spark.createDataFrame(odd, docs.schema))


def test_stages(spark, corpus):
    docs = corpus
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, "/root/testdata/sf0.001")
        assert out.columns == docs.columns and [t for _, t in out.dtypes] == [t for _, t in docs.dtypes], name
        before, after = docs.collect(), out.cache().collect()
        ids = lambda rows: sorted((r.doc_id for r in rows), key=lambda i: (i is None, i or 0))
        if name == "language_id":
            gone = [r for r in before if not langid_crf.words_of(r.text)]
            assert len(after) == len(before) - len(gone) and {90001, 90002, 90003} <= {r.doc_id for r in gone}
            assert all(r.lang in ("de", "en", "es", "fr") for r in after)
        elif name == "near_dedup":
            # Equal rows of the rule: five-word Jaccard similarity of 0.8 or more, by reachability.
            assert ids(after) == sorted(brute_kept([(r.doc_id, r.text) for r in before]), key=lambda i: (i is None, i or 0))
            assert 90004 not in ids(after)
        elif name == "pii":
            assert ids(before) == ids(after)
            text = {r.doc_id: r for r in after}
            assert text[90006].text == "write to [EMAIL] or [PHONE] for the thing and this" and text[90006].n_chars == len(text[90006].text)
        else:
            copies = {r.doc_id: r.copies for r in mixing.mixed(docs).collect()}
            assert ids(after) == ids([r for r in before for _ in range(copies[r.doc_id])])
        docs = out
    coded = corpus_pipeline.STAGES[-1][1](spark, docs, "").collect()
    own = bpe.WordBpe(open(bpe.default_vocabulary(), "rb").read())
    want = sorted((len(own.encode(r.text)), hashlib.sha256(own.encode(r.text).tobytes()).hexdigest()) for r in docs.collect())
    assert sorted((r.n_tokens, r.ids_sha256) for r in coded) == want


def test_clashing_columns(spark, corpus):
    names = "terms term_key spans text_key root fp size key of rate copies bin term entity score lang_pred target whole row ids n".split()
    docs = corpus.limit(60).selectExpr("*", *[f"'{n}' AS {n}" for n in names])
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, "")
        assert out.columns == docs.columns, name
        assert out.where(" or ".join(f"{n} <> '{n}'" for n in names)).count() == 0
        docs = out
    assert corpus_pipeline.STAGES[-1][1](spark, docs, "").count() == docs.count()


def test_empty_table(spark, corpus):
    docs = corpus.limit(0)
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, "")
        assert docs.count() == 0


def test_registered_run(spark):
    assert corpus_pipeline.run(spark, "/root/testdata/sf0.001").count() > 150
    assert pii.KINDS == ("email", "ip", "card", "phone")
