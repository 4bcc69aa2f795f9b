"""What Python workers and Arrow batches hold at once."""

import sys

import corpus_pipeline
from harvestgrid.llm import bpe, common, langid_crf, similar

_ROWS = "spark.sql.execution.arrow.maxRecordsPerBatch"


def test_encode_gets_small_batches(spark, monkeypatch):
    import pyarrow as pa

    def sizes(shared):
        def run(batches):
            for batch in batches:
                n = batch.num_rows
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([n] * n), *[pa.array(["x"] * n)] * 2], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

        return run

    monkeypatch.setattr(bpe, "_digests", sizes)
    own = spark.conf.get(_ROWS)
    docs = spark.range(0, 1500, 1, 1).selectExpr("id AS doc_id", "'some words' AS text")
    rows = corpus_pipeline.encode(spark, docs, "").collect()
    assert len(rows) == 1500 and max(r.n_tokens for r in rows) <= common.TEXT_ROWS
    assert spark.conf.get(_ROWS) == own


def test_smaller_session_setting_stays(spark):
    own = spark.conf.get(_ROWS)
    spark.conf.set(_ROWS, "7")
    try:
        with common.arrow_rows(spark, 256):
            assert spark.conf.get(_ROWS) == "7"
        assert spark.conf.get(_ROWS) == "7"
    finally:
        spark.conf.set(_ROWS, own)


def test_worker_keeps_tables_of_one_operator(monkeypatch):
    import pyarrow as pa

    monkeypatch.setattr(common, "_WORKER", {})
    model = langid_crf.train([("the and of", "en"), ("der die das", "de")])
    shared = type("Shared", (), {"value": model})
    batch = lambda: iter([pa.RecordBatch.from_pydict({"doc_id": [1], "text": ["the thing"]})])
    assert [r["lang_pred"] for b in langid_crf._predict_batches(shared, "a")(batch()) for r in b.to_pylist()]
    assert list(common._WORKER) == ["langid a"]
    list(similar._marks(iter([pa.RecordBatch.from_pydict({"doc_id": [1], "text": [b"the thing"], "digest": ["d"]})])))
    assert list(common._WORKER) == ["similar"]
    with open(bpe.default_vocabulary(), "rb") as f:
        shared = type("Shared", (), {"value": f.read()})
    list(bpe._digests(shared)(batch()))
    assert len(common._WORKER) == 1 and next(iter(common._WORKER)).startswith("bpe ")


def test_known_words_are_compact():
    with open(bpe.default_vocabulary(), "rb") as f:
        own = bpe.WordBpe(f.read())
    words = {f"word{k}" for k in range(500)} | set(map(chr, range(97, 123)))
    own.learn(words)
    assert all(isinstance(v, bytes) and sys.getsizeof(v) <= 33 + 4 * len(w) for w, v in own.known.items())
