import hashlib
import random

import numpy as np
import pytest

from harvestgrid.llm import bpe

tokenizers = pytest.importorskip("tokenizers")

ODD = [
    None, "", " ", "a", "aaa aaaaaaa", "Hello, wörld's  ΣΑΣ ΟΔΟΣ 12<|endoftext|>x İa", "<|startoftext|><|endoftext|><|nope|>",
    "é ﬁ Ǆ ẞ ß", "a b\x1cc\x85d e", "it's we'll they've I'm he'd 'tis ''s", "日本語テキスト 123 ٣٤ ²Ⅷ", "🙂🙂 👩‍👩‍👧 ​﻿", "x" * 5000, "ab" * 3000,
    "!!!???...", "\x00\x01", "ΣΣ ͅ", "K Å",
]


@pytest.fixture(scope="module")
def both():
    path = bpe.default_vocabulary()
    return tokenizers.Tokenizer.from_file(path), bpe.WordBpe(open(path, "rb").read())


def test_matches_library(both):
    lib, own = both
    rng = random.Random(3)
    texts = ODD + ["".join(rng.choice("abcdeéß' 1!.<|>\ńΣσ") for _ in range(rng.randrange(200))) for _ in range(300)]
    for t in texts:
        want = lib.encode(t or "", add_special_tokens=False).ids
        assert own.encode(t).tolist() == want, t
        assert own.decode(want) == lib.decode(want, skip_special_tokens=False), t


def test_round_trip_rows(spark, both):
    lib, _ = both
    rows = [(i, t, "x") for i, t in enumerate(ODD)] + [(None, "a b", "y"), (3, "a", None)]
    got = bpe.round_trip(spark.createDataFrame(rows, "doc_id long, text string, n_tokens string")).collect()
    assert len(got) == len(rows)
    for (_, t, _), r in zip(rows, got):
        ids = lib.encode(t or "", add_special_tokens=False).ids
        assert r.n_tokens == len(ids)
        assert r.ids_sha256 == hashlib.sha256(np.array(ids, dtype="<u4").tobytes()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256(lib.decode(ids, skip_special_tokens=False).encode()).hexdigest()
    back = bpe.decode(bpe.encode(spark.createDataFrame(rows[:6], "doc_id long, text string, z string"))).collect()
    assert [r.text for r in back] == [lib.decode(lib.encode(t or "").ids, skip_special_tokens=False) for _, t, _ in rows[:6]]
    assert bpe.round_trip(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_other_steps_are_refused(both):
    import json

    spec = json.loads(open(bpe.default_vocabulary(), "rb").read())
    for change in ({"normalizer": None}, {"pre_tokenizer": {"pretokenizers": spec["pre_tokenizer"]["pretokenizers"][:1]}}, {"decoder": {"type": "ByteLevel"}}):
        with pytest.raises(ValueError):
            bpe.WordBpe(json.dumps(spec | change).encode())


def test_special_tokens_of_any_form(both):
    import json

    spec = json.loads(open(bpe.default_vocabulary(), "rb").read())
    spec["added_tokens"][0]["content"] = "[BEGIN]"
    changed = json.dumps(spec)
    lib, own = tokenizers.Tokenizer.from_str(changed), bpe.WordBpe(changed.encode())
    for t in ("a [BEGIN] b", "[BEGIN][begin]", "x<|endoftext|>[BEGIN"):
        assert own.encode(t).tolist() == lib.encode(t, add_special_tokens=False).ids
