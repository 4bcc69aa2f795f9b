"""Disclosing terms are found and removed wherever they stand."""

import random
import re

from harvestgrid.llm import pii


def corpus():
    rng = random.Random(8)
    words = ["".join(rng.choice("bcdfgklmn") + rng.choice("aeiou") for _ in range(3)) for _ in range(60)]
    prose = lambda n: " ".join(rng.choice(words) for _ in range(n))
    texts = [prose(30) for _ in range(300)]
    for k in range(20):
        texts[k] = f"{prose(10)} zanzi boss@secret.example.com {prose(10)}"
    texts[2] += " " + prose(40) + " Zanzi, zanzibar"  # far from the address
    texts.append(prose(20) + " about ZANZI and pre-zanzi " + prose(20))  # no base span at all
    texts.append("x " * 12_000 + "zanzi " + "y. " * 12_000)
    return texts + [texts[300], None]


def test_terms_are_marked_in_every_text(spark):
    texts = corpus()
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    for r in pii.detect(df).collect():
        t = texts[r.doc_id] or ""
        want = {(m.start(), m.end()) for m in re.finditer(r"[^\W\d_]{2,}", t) if m[0].lower() == "zanzi"}
        got = {tuple(map(int, s.split(":")[1:])) for s in r.spans.split(",") if s.startswith("term")}
        assert got == want and r.n_term == len(want), t[:200]


def test_sanitised_texts_keep_no_disclosing_term(spark):
    texts = corpus()
    df = spark.createDataFrame([(k, t, len(t or "")) for k, t in enumerate(texts)], "doc_id long, text string, n_chars long")
    for r in pii.sanitise(df).collect():
        want = texts[r.doc_id]
        if want is not None:
            want = re.sub(r"(?<![^\W\d_])zanzi(?![^\W\d_])", "[TERM]", want.replace("boss@secret.example.com", "[EMAIL]"), flags=re.IGNORECASE)
        assert r.text == want and r.n_chars == len(want or "")


def test_counts_are_of_whole_texts(spark):
    """Near the address in three texts, but with it in all five: every text counts."""
    filler = lambda k: " ".join("f%s" % "abcdefghij"[(k + i) % 10] * 3 for i in range(40))
    texts = [f"{filler(k)} tell boss@secret.example.com {filler(k)}" for k in range(5)]
    texts = [t.replace("tell", "zanzi") if k < 3 else t + " zanzi" for k, t in enumerate(texts)] + [filler(k) for k in range(60)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: r for r in pii.detect(df).collect()}
    for k in range(5):
        at = texts[k].index("zanzi")
        assert f"term:{at}:{at + 5}" in got[k].spans.split(",")
