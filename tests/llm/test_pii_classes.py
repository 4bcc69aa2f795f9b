"""Terms that disclose a class of values, evidence from distinct surroundings, and broader terms."""

import random

import pytest

from harvestgrid.llm import pii


def prose(rng, words, n):
    return " ".join(rng.choice(words) for _ in range(n))


def corpus(near_copies=False):
    """"kundenruf" stands by forty phone numbers, no two alike; "bankaria" by 25 mail addresses of one domain."""
    rng = random.Random(3)
    words = ["".join(rng.choice("bcdfgklmn") + rng.choice("aeiou") for _ in range(3)) for _ in range(80)]
    texts = [prose(rng, words, 30) for _ in range(400)]
    fixed = prose(rng, words, 12)
    for k in range(40):
        left, right = (fixed, fixed) if near_copies else (prose(rng, words, 12), prose(rng, words, 12))
        texts[k] = f"{left} kundenruf +1 (415) 555-{1000 + k} {right}" + (f" tail{'abcdefghij'[k % 10]}{'abcdefghij'[k // 10]}" if near_copies else "")
    for k in range(40, 65):
        left, right = (fixed, fixed) if near_copies else (prose(rng, words, 12), prose(rng, words, 12))
        texts[k] = f"{left} bankaria p{k}@mail.bank.example {right}"
    texts[70] += " kundenruf and bankaria"  # no personal data here
    return texts


def told(spark, texts):
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    return {r.term for r in pii.disclosing(df, pii.scanned(df)).collect()}, df


def test_classes_disclose(spark):
    texts = corpus()
    found, df = told(spark, texts)
    assert found == {"kundenruf", "bankaria"}
    rows = {r.doc_id: r for r in pii.detect(df).collect()}
    assert rows[70].n_term == 2 and rows[70].n_phone == 0 and rows[45].n_term == 1 and rows[71].n_term == 0
    assert {r.n_term for r in rows.values()} == {0, 1, 2}


def test_near_copies_are_no_evidence(spark):
    """The same surroundings forty times: one piece of evidence."""
    found, _ = told(spark, corpus(near_copies=True))
    assert found == set()


def test_broader_terms(spark):
    texts = corpus()
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    table = [("kundenruf", "bankaria"), ("Bankaria", "Contact"), ("other", "thing")]
    out = {r.doc_id: r.text for r in pii.sanitise(df, broader=spark.createDataFrame(table, "term string, broader string")).collect()}
    assert out[70] == texts[70].replace("kundenruf", "Contact").replace("bankaria", "Contact")  # past a term that discloses too
    plain = {r.doc_id: r.text for r in pii.sanitise(df).collect()}
    assert plain[70] == texts[70].replace("kundenruf", "[TERM]").replace("bankaria", "[TERM]")


def test_lower_limit(spark):
    rows = spark.createDataFrame([(1.0, 10.0), (0.5, 40.0), (0.0, 5.0)], "p double, n double")
    got = [r[0] for r in rows.select(pii._lower_limit(rows.p, rows.n, 1.96)).collect()]
    assert got == pytest.approx([10 / (10 + 1.96**2), 0.35199, 0.0], abs=1e-4)
