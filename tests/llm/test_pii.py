import hashlib
import math
import random
import re

from harvestgrid.llm import pii

BASE = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def luhn(d):
    return sum(sum(divmod(2 * int(c), 10)) if k % 2 else int(c) for k, c in enumerate(reversed(d))) % 10 == 0


def base(text):
    out = []
    for rank, (kind, pattern) in enumerate(BASE.items()):
        for m in re.finditer(pattern, text or ""):
            d = re.sub(r"[^0-9]", "", m[0])
            ok = {"email": True, "ip": all(int(p) <= 255 for p in m[0].split(".")) if kind == "ip" else 0, "card": 12 <= len(d) <= 19 and luhn(d), "phone": 9 <= len(d) <= 15}[kind]
            if ok:
                out.append((m.start(), rank, m.end(), kind, m[0]))
    return sorted(out)


def line(spans):
    return ",".join(f"{k}:{a}:{b}" for a, _, b, k, *_ in spans)


def terms(texts):
    """Term spans per distinct text, straight from the definition."""
    rows = [t or "" for t in texts]
    near, has, words = {}, {}, {}
    for k, t in enumerate(rows):
        spans = base(t)
        for a, _, b, kind, v in spans:
            e = kind + ":" + (v.lower() if kind == "email" else v if kind == "ip" else re.sub(r"[^0-9]", "", v))
            has.setdefault(e, set()).add(k)
            low, high = max(0, a - 48), min(len(t), b + 48)
            for m in re.finditer(r"[^\W\d_]{2,}", t[low:high]):
                s, z = m.start() + low, m.end() + low
                if (s > low or low == 0) and (z < high or high == len(t)) and not any(o[0] < z and s < o[2] for o in spans):
                    near.setdefault((e, m[0].lower()), {}).setdefault(k, set()).add((s, z))
        for w in set(re.split(r"[\W\d_]+", t.lower())):
            words.setdefault(w, set()).add(k)
    out, n = {}, len(rows)
    for (e, w), where in near.items():
        if len({rows[k] for k in where}) >= 3:
            pmi = math.log(len(where) * n / (len(words[w]) * len(has[e])))
            if pmi > 0 and pmi >= 0.9 * math.log(n / len(has[e])):
                for k, places in where.items():
                    out.setdefault(rows[k], set()).update(places)
    return out


def check(spark, texts):
    rows = [(k, t) for k, t in enumerate(texts)]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "'x' AS spans", "1 AS n_email", "array(1) AS terms").repartition(4)
    got = {r.doc_id: r for r in pii.detect(df).collect()}
    extra = terms(texts)
    assert len(got) == len(rows)
    for k, t in rows:
        want = base(t)
        assert line(want) == ",".join(x for x in got[k].spans.split(",") if x and not x.startswith("term")), t
        assert got[k].base_sha256 == hashlib.sha256(line(want).encode()).hexdigest()
        assert [got[k][f"n_{x}"] for x in BASE] == [sum(s[3] == x for s in want) for x in BASE]
        both = sorted(want + [(a, 4, b, "term", "") for a, b in extra.get(t or "", ())])
        assert got[k].spans == line(both), (t, got[k].spans, line(both))
    return extra


def test_patterns(spark):
    rng = random.Random(4)
    texts = [None, "", " ", "a@b.co", "a@b.com_x@y.zz", "a@b.c.d@e.f", "x@@y.z a@b..c", "é🙂 a@b.co ü 1.2.3.4", "1.2.3.4.5.6.7.8 256.1.1.1 001.02.003.0255 0256.1.1.1", "4111 1111 1111 1111", "4111-1111-1111-1112 4111111111111111",
             "+1 (415) 555-2671 +12 +123456789012345678 ++1 23 45 67 89", "+1 2 3)(4.5-6 7 8 9-", "5" * 30, "1 2 3 4 5 6 7 8 9 0 1 2 3 4", "+4111111111111111"]
    texts += ["".join(rng.choice("ab1234567890..@@-+ ()_%é") for _ in range(rng.randrange(120))) for _ in range(300)]
    check(spark, texts)


def test_long_runs_stay_linear(spark):
    runs = [("a", 1), ("1", 1), ("1.", 1), ("1 ", 1), ("+1 ", 1), ("a@b.co ", 1), ("@", 1), ("1(", 1), (".y", 1)]
    check(spark, [x * 400 for x, _ in runs] + ["a.b" * 200 + "@x" + ".y" * 200])  # brute force is quadratic: short runs
    long = ["a" * 120_000, "1" * 120_000, "1." * 8_000, "1 " * 60_000, "+1 " * 40_000, "a.b" * 40_000 + "@x" + ".y" * 40_000, "a@b.co " * 1000, "@" * 50_000, "+" + "1(" * 50_000]
    got = pii.scanned(spark.createDataFrame(list(enumerate(long)), "doc_id long, text string")).selectExpr("doc_id", "size(spans) n").collect()
    assert {r.doc_id: r.n for r in got} == {0: 0, 1: 0, 2: 2000, 3: 0, 4: 0, 5: 1, 6: 1000, 7: 0, 8: 0}


def test_disclosing_terms(spark):
    rng = random.Random(1)
    words = ["".join(rng.choice("bcdfgklmn") + rng.choice("aeiou") for _ in range(3)) for _ in range(60)]
    texts = [" ".join(rng.choice(words) for _ in range(30)) for _ in range(60)]
    for k in range(5):  # "zanzi" is met almost only near this address
        texts[k] = texts[k][:70] + " zanzi boss@secret.example.com is " + texts[k][70:]
    texts += [texts[0], texts[0], None]
    extra = check(spark, texts)
    assert any("zanzi" in {t[a:b].lower() for a, b in x} for t, x in extra.items())
    df = spark.createDataFrame([(k, t, "s", len(t or "")) for k, t in enumerate(texts)], "doc_id long, text string, source string, n_chars long")
    clean = pii.sanitise(df)
    assert clean.columns == df.columns and clean.count() == len(texts)
    for r in clean.collect():
        t = texts[r.doc_id]
        if t is None or not base(t):
            assert r.text == t
        else:
            assert "boss@" not in r.text and "[EMAIL]" in r.text and "zanzi" not in r.text and r.n_chars == len(r.text)
    assert pii.detect(df.limit(0)).count() == 0 and pii.sanitise(df.limit(0)).count() == 0
