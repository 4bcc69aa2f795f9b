"""Personal data: pattern spans, and terms that disclose them.

Base spans come from fixed patterns (addresses of mail and machines, payment cards,
phone numbers). Around them an information-theoretic test adds terms: a word t
seen near a protected value e discloses it when their pointwise mutual
information reaches a share of what there is to learn about e,

    PMI(t; e) = ln( p(t, e) / (p(t) p(e)) ) >= disclosure * IC(e),   IC(e) = -ln p(e),

with probabilities counted over the rows of the whole corpus (p(t, e): rows with both anywhere
in the text), and only if at least ``support`` distinct texts have t near e, so that a chance meeting of rare
words in one text, however often copied, tells nothing. Entities are literal values and the classes they
belong to: a mail domain, a network, a card issuer, a phone area, and each kind as a whole. A class is met in many
places, so chance meetings are frequent; there p(t, e) / p(t) is replaced by its lower confidence
limit (Wilson's, at ``z``) for as many trials as there are distinct surroundings with t near e. Near copies
of a text share their surroundings and count once.

Disclosing terms become spans wherever they stand, in every text, whether it has other spans or not. ``sanitise``
replaces spans by the name of their kind, and a term by its nearest broader term that
discloses nothing, where a table of broader terms has one.

Everything is DataFrame expressions. Patterns are written so that the matcher
never rescans a run of characters (possessive repeats, a start only at the
beginning of a run or where the last match ended), which changes no match but
keeps long runs linear. Positions are sums of the lengths between matches.

Defined results: null and empty texts have no spans. Copies of a text get equal spans. Overlapping spans are all reported; ``sanitise`` replaces their
union. Other columns pass through.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import spool

KINDS = ("email", "ip", "card", "phone")
#: Fixed patterns of the contract, in linear form.
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[ -]?[0-9])++",
    "phone": r"\+[0-9][ ().0-9-]+[0-9]",
}
#: What a text needs to have any valid match at all.
_POSSIBLE = {"email": "@", "ip": r"[0-9]\.[0-9]++\.[0-9]", "card": r"[0-9](?:[ -]?[0-9]){11}", "phone": r"\+[0-9]"}
_BYTE = r"0*+(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9]|)"
_IP = rf"^(?!\.)(?:{_BYTE})\.(?:{_BYTE})\.(?:{_BYTE})\.(?:{_BYTE})$"
_TERM = r"\p{L}{2,}+"
#: Code points on both sides of a span in which terms are looked for.
CONTEXT, SUPPORT, DISCLOSURE = 48, 3, 0.9
#: Confidence of the lower limit for classes: 1.96 is 97.5 % on one side.
CONFIDENCE = 1.96
#: Steps up a table of broader terms at most.
STEPS_UP = 8


def located(text: Column, pattern: str) -> Column:
    """All matches with their places: array<struct<start, end, value>>, in code points."""
    gaps = F.zip_with(F.split(text, pattern, -1), F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), lambda g, h: F.struct(F.char_length(g).alias("gap"), h.alias("hit")))
    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<start:int,end:int,value:string>>").alias("out"))

    def step(acc, x):
        a = acc["at"] + x["gap"]
        b = a + F.char_length(x["hit"])
        grown = F.concat(acc["out"], F.array(F.struct(a.alias("start"), b.alias("end"), x["hit"].alias("value"))))
        return F.when(x["hit"].isNull(), acc).otherwise(F.struct(b.alias("at"), grown.alias("out")))

    return F.aggregate(gaps, start, step, lambda acc: acc["out"])


def luhn(digits: Column) -> Column:
    """Whether a string of digits passes the mod-10 check."""
    n = F.char_length(digits)

    def part(i):
        d = F.substring(digits, n - i, F.lit(1)).cast("int")
        twice = d * 2
        return F.when(i % 2 == 1, twice - F.when(twice > 9, 9).otherwise(0)).otherwise(d)

    return F.aggregate(F.transform(F.sequence(F.lit(0), n - 1), part), F.lit(0), lambda a, x: a + x) % 10 == 0


def _valid(kind: str, value: Column) -> Column:
    digits = F.regexp_replace(value, "[^0-9]", "")
    if kind == "ip":
        return value.rlike(_IP)
    if kind == "card":
        return F.when(F.char_length(digits).between(12, 19), luhn(digits)).otherwise(False)
    if kind == "phone":
        return F.char_length(digits).between(9, 15)
    return F.lit(True)


def _words(text: Column) -> Column:
    """Distinct words of the whole text, in lower case."""
    return F.array_distinct(F.transform(F.regexp_extract_all(text, F.lit(_TERM), F.lit(0)), F.lower))


_SPAN = "array<struct<start:int,rank:int,end:int,kind:string,value:string>>"


def base_spans(text: Column) -> Column:
    """Valid matches of all patterns, by start, then kind."""
    return F.array_sort(F.concat(*[_kind_spans(text, rank, kind) for rank, kind in enumerate(KINDS)]))


def _kind_spans(text: Column, rank: int, kind: str) -> Column:
    possible = text.contains("@") if kind == "email" else text.rlike(_POSSIBLE[kind])
    hits = F.filter(located(text, PATTERNS[kind]), lambda s: _valid(kind, s["value"]))
    parts = lambda s: F.struct(s["start"].alias("start"), F.lit(rank).alias("rank"), s["end"].alias("end"), F.lit(kind).alias("kind"), s["value"].alias("value"))
    return F.when(possible, F.transform(hits, parts).cast(_SPAN)).otherwise(F.array().cast(_SPAN))


def _masked(text: Column, spans: Column) -> Column:
    """The text, as long as before, with every code point of a span made a sign that is no letter."""
    start = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))

    def step(acc, s):
        low, high = F.greatest(acc["at"], s["start"]), F.greatest(acc["at"], s["end"])
        out = F.concat(acc["out"], F.substring(text, acc["at"] + 1, low - acc["at"]), F.repeat(F.lit("#"), high - low))
        return F.struct(high.alias("at"), out.alias("out"))

    return F.aggregate(spans, start, step, lambda acc: F.concat(acc["out"], F.substring(text, acc["at"] + 1, F.char_length(text) - acc["at"])))


def _contexts(text: Column, spans: Column, width: int) -> Column:
    """For each span its entities and the whole words around it: array<struct<entities, terms, around>>; words inside any span don't count.

    ``entities`` are the value itself, its class and its kind; ``around`` is a digest of the set of words.

    The outer transform over one element binds what all spans share, so that it is computed once a row.
    """
    shared = F.array(F.struct(_masked(text, spans).alias("text"), F.char_length(text).alias("size"), spans.alias("spans")))

    def of_row(z):
        def around(s):
            low = F.greatest(F.lit(0), s["start"] - width)
            high = F.least(z["size"], s["end"] + width)
            words = located(F.substring(z["text"], low + 1, high - low), _TERM)
            moved = F.transform(words, lambda w: F.struct((w["start"] + low).alias("start"), (w["end"] + low).alias("end"), F.lower(w["value"]).alias("term")))
            whole = F.filter(moved, lambda w: ((w["start"] > low) | (low == 0)) & ((w["end"] < high) | (high == z["size"])))
            terms = F.array_sort(F.array_distinct(F.transform(whole, lambda w: w["term"])))
            return F.struct(_entities(s).alias("entities"), terms.alias("terms"), F.xxhash64(F.concat_ws(" ", terms)).alias("around"))

        return F.transform(z["spans"], around)

    return F.transform(shared, of_row)[0]


def _entities(s: Column) -> Column:
    """What a span tells: its value, the class of that value, its kind."""
    kind, digits = s["kind"], F.regexp_replace(s["value"], "[^0-9]", "")
    plain = F.when(kind == "email", F.lower(s["value"])).when(kind == "ip", s["value"]).otherwise(digits)
    domain, network = F.substring_index(F.lower(s["value"]), "@", -1), F.substring_index(s["value"], ".", 3)
    area = F.substring(digits, F.lit(1), F.char_length(digits) - 7)
    wider = F.when(kind == "email", domain).when(kind == "ip", network).when(kind == "card", F.substring(digits, 1, 6)).otherwise(area)
    return F.array(F.concat(kind, F.lit(":"), plain), F.concat(kind, F.lit(" of "), wider), kind)


def scanned(docs: DataFrame, context: int = CONTEXT) -> DataFrame:
    """doc_id, text_key, spans, contexts and words (of rows with spans) of every row, written once."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text"))
    both = F.transform(
        F.array(base_spans(F.col("text"))),
        lambda spans: F.struct(spans.alias("spans"), F.when(F.size(spans) > 0, _contexts(F.col("text"), spans, context)).alias("contexts"), F.when(F.size(spans) > 0, _words(F.col("text"))).alias("words")),
    )[0]
    return spool(rows.select("doc_id", F.md5(F.col("text").cast("binary")).alias("text_key"), both.alias("b")).select("doc_id", "text_key", "b.spans", "b.contexts", "b.words"), "scanned")


def disclosing(docs: DataFrame, found: DataFrame, support: int = SUPPORT, disclosure: float = DISCLOSURE, z: float = CONFIDENCE) -> DataFrame:
    """The distinct terms that disclose some entity."""
    held = found.where("size(spans) > 0")
    n = F.lit(float(max(1, found.count())))
    # Probabilities count rows: of the entity, of both, and, over the whole corpus, of the term; each is summed in a task before the shuffle.
    entities = F.array_distinct(F.flatten(F.transform("contexts", lambda c: c["entities"])))
    entity = spool(held.select(F.explode(entities).alias("entity")).groupBy("entity").agg(F.count(F.lit(1)).alias("n_entity")), "entities")
    # The evidence for a value is distinct texts, that for a class distinct surroundings, so that copies are no evidence of their own.
    each = held.select("text_key", F.explode("contexts").alias("c"))
    each = each.select("text_key", "c.around", "c.terms", F.posexplode("c.entities").alias("level", "entity"))
    seen_in = F.when(F.col("level") > 0, F.col("around").cast("string")).otherwise(F.col("text_key"))
    mentions = each.select("entity", (F.col("level") > 0).alias("wide"), seen_in.alias("seen_in"), F.explode("terms").alias("term")).distinct()
    near = mentions.groupBy("entity", "wide", "term").agg(F.count(F.lit(1)).alias("n_seen")).where(F.col("n_seen") >= support).join(entity, "entity")
    # A term that is met in classes only so often can't reach the threshold, even if it never stands elsewhere.
    need = F.pow(F.col("n_entity") / n, F.lit(1 - disclosure))
    near = spool(near.where(~F.col("wide") | (F.col("n_seen") / (F.col("n_seen") + z * z) >= need)), "near")
    both = held.select(F.explode(entities).alias("entity"), "words").join(spool(near.select("entity").distinct(), "candidates"), "entity", "left_semi")
    both = both.select("entity", F.explode("words").alias("term")).groupBy("entity", "term").agg(F.count(F.lit(1)).alias("n_both"))
    joint = spool(both.join(near, ["entity", "term"]), "joint")
    wanted = spool(near.select("term").distinct(), "wanted")
    words = docs.where(F.col("text").isNotNull()).select(F.explode(_words(F.col("text").cast("string"))).alias("term"))
    counts = words.join(wanted, "term", "left_semi").groupBy("term").agg(F.count(F.lit(1)).alias("n_term"))
    given = F.when(F.col("wide"), _lower_limit(F.col("n_both") / F.col("n_term"), F.col("n_seen"), z)).otherwise(F.col("n_both") / F.col("n_term"))
    pmi = F.log(given * n / F.col("n_entity"))
    told = joint.join(counts, "term").where((pmi >= disclosure * F.log(n / F.col("n_entity"))) & (pmi > 0)).select("term").distinct()
    return spool(told, "told")


def _lower_limit(share: Column, trials: Column, z: float) -> Column:
    """Wilson's lower confidence limit of a share."""
    square = z * z / trials
    return (share + square / 2 - F.sqrt(square * (share * (1 - share) + square / 4))) / (1 + square)


def generalised(told: DataFrame, broader: DataFrame | None = None, steps: int = STEPS_UP) -> DataFrame:
    """term, general: the nearest term above it that discloses nothing, by a table (term, broader); empty where there is none.

    A term with several broader terms goes to the first in order of code points; terms above that disclose are climbed past.
    """
    if broader is None:
        return told.select("term", F.lit("").alias("general"))
    up = broader.groupBy(F.lower("term").alias("below")).agg(F.min("broader").alias("above"))
    bad = told.select(F.col("term").alias("bad"))
    at = told.select("term", F.col("term").alias("now"))
    for _ in range(steps):
        climbed = at.join(bad, F.lower("now") == F.col("bad"), "left").join(up, F.lower("now") == F.col("below"), "left")
        at = spool(climbed.select("term", F.when(F.col("bad").isNull(), F.col("now")).otherwise(F.coalesce("above", F.lit(""))).alias("now")), "climbed")
    last = at.join(bad, F.lower("now") == F.col("bad"), "left")
    return last.select("term", F.when(F.col("bad").isNull(), F.col("now")).otherwise("").alias("general"))


def told_texts(docs: DataFrame, told: DataFrame) -> DataFrame:
    """term_key (digest of the text) and told (the disclosing words it has, each with its general term) of all texts of the corpus that have any."""
    text = F.col("text").cast("string")
    words = docs.where(F.col("text").isNotNull()).select(F.md5(text.cast("binary")).alias("term_key"), F.explode(_words(text)).alias("term"))
    hits = words.join(told, "term").groupBy("term_key").agg(F.map_from_entries(F.collect_set(F.struct("term", "general"))).alias("told"))
    return spool(hits, "told_texts")


def term_spans(text: Column, spans: Column, told: Column) -> Column:
    """All places of the words ``told`` outside of spans: array<struct<start, end, general>>, in code points; only hits are gathered, so a text costs its length."""
    shared = F.array(F.struct(_masked(text, spans).alias("text"), told.alias("told")))

    def of_row(z):
        gaps = F.zip_with(F.split(z["text"], _TERM, -1), F.regexp_extract_all(z["text"], F.lit(_TERM), F.lit(0)), lambda g, h: F.struct(F.char_length(g).alias("gap"), h.alias("hit")))
        start = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<start:int,end:int,general:string>>").alias("out"))

        def step(acc, x):
            a = acc["at"] + x["gap"]
            b = a + F.char_length(x["hit"])
            general = z["told"][F.lower(x["hit"])]
            grown = F.concat(acc["out"], F.array(F.struct(a.alias("start"), b.alias("end"), general.alias("general"))))
            out = F.when(general.isNotNull(), grown).otherwise(acc["out"])
            return F.when(x["hit"].isNull(), acc).otherwise(F.struct(b.alias("at"), out.alias("out")))

        return F.aggregate(gaps, start, step, lambda acc: acc["out"])

    return F.when(told.isNotNull(), F.transform(shared, of_row)[0])


def disclosing_terms(docs: DataFrame, found: DataFrame, **options) -> DataFrame:
    """term_key and its term spans (array<struct<start, end, general>>), for texts that have any."""
    held = told_texts(docs, generalised(disclosing(docs, found, **options)))
    rows = docs.select(F.col("text").cast("string").alias("text")).withColumn("key", F.md5(F.col("text").cast("binary")))
    rows = rows.join(held, F.col("key") == F.col("term_key")).dropDuplicates(["term_key"])
    spans = F.transform(F.array(base_spans(F.col("text"))), lambda s: term_spans(F.col("text"), s, F.col("told")))[0]
    return spool(rows.select("term_key", spans.alias("terms")).where("size(terms) > 0"), "terms")


def _line(spans: Column) -> Column:
    return F.concat_ws(",", F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))))


def _all_spans(spans: Column, terms: Column) -> Column:
    extra = F.transform(terms, lambda t: F.struct(t["start"].alias("start"), F.lit(len(KINDS)).alias("rank"), t["end"].alias("end"), F.lit("term").alias("kind"), t["general"].alias("value")))
    return F.array_sort(F.concat(spans, F.coalesce(extra.cast(_SPAN), F.array().cast(_SPAN))))


def detect(docs: DataFrame, **options) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, n_term, base_sha256, spans of every row."""
    found = scanned(docs)
    terms = disclosing_terms(docs, found, **options)
    rows = found.join(terms, F.col("text_key") == F.col("term_key"), "left")
    counts = [_count_of(k).alias(f"n_{k}") for k in KINDS]
    return rows.select(
        "doc_id", *counts, _size("terms").alias("n_term"),
        F.sha2(_line(F.col("spans")).cast("binary"), 256).alias("base_sha256"), _line(_all_spans(F.col("spans"), F.col("terms"))).alias("spans"),
    )


def _count_of(kind: str) -> Column:
    return F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long")


def _size(name: str) -> Column:
    return F.when(F.col(name).isNull(), 0).otherwise(F.size(name)).cast("long")


def replaced(text: Column, spans: Column) -> Column:
    """The text with the union of its spans replaced by the kinds' names, terms by their general terms."""
    start = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))

    def step(acc, s):
        fresh = s["start"] >= acc["at"]
        before = F.substring(text, acc["at"] + 1, s["start"] - acc["at"])
        name = F.concat(F.lit("["), F.upper(s["kind"]), F.lit("]"))
        put = F.when((s["kind"] == "term") & (s["value"] != ""), s["value"]).otherwise(name)
        out = F.when(fresh, F.concat(acc["out"], before, put)).otherwise(acc["out"])
        return F.struct(F.greatest(acc["at"], s["end"]).alias("at"), out.alias("out"))

    end = F.char_length(text)
    return F.aggregate(spans, start, step, lambda acc: F.concat(acc["out"], F.substring(text, acc["at"] + 1, end - acc["at"])))


def sanitise(docs: DataFrame, broader: DataFrame | None = None, **options) -> DataFrame:
    """``docs`` with personal data and disclosing terms replaced; n_chars, where present, follows the text.

    ``broader`` (term, broader) generalises disclosing terms; those without a harmless broader term become [TERM].
    """
    told = told_texts(docs, generalised(disclosing(docs, scanned(docs), **options), broader)).select(F.col("term_key").alias("pii_term_key"), F.col("told").alias("pii_told"))
    # The texts themselves move only when the table of texts with disclosing words is too large to broadcast.
    text = F.col("text").cast("string")
    marked = docs.withColumn("pii_key", F.md5(text.cast("binary"))).join(told, F.col("pii_key") == F.col("pii_term_key"), "left")
    spans = F.transform(F.array(base_spans(F.coalesce(text, F.lit("")))), lambda s: _all_spans(s, term_spans(text, s, F.col("pii_told"))))[0]
    marked = marked.withColumn("pii_spans", spans)
    hit = F.size("pii_spans") > 0
    marked = marked.withColumn("pii_text", F.when(hit, replaced(text, F.col("pii_spans"))).otherwise(F.col("text")))
    new = {"text": F.col("pii_text")}
    if "n_chars" in docs.columns:
        new["n_chars"] = F.when(hit, F.char_length("pii_text")).otherwise(F.col("n_chars")).cast(docs.schema["n_chars"].dataType)
    return marked.select(*[new[c].alias(c) if c in new else F.col(c) for c in docs.columns])
