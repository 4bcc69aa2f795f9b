"""Mixing sources to target weights by entropy balancing.

Every document i gets a rate r_i, the number of times the mix takes it. Among all
rates from 0 to ``most`` that give each source its target number of words, those are wanted that stray least from 1 in
relative entropy (weighed by words), while the mix keeps, as nearly as the
targets allow, the corpus' share of words in every language and its mean length of documents. The
solution is an exponential tilt,

    r_i = min(most, exp(theta_source + beta_language + nu z_i)),     z_i: standardised log length,

whose parameters minimise the convex dual: the sum over documents of size * phi(theta + beta + nu z) (phi' = the rate), less
parameters times targets, plus ``ridge`` / 2 * words * (beta^2 + nu^2), which lets languages and length give way where
they contradict the sources. Sources are met exactly.

Newton iterations are distributed: each makes one pass over the documents' sizes (never the texts) for the
gradient and the Hessian, summed per source and language. A source's own curvature is
a number, so its parameter is eliminated in its row, and only the system of languages and length,
a few numbers square, is solved on the driver.

Rates become copies: every document is taken floor(r_i) times; the fractional parts
are settled by a reproducible random key per document, lowest key / fraction first, while the
source's words stay within its target. The last one taken is found in two steps (sums per bin, then exact order
within the one bin that holds it), so no task gets a whole source. Then single moves (one copy more of one
document, one less of another, or both) bring each source closer to its target until none does or ``rounds`` are done;
the best move is found on the distinct sizes of a source.

Targets: sources ordered by code point, null last, weigh 1, 2, 3, repeating, and
share all words; no target exceeds ``most`` times its source's words, the
excess goes to the others by weight until none is above.

Defined results: null and empty texts have size 0 and never count towards a
target; they follow the same rule (0 words taken). A null source is a source of its own, a null language a
language of its own; a table without the column ``lang``, or with more than ``most_languages`` of them, is
balanced on sources and length only. Null ids and repeated rows are rows like
any other, but equal (id, text size) rows of a source share one key and are taken together, which can keep a source from
coming closer to its target. An empty table gives an empty result.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import spool, uniform, word_count

#: Fixed weights of the contract, by rank of the source.
CYCLE = (1.0, 2.0, 3.0)
#: Give of languages and length against the sources; Newton steps; moves per source; languages that are balanced.
RIDGE, STEPS, ROUNDS, MOST_LANGUAGES = 0.05, 40, 6, 256
#: Newton ends when no shared parameter moves by more and no source is off its target by a larger share; steps shrink quadratically.
TOLERANCE = 1e-6
#: Key over fraction stays below this; documents with no fraction have it.
_FAR = 8.0


class Tilt:
    """Languages in order, mean and spread of log length, and the parameters that all documents share."""

    def __init__(self, languages: list[str | None], mean: float, spread: float):
        self.languages, self.mean, self.spread = languages, mean, spread
        self.beta, self.nu = [0.0] * len(languages), 0.0

    def language(self, lang: Column) -> Column:
        names = F.array(*[F.lit("" if x is None else "=" + x) for x in self.languages])
        return (F.array_position(names, F.coalesce(F.concat(F.lit("="), lang), F.lit(""))) - 1).cast("int")

    def length(self, size: Column) -> Column:
        return (F.log1p(size.cast("double")) - F.lit(self.mean)) / F.lit(self.spread)

    def exponent(self, theta: Column, language: Column, size: Column) -> Column:
        shift = F.element_at(F.array(*[F.lit(b) for b in self.beta]), language + 1)
        return theta + shift + F.lit(self.nu) * self.length(size)


def _columns(docs: DataFrame) -> DataFrame:
    """doc_id, source, lang, size, key of every row."""
    lang = F.col("lang").cast("string") if "lang" in docs.columns else F.lit(None).cast("string")
    picked = docs.select("doc_id", "source", lang.alias("lang"), word_count(F.col("text")).alias("size"))
    return picked.withColumn("key", uniform(F.col("doc_id"), F.col("size"), salt="mix"))


def sized(docs: DataFrame) -> DataFrame:
    """doc_id, source, lang, size, key of every row, written once: the only pass over the texts."""
    return spool(_columns(docs), "sized")


def targets(sizes: DataFrame, cycle: tuple[float, ...] = CYCLE, most: float = 3.0) -> DataFrame:
    """source, source_size, weight, target: one row per source.

    The resharing ends where every source that isn't capped holds level *
    weight words. Sources are capped in order of cap / weight, so the level follows
    from running sums over the sources in that order.
    """
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    ranked = per.withColumn("place", F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())))
    weight = F.element_at(F.array(*[F.lit(c) for c in cycle]), ((F.col("place") - 1) % len(cycle) + 1).cast("int"))
    capped = ranked.withColumn("weight", weight).withColumn("cap", most * F.col("source_size"))
    order = Window.orderBy(F.col("cap") / F.col("weight"), "place")
    before, all_rows = order.rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy()
    level = (F.sum("source_size").over(all_rows) - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / (
        F.sum("weight").over(all_rows) - F.coalesce(F.sum("weight").over(before), F.lit(0.0))
    )
    stepped = capped.withColumn("level", level).withColumn("open", F.col("level") * F.col("weight") < F.col("cap"))
    # The level of the first source that stays below its cap holds for all that follow.
    final = F.min(F.when(F.col("open"), F.struct(F.col("cap") / F.col("weight"), "place", "level"))).over(all_rows)
    target = F.when(final.isNull(), F.col("cap")).otherwise(F.least("cap", final["level"] * F.col("weight")))
    return stepped.select("source", "source_size", "weight", target.alias("target"))


def _side(per_source: DataFrame, tag: str, small: int) -> DataFrame:
    """A table of one row per source: broadcast behind a check of its count, else joined with splitting of hot sources."""
    written = spool(per_source, tag)
    return F.broadcast(written) if written.count() <= small else written


def _of(rows: DataFrame, per_source: DataFrame) -> DataFrame:
    """Rows with the columns of their source's row, which names the source ``of``."""
    return rows.join(per_source, F.col("source").eqNullSafe(F.col("of")))


def solve(a: list[list[float]], b: list[float]) -> list[float]:
    """x of a x = b for a symmetric positive definite system, by elimination."""
    n = len(b)
    rows = [list(r) + [v] for r, v in zip(a, b)]
    for p in range(n):
        best = max(range(p, n), key=lambda k: abs(rows[k][p]))
        rows[p], rows[best] = rows[best], rows[p]
        for q in range(p + 1, n):
            f = rows[q][p] / rows[p][p]
            rows[q] = [x - f * y for x, y in zip(rows[q], rows[p])]
    x = [0.0] * n
    for p in range(n - 1, -1, -1):
        x[p] = (rows[p][n] - sum(rows[p][c] * x[c] for c in range(p + 1, n))) / rows[p][p]
    return x


def balanced(sizes: DataFrame, goal: DataFrame, most: float = 3.0, ridge: float = RIDGE, steps: int = STEPS, small_sources: int = 2000, most_languages: int = MOST_LANGUAGES) -> tuple[Tilt, DataFrame]:
    """The tilt, and of, source_size, target, theta of every source (see module text)."""
    by_lang = sizes.groupBy("lang").agg(F.sum("size").alias("words")).limit(most_languages + 1).collect()
    words = {r.lang: float(r.words) for r in by_lang} if len(by_lang) <= most_languages else {}
    log = F.log1p(F.col("size").cast("double"))
    total, mean, square = sizes.agg(F.sum("size"), F.sum(F.col("size") * log) / F.sum("size"), F.sum(F.col("size") * log * log) / F.sum("size")).first() if words or by_lang else (0, 0.0, 0.0)
    total, mean = float(total or 0), round(mean or 0.0, 9)
    languages = sorted(words, key=lambda x: (x is None, x or "")) if len(words) > 1 else []
    tilt = Tilt(languages or [None], mean, round(math.sqrt(max((square or 0.0) - mean * mean, 1e-6)), 9))
    coupled = len(languages)
    place = tilt.language(F.col("lang")) if coupled else F.lit(0)
    rows = sizes.where("size > 0").select("source", place.alias("language"), "size")
    state = goal.select(F.col("source").alias("of"), "source_size", "target", F.when(F.col("target") > 0, F.log(F.col("target") / F.col("source_size"))).otherwise(0.0).alias("theta"))
    state = _side(state, "state", small_sources)
    planned, sources = goal.agg(F.sum("target"), F.count(F.lit(1))).first()
    planned, few = float(planned or 0.0), sources <= small_sources
    # Words that each language has in the mix if it keeps its share.
    want = [words[x] / total * planned for x in languages] if total else []
    width = coupled + 1  # languages, then length
    held = ridge * max(total, 1.0)
    for _ in range(steps if total else 0):
        e = F.exp(F.least(F.lit(30.0), tilt.exponent(F.col("theta"), F.col("language"), F.col("size"))))
        z, size = tilt.length(F.col("size")), F.col("size").cast("double")
        cells = _of(rows, state).select("of", "language", size.alias("s"), z.alias("z"), F.least(F.lit(most), e).alias("r"), F.when(e < most, e).otherwise(0.0).alias("o"))
        sums = {"a0": "s * r", "a1": "s * r * z", "o0": "s * o", "o1": "s * o * z", "o2": "s * o * z * z"}
        cells = cells.groupBy("of", "language").agg(*[F.sum(F.expr(x)).alias(n) for n, x in sums.items()])
        per = cells.groupBy(F.col("of").alias("named")).agg(*[F.sum(n).alias(n) for n in sums], F.collect_list(F.struct(F.col("language").alias("i"), F.col("o0").alias("h"), "a0", "o1")).alias("cells"))
        # A source without words has no cells.
        per = state.join(per, F.col("of").eqNullSafe(F.col("named")), "left").drop("named").fillna(0.0, list(sums)).withColumn("cells", F.coalesce("cells", F.array().cast(per.schema["cells"].dataType))).withColumn("g", F.col("a0") - F.col("target")).withColumn("own", F.greatest(F.col("o0"), 1e-6 * F.col("source_size"), F.lit(1e-6)))
        per = spool(per, "newton")
        # Gradient and Hessian of languages and length, after the sources are eliminated; one row per pair of parameters.
        entry = F.array(F.struct(F.lit(coupled).alias("i"), F.col("o1").alias("h")))
        if coupled:
            entry = F.concat(F.transform("cells", lambda c: F.struct(c["i"].alias("i"), c["h"].alias("h"))), entry)
        each = per.select("g", "own", entry.alias("e")).select("g", "own", "e", F.inline("e"))
        pairs = each.select("i", "h", "own", F.inline(F.transform("e", lambda c: F.struct(c["i"].alias("j"), c["h"].alias("k"))))).groupBy("i", "j").agg(F.sum(F.col("h") * F.col("k") / F.col("own")).alias("x"))
        sides = each.groupBy("i").agg(F.sum(F.col("h") * F.col("g") / F.col("own")).alias("x")).select("i", F.lit(-1).alias("j"), "x")
        plain = per.select(F.inline("cells")).groupBy("i").agg(F.sum("a0").alias("a"), F.sum("h").alias("h"), F.sum("o1").alias("o")).select("i", F.inline(F.array(*[F.struct(F.lit(c).alias("j"), F.col(n).alias("x")) for c, n in ((-2, "a"), (-3, "h"), (-4, "o"))])))
        whole = per.agg(F.sum("a1").alias("a"), F.sum("o2").alias("h"), F.max(F.abs("g") / F.greatest("target", F.lit(1.0))).alias("o")).select(F.lit(-1).alias("i"), F.inline(F.array(*[F.struct(F.lit(c).alias("j"), F.col(n).alias("x")) for c, n in ((-2, "a"), (-3, "h"), (-4, "o"))])))
        got = {(r.i, r.j): r.x or 0.0 for r in pairs.unionByName(sides).unionByName(plain).unionByName(whole).collect()}
        param = [*tilt.beta[:coupled], tilt.nu]
        grad = [got.get((i, -2), 0.0) - want[i] for i in range(coupled)] + [got.get((-1, -2), 0.0)]
        grad = [g + held * p for g, p in zip(grad, param)]
        hess = [[0.0] * width for _ in range(width)]
        for i in range(coupled):
            hess[i][i] = got.get((i, -3), 0.0)
            hess[i][coupled] = hess[coupled][i] = got.get((i, -4), 0.0)
        hess[coupled][coupled] = got.get((-1, -3), 0.0)
        system = [[hess[i][j] + (held if i == j else 0.0) - got.get((i, j), 0.0) for j in range(width)] for i in range(width)]
        step = solve(system, [got.get((i, -1), 0.0) - grad[i] for i in range(width)])
        longest = max(abs(x) for x in step)
        step = [x / max(1.0, longest) for x in step]
        moved = F.col("o1") * F.lit(step[coupled])
        if coupled:
            moved = moved + F.aggregate("cells", F.lit(0.0), lambda a, c: a + c["h"] * F.element_at(F.array(*[F.lit(x) for x in step[:coupled]]), c["i"] + 1))
        theta = F.col("theta") - F.greatest(F.lit(-2.0), F.least(F.lit(2.0), (F.col("g") + moved) / F.col("own")))
        done = longest < TOLERANCE and got.get((-1, -4), 0.0) < TOLERANCE
        if coupled:
            tilt.beta = [round(b + x, 12) for b, x in zip(tilt.beta, step)]
        tilt.nu = round(tilt.nu + step[coupled], 12)
        state = per.select("of", "source_size", "target", theta.alias("theta"))
        state = F.broadcast(state) if few else state
        if done:
            break
    tilt.beta, tilt.nu = [round(b, 9) for b in tilt.beta], round(tilt.nu, 9)
    return tilt, state.withColumn("theta", F.round("theta", 9))


def _rated(rows: DataFrame, tilt: Tilt, most: float) -> DataFrame:
    """+ rate, whole, rank (key over fraction) of rows joined with their source."""
    place = tilt.language(F.col("lang")) if len(tilt.languages) > 1 else F.lit(0)
    rate = F.least(F.lit(float(most)), F.exp(tilt.exponent(F.col("theta"), place, F.col("size"))))
    rows = rows.withColumn("rate", F.when(F.col("target") > 0, F.round(rate, 9)).otherwise(0.0))
    rows = rows.withColumn("whole", F.floor(F.col("rate") + 1e-9).cast("int"))
    part = F.col("rate") - F.col("whole")
    return rows.withColumn("rank", F.when(part > 1e-9, F.least(F.lit(_FAR), F.col("key") / part)).otherwise(_FAR))


def _bin(bins: int) -> Column:
    return F.floor(F.col("rank") * (bins / _FAR)).cast("int")


def _copies(bins: int, most: float) -> Column:
    """Copies of a row joined with its source's rule."""
    upto = F.coalesce(F.struct("rank", "doc_id") <= F.col("cut"), F.lit(False))
    extra = (_bin(bins) < F.col("edge_bin")) | ((_bin(bins) == F.col("edge_bin")) & upto)
    named = lambda m: F.when((m["key"] == F.col("key")) & m["doc_id"].eqNullSafe(F.col("doc_id")) & (m["size"] == F.col("size")), m["by"]).otherwise(0)
    moved = F.aggregate("moves", F.lit(0), lambda a, m: a + named(m))
    return F.greatest(F.lit(0), F.least(F.lit(int(most)), F.col("whole") + extra.cast("int") + moved))


def rules(docs: DataFrame, cycle: tuple[float, ...] = CYCLE, most: float = 3.0, bins: int = 32768, small_sources: int = 2000, rounds: int = ROUNDS, **options) -> tuple[Tilt, DataFrame]:
    """The tilt, and one row per source with all that decides a document's copies."""
    sizes = sized(docs)
    goal = spool(targets(sizes, cycle, most), "goal")
    tilt, state = balanced(sizes, goal, most, small_sources=small_sources, **options)
    state = _side(state, "tilted", small_sources)
    rows = _rated(_of(sizes, state), tilt, most)

    # Words left for fractions; the bin in which each source passes them, and the words below that bin.
    left = rows.groupBy(F.col("of").alias("left_of")).agg((F.first("target") - F.sum(F.col("whole") * F.col("size"))).alias("rest"))
    sums = rows.where(F.col("rank") < _FAR).groupBy("source", _bin(bins).alias("bin")).agg(F.sum("size").alias("words"))
    run = Window.partitionBy("source").orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)
    passed = sums.withColumn("below", F.coalesce(F.sum("words").over(run), F.lit(0))).join(spool(left, "left"), F.col("source").eqNullSafe(F.col("left_of"))).where("below + words > rest")
    edge = passed.groupBy(F.col("left_of").alias("edge_of")).agg(F.min(F.struct("bin", "below", "rest")).alias("e"))
    state = state.join(spool(edge, "edge"), F.col("of").eqNullSafe(F.col("edge_of")), "left").drop("edge_of")
    state = _side(state.select(*[c for c in state.columns if c != "e"], F.coalesce("e.bin", F.lit(bins - 1)).alias("edge_bin"), F.coalesce("e.below", F.lit(0)).alias("below"), F.coalesce("e.rest", F.lit(0.0)).alias("rest")), "edged", small_sources)

    # Within that bin, the last one that still fits.
    inside = _rated(_of(sizes, state), tilt, most).where((F.col("rank") < _FAR) & (_bin(bins) == F.col("edge_bin")))
    upto = F.sum("size").over(Window.partitionBy("source").orderBy("rank", "doc_id").rangeBetween(Window.unboundedPreceding, 0))
    fits = inside.withColumn("upto", upto).where("below + upto <= rest").groupBy(F.col("of").alias("cut_of")).agg(F.max(F.struct("rank", "doc_id")).alias("cut"))
    moves = F.array().cast("array<struct<key:double,doc_id:" + sizes.schema["doc_id"].dataType.simpleString() + ",size:long,by:int>>")
    state = state.join(spool(fits, "fits"), F.col("of").eqNullSafe(F.col("cut_of")), "left").drop("cut_of", "below", "rest").withColumn("moves", moves)
    state = _side(state, "rule", small_sources)
    for _ in range(rounds):
        state, moved = _moved(sizes, state, tilt, most, bins, small_sources)
        if not moved:
            break
    return tilt, state


def _moved(sizes: DataFrame, state: DataFrame, tilt: Tilt, most: float, bins: int, small_sources: int) -> tuple[DataFrame, bool]:
    """Rules with the move that brings each source closest to its target, and whether there was any."""
    rows = _rated(_of(sizes, state), tilt, most).withColumn("copies", _copies(bins, most)).where("size > 0")
    who = F.struct("key", "doc_id")
    by_size = rows.groupBy("of", "size").agg(
        F.sum(F.col("copies") * F.col("size")).alias("taken"), F.first("target").alias("target"),
        F.min(F.when(F.col("copies") < int(most), who)).alias("more"), F.min(F.when(F.col("copies") > 0, who)).alias("less"),
    )
    by_size = spool(by_size, "by_size")
    gap = by_size.groupBy(F.col("of").alias("gap_of")).agg((F.first("target") - F.sum("taken")).alias("gap")).where(F.abs("gap") > 0.5)
    gap = _side(gap, "gap", small_sources)
    near = by_size.join(gap, F.col("of").eqNullSafe(F.col("gap_of")))
    # Giving up a document of size a (0: none) asks for one of size gap + a (0: none); the nearest sizes on both sides are candidates.
    base = near.groupBy("of", "gap").agg(F.lit(0).cast("long").alias("size")).withColumn("who", F.lit(None).cast(by_size.schema["more"].dataType))
    ask = near.where("less is not null").select("of", "gap", "size", F.col("less").alias("who")).unionByName(base)
    have = near.where("more is not null").select("of", "gap", "size", F.col("more").alias("who")).unionByName(base)
    both = ask.select("of", "gap", (F.col("size") + F.col("gap")).alias("at"), F.struct("size", "who").alias("a"), F.lit(None).cast("struct<size:bigint,who:" + by_size.schema["more"].dataType.simpleString() + ">").alias("b"))
    both = both.unionByName(have.select("of", "gap", F.col("size").cast("double").alias("at"), F.lit(None).cast(both.schema["a"].dataType).alias("a"), F.struct("size", "who").alias("b")))
    line = Window.partitionBy("of").orderBy("at", F.col("a").isNotNull())
    back = F.last("b", ignorenulls=True).over(line.rowsBetween(Window.unboundedPreceding, -1))
    ahead = F.first("b", ignorenulls=True).over(line.rowsBetween(1, Window.unboundedFollowing))
    tried = both.withColumns({"low": back, "high": ahead}).where("a is not null").select("of", "gap", "a", F.explode(F.array("low", "high")).alias("b")).where("b is not null")
    off = F.abs(F.col("gap") - F.col("b.size") + F.col("a.size"))
    best = tried.where(off < F.abs("gap") - 1e-6).groupBy(F.col("of").alias("best_of")).agg(F.min_by(F.struct("a", "b"), F.struct(off, F.col("a.size") + F.col("b.size"), F.col("a.size"))).alias("m"))
    best = spool(best, "best")
    if not best.take(1):
        return state, False
    step = lambda s, by: F.struct(F.col(f"m.{s}.who.key").alias("key"), F.col(f"m.{s}.who.doc_id").alias("doc_id"), F.col(f"m.{s}.size").alias("size"), F.lit(by).alias("by"))
    new = F.filter(F.array(step("a", -1), step("b", 1)), lambda s: s["size"] > 0)
    grown = state.join(best, F.col("of").eqNullSafe(F.col("best_of")), "left")
    grown = grown.withColumn("moves", F.when(F.col("m").isNull(), F.col("moves")).otherwise(F.concat("moves", new))).drop("best_of", "m")
    return _side(grown, "moved", small_sources), True


def mixed(docs: DataFrame, most: float = 3.0, bins: int = 32768, **options) -> DataFrame:
    """doc_id, source, size, source_size, target, rate, copies of every row."""
    tilt, state = rules(docs, most=most, bins=bins, **options)
    rows = _rated(_of(_columns(docs), state), tilt, most)
    return rows.select("doc_id", "source", "size", "source_size", "target", "rate", _copies(bins, most).alias("copies"))


def take_copies(docs: DataFrame, most: float = 3.0, bins: int = 32768, **options) -> DataFrame:
    """``docs`` with each row repeated as often as the mix takes it; rows not taken go. The texts are not shuffled."""
    tilt, state = rules(docs, most=most, bins=bins, **options)
    lang = [F.col("lang").cast("string").alias("lang")] if "lang" in docs.columns else [F.lit(None).cast("string").alias("lang")]
    packed = docs.select("doc_id", "source", *lang, word_count(F.col("text")).alias("size"), F.struct(*docs.columns).alias("row"))
    packed = packed.withColumn("key", uniform(F.col("doc_id"), F.col("size"), salt="mix"))
    rows = _rated(_of(packed, state), tilt, most).withColumn("copies", _copies(bins, most)).where("copies > 0")
    return rows.select("row", F.explode(F.sequence(F.lit(1), "copies")).alias("copy")).select("row.*")
