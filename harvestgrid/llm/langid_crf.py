"""Language of words and documents by a linear-chain conditional random field.

Words (runs of letters, lower case) are the positions, languages the labels. A
word's emission score sums learned weights of its character n-grams, of its affixes
(n-grams that touch a word boundary) and, if training met it often enough, of its
own lexicon entry; transition weights between neighbouring labels are learned
too. Training maximises the conditional likelihood on monolingual and on spliced
(code-switched) word sequences from a bounded sample of labelled documents. Labels
come by forward-backward: every word of a text gets posterior probabilities, over
chains of up to ``CHAIN`` words, many chains at a time in numpy. A document's
language is the one with the largest mean posterior; that mean is its score.

Defined results: null texts and texts without a letter are ``und`` with score 0.
Rows whose lang, text or id is null teach nothing. Repeated rows get equal
results. If no row can teach, every text is ``und``.
"""

from __future__ import annotations

import itertools
import uuid

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fold, slices, uniform, worker_table

_LETTERS = regex.compile(r"\p{L}+")
UNKNOWN = "und"
#: Documents per language to learn from (about; a documented bound), hash buckets of n-grams, lexicon entries, words in a chain.
SAMPLE, BUCKETS, LEXICON, CHAIN = 300, 1 << 17, 40_000, 128
#: Words of all training texts together at most, and emission rows a worker keeps.
TRAIN_WORDS, WORDS_KEPT = 400_000, 300_000
_A, _B, _C = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(40)


def words_of(text: str | None) -> list[str]:
    return _LETTERS.findall(text.lower()) if text else []


def features(words: list[str], lexicon: dict[str, int]) -> tuple[np.ndarray, np.ndarray]:
    """(feature, word index) pairs: all 2- and 3-grams, 4- and 5-grams at the edges (affixes), lexicon entries."""
    flat = np.frombuffer("".join(f"\x02{w}\x03" for w in words).encode("utf-32-le"), dtype=np.uint32).astype(np.uint64)
    sizes = np.array([len(w) + 2 for w in words])
    owner = np.repeat(np.arange(len(words)), sizes)
    first = np.concatenate([[0], np.cumsum(sizes)[:-1]])
    place = np.arange(len(flat)) - np.repeat(first, sizes)
    left = np.repeat(sizes, sizes) - place
    ids, owners = [], []
    code = flat * _A
    for n in range(2, 6):
        code = code[:-1] * _B + flat[n - 1 :] * _A + np.uint64(n)
        inside = left[: len(code)] >= n
        if n > 3:
            inside &= (place[: len(code)] == 0) | (left[: len(code)] == n)
        at = np.nonzero(inside)[0]
        ids.append((code[at] * _B >> _C).astype(np.int64) % BUCKETS)
        owners.append(owner[at])
    known = [(BUCKETS + lexicon[w], k) for k, w in enumerate(words) if w in lexicon]
    if known:
        ids.append(np.array([k for k, _ in known]))
        owners.append(np.array([k for _, k in known]))
    return np.concatenate(ids), np.concatenate(owners)


def _emissions(words: list[str], lexicon: dict[str, int], weights: np.ndarray) -> np.ndarray:
    ids, owner = features(words, lexicon)
    scale = 1 / np.sqrt(np.maximum(1, np.bincount(owner, minlength=len(words))))
    return np.stack([np.bincount(owner, w[ids], minlength=len(words)) for w in weights.T], axis=1) * scale[:, None]


def forward_backward(scores: np.ndarray, valid: np.ndarray, trans: np.ndarray):
    """Posteriors (T, C, L) of C chains, given emission scores and a mask of the same T; and expected transitions (L, L)."""
    t, c, n = scores.shape
    e = np.exp(scores - scores.max(axis=2, keepdims=True))
    m = np.exp(trans - trans.max())
    alpha = np.empty_like(e)
    alpha[0] = e[0] / e[0].sum(axis=1, keepdims=True)
    for k in range(1, t):
        a = (alpha[k - 1] @ m) * e[k]
        alpha[k] = a / a.sum(axis=1, keepdims=True)
    beta = np.ones_like(e)
    pairs = np.zeros((n, n))
    for k in range(t - 2, -1, -1):
        after = e[k + 1] * beta[k + 1]
        b = after @ m.T
        live = valid[k + 1][:, None]
        beta[k] = np.where(live, b / b.sum(axis=1, keepdims=True), 1.0)
        norm = (alpha[k] * b).sum(axis=1, keepdims=True)
        pairs += m * ((alpha[k] / norm * live).T @ after)
    post = alpha * beta
    return post / post.sum(axis=2, keepdims=True), pairs


def _chains(index: np.ndarray, chain: int):
    """Flat word positions cut to chains: (T, C) of positions, and mask. ``index`` starts each document's words."""
    rows = []
    for a, b in zip(index, index[1:]):
        rows += [(s, min(b, s + chain)) for s in range(a, b, chain)]
    if not rows:
        return np.zeros((1, 0), int), np.zeros((1, 0), bool)
    start, end = np.array(rows).T
    at = start[None, :] + np.arange((end - start).max())[:, None]
    valid = at < end
    return np.where(valid, at, start[None, :]), valid


class LanguageModel:
    """Learned labels, lexicon and weights; labels the words of any text."""

    def __init__(self, labels: list[str], lexicon: dict[str, int], weights: np.ndarray, trans: np.ndarray):
        self.labels, self.lexicon, self.weights, self.trans = labels, lexicon, weights, trans

    def posteriors(self, documents: list[list[str]], kept: dict | None = None) -> list[np.ndarray]:
        """For each document its (words, labels) posteriors."""
        flat = list(itertools.chain.from_iterable(documents))
        index = np.concatenate([[0], np.cumsum([len(d) for d in documents])]).astype(int)
        if not flat or not self.labels:
            return [np.zeros((0, len(self.labels))) for _ in documents]
        kept = {} if kept is None else kept
        if len(kept) > WORDS_KEPT:
            kept.clear()
        rows = kept.setdefault("", (0, np.zeros((1024, len(self.labels)), dtype=np.float32)))
        fresh = list(dict.fromkeys(w for w in flat if w not in kept))
        if fresh:
            used, table = rows
            need = used + len(fresh)
            if need > len(table):
                table = np.concatenate([table, np.zeros((max(need, 2 * len(table)) - len(table), table.shape[1]), dtype=np.float32)])
            for at in range(0, len(fresh), 20_000):
                part = fresh[at : at + 20_000]
                table[used + at : used + at + len(part)] = _emissions(part, self.lexicon, self.weights)
            kept.update(zip(fresh, range(used, need)))
            kept[""] = rows = (need, table)
        scores = rows[1][np.fromiter(map(kept.__getitem__, flat), dtype=np.int64, count=len(flat))]
        at, valid = _chains(index, CHAIN)
        post, _ = forward_backward(scores[at].astype(float), valid, self.trans)
        out = np.empty((len(flat), len(self.labels)))
        out[at[valid]] = post[valid]
        return [out[a:b] for a, b in zip(index, index[1:])]

    def tag(self, text: str | None) -> list[tuple[str, str]]:
        """(word, label) of each word."""
        words = words_of(text)
        return [(w, self.labels[k]) for w, k in zip(words, self.posteriors([words])[0].argmax(axis=1))] if words else []


def train(texts: list[tuple[str, str]], rounds: int = 3, rate: float = 0.3, seed: int = 7, train_words: int = TRAIN_WORDS) -> LanguageModel:
    """Fit from (text, label) pairs by adaptive gradient steps on batches of chains."""
    labels = sorted({label for _, label in texts})
    docs = [(words_of(t), labels.index(label)) for t, label in texts]
    docs = [d for d in docs if d[0]]
    each = max(1, train_words // max(1, len(docs)))
    pieces = []
    for words, label in docs:  # evenly spread chains, so that long texts don't crowd out the others
        starts = range(0, len(words), 40)
        step = max(1, len(starts) * 40 // max(40, each))
        pieces += [(words[s : s + 40], label) for s in list(starts)[::step]]
    counts: dict[str, int] = {}
    for words, _ in pieces:
        for w in words:
            counts[w] = counts.get(w, 0) + 1
    frequent = sorted((w for w, n in counts.items() if n > 2), key=lambda w: (-counts[w], w))[:LEXICON]
    lexicon = {w: k for k, w in enumerate(frequent)}
    n = len(labels)
    weights, trans = np.zeros((BUCKETS + len(lexicon), n)), np.zeros((n, n))
    if not pieces or n < 2:
        return LanguageModel(labels, lexicon, weights.astype(np.float32), trans)
    grown, grown_t = np.full_like(weights, 1e-2), np.full_like(trans, 1e-2)
    rng = np.random.default_rng(seed)
    for _ in range(rounds):
        order = rng.permutation(len(pieces))
        chains = []
        for a, b in zip(order[::2], order[1::2]):  # half of the chains switch language inside
            (wa, la), (wb, lb) = pieces[a], pieces[b]
            if rng.random() < 0.5:
                ca, cb = rng.integers(0, len(wa) + 1), rng.integers(0, len(wb) + 1)
                chains.append((wa[:ca] + wb[cb:], [la] * ca + [lb] * (len(wb) - cb)))
                chains.append((wb[:cb] + wa[ca:], [lb] * cb + [la] * (len(wa) - ca)))
            else:
                chains += [(wa, [la] * len(wa)), (wb, [lb] * len(wb))]
        chains = [c for c in chains if c[0]] or [(w, [k] * len(w)) for w, k in pieces]
        for s in range(0, len(chains), 128):
            part = chains[s : s + 128]
            flat = [w for c, _ in part for w in c]
            gold = np.array([k for _, g in part for k in g])
            types = {w: k for k, w in enumerate(dict.fromkeys(flat))}
            use = np.array([types[w] for w in flat])
            ids, owner = features(list(types), lexicon)
            scale = 1 / np.sqrt(np.maximum(1, np.bincount(owner, minlength=len(types))))
            emit = np.stack([np.bincount(owner, weights[ids, k], minlength=len(types)) for k in range(n)], axis=1) * scale[:, None]
            at, valid = _chains(np.concatenate([[0], np.cumsum([len(c) for c, _ in part])]), CHAIN)
            post, pairs = forward_backward(emit[use][at], valid, trans)
            wrong = -post
            wrong[valid, gold[at[valid]]] += 1
            by_type = np.stack([np.bincount(use[at[valid]], wrong[valid][:, k], minlength=len(types)) for k in range(n)], axis=1) * scale[:, None]
            touched, back = np.unique(ids, return_inverse=True)
            grad = np.stack([np.bincount(back, by_type[owner, k], minlength=len(touched)) for k in range(n)], axis=1) / len(part)
            grad -= 1e-5 * weights[touched]
            grown[touched] += grad**2
            weights[touched] += rate * grad / np.sqrt(grown[touched])
            seen = np.zeros((n, n))
            both = valid[1:] & valid[:-1]
            np.add.at(seen, (gold[at[:-1][both]], gold[at[1:][both]]), 1)
            grad_t = (seen - pairs) / len(part)
            grown_t += grad_t**2
            trans += rate * grad_t / np.sqrt(grown_t)
    return LanguageModel(labels, lexicon, weights.astype(np.float32), trans)


def fit(docs: DataFrame, sample: int = SAMPLE, train_words: int = TRAIN_WORDS) -> LanguageModel:
    """Train on about ``sample`` documents per language, none of the held-out fold, and on about ``train_words`` of their words at most, evenly spread."""
    learn = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & (fold(F.col("doc_id"), 4) != 2))
    per = {r.lang: r.n for r in learn.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}
    chance = F.lit(0.0)
    for lang, n in per.items():
        chance = F.when(F.col("lang") == lang, F.lit(min(1.0, sample / n))).otherwise(chance)
    picked = learn.where(uniform(F.col("doc_id"), salt="langid") < chance).select("doc_id", "text", "lang")
    rows = sorted({(r.doc_id, r.text, r.lang) for r in picked.collect()})
    return train([(t, lang) for _, t, lang in rows], train_words=train_words)


def _predict_batches(shared, name: str):
    def run(batches):
        model = shared.value
        kept = worker_table(f"langid {name}", dict)

        def label(held):
            for post in model.posteriors([w for _, w in held], kept):
                if not len(post) or not model.labels:
                    yield UNKNOWN, 0.0
                else:
                    mean = post.mean(axis=0)
                    yield model.labels[int(mean.argmax())], float(min(1.0, mean.max()))

        def packed(held):
            got = list(label(held))
            ids, out = pa.array([i for i, _ in held], pa.int64()), (pa.array([x for x, _ in got], pa.string()), pa.array([x for _, x in got], pa.float64()))
            return pa.RecordBatch.from_arrays([ids, *out], names=["doc_id", "lang_pred", "score"])

        for batch in slices(batches, 256):
            held, size = [], 0
            for i, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                held.append((i, words_of(text)))
                size += len(held[-1][1])
                if size > 100_000:
                    yield packed(held)
                    held, size = [], 0
            if held:
                yield packed(held)

    return run


def predict(docs: DataFrame, model: LanguageModel) -> DataFrame:
    """doc_id, lang_pred, score of every row, from its text alone."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    picked = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return picked.mapInArrow(_predict_batches(shared, uuid.uuid4().hex), "doc_id long, lang_pred string, score double")


def _label_batches(shared, name: str, text_at: int, lang_at: int, least: float):
    inner = _predict_batches(shared, name)

    def run(batches):
        for batch in slices(batches, 256):
            ids = pa.array(range(batch.num_rows), pa.int64())
            parts = list(inner([pa.RecordBatch.from_arrays([ids, batch.column(text_at).cast(pa.string())], names=["doc_id", "text"])]))
            lang = pa.concat_arrays([p.column(1) for p in parts]) if parts else pa.array([], pa.string())
            score = pa.concat_arrays([p.column(2) for p in parts]) if parts else pa.array([], pa.float64())
            keep = pa.array([x != UNKNOWN and s >= least for x, s in zip(lang.to_pylist(), score.to_pylist())], pa.bool_())
            columns = [lang if k == lang_at else c for k, c in enumerate(batch.columns)]
            yield pa.RecordBatch.from_arrays(columns, names=batch.schema.names).filter(keep)

    return run


def keep_identified(docs: DataFrame, least: float = 0.3, sample: int = SAMPLE) -> DataFrame:
    """Rows whose text has a language (posterior mean of at least ``least``), with lang set to it; the columns of ``docs``."""
    model = fit(docs, sample)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    at = docs.columns.index
    return docs.mapInArrow(_label_batches(shared, uuid.uuid4().hex, at("text"), at("lang"), least), docs.schema)
