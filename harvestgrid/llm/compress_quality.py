"""Quality by compression: which dictionary makes a text smaller?

Two Zstandard dictionaries are trained, one on good and one on bad labelled
texts. A text is cut to blocks (so that the dictionary, not the text's own past, does
the work in all of it) and every block is compressed with both. From the two total sizes
come the normalised difference (bad - good) / (bad + good) and both ratios to the
text's size; a logistic curve fitted on other labelled texts turns them into the
probability of label 1.

Learning uses a bounded sample of labelled rows outside the held-out fold. Only
the text is an input of a score.

Defined results: null and empty texts are scored like any other, as an empty block;
rows with null id are scored (held_out null); labels other than 0 and 1 and
labels without a document teach nothing. Without both labels the score is the share of
label 1 among what was learned (0.5 if nothing).
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fold, slices, uniform

#: Labelled documents per class to learn from (about; a documented bound), bytes of a block, level, bytes of a dictionary.
SAMPLE, BLOCK, LEVEL, DICTIONARY = 1500, 512, 3, 112_640
#: Bytes of text per class that a dictionary is trained on at most (a documented bound, like the sample; whole texts, the first one always).
TRAIN_BYTES = 16 << 20


def blocks(text: bytes, size: int = BLOCK) -> list[bytes]:
    return [text[a : a + size] for a in range(0, len(text), size)] or [b""]


def build_dictionary(texts: list[bytes]) -> bytes:
    """Trained content; where there is too little to train on, the texts themselves."""
    parts = [b for t in texts for b in blocks(t) if b]
    try:
        return zstandard.train_dictionary(max(1024, min(DICTIONARY, sum(map(len, parts)) // 4)), parts).as_bytes()
    except zstandard.ZstdError:
        return b"".join(parts)[-DICTIONARY:] or b" " * 8


class Measure:
    """Compressed sizes under both dictionaries."""

    def __init__(self, good: bytes, bad: bytes):
        self._packers = []
        for content in (good, bad):
            d = zstandard.ZstdCompressionDict(content)
            d.precompute_compress(level=LEVEL)
            self._packers.append(zstandard.ZstdCompressor(level=LEVEL, dict_data=d, write_content_size=False, write_dict_id=False))

    def features(self, text: bytes) -> tuple[float, float, float]:
        parts = blocks(text)
        good, bad = (sum(len(p.compress(b)) for b in parts) for p in self._packers)
        size = max(1, len(text))
        return (bad - good) / (bad + good), min(good / size, 4.0), min(bad / size, 4.0)


@dataclass
class QualityModel:
    good: bytes = b""
    bad: bytes = b""
    centre: np.ndarray | None = None
    spread: np.ndarray | None = None
    weights: np.ndarray | None = None
    prior: float = 0.5

    def _design(self, x: np.ndarray) -> np.ndarray:
        z = np.clip((x - self.centre) / self.spread, -5, 5)
        return np.concatenate([np.ones((len(z), 1)), z, z**2], axis=1)

    def score(self, texts: list[bytes], measure: Measure | None = None) -> np.ndarray:
        if self.weights is None:
            return np.full(len(texts), self.prior)
        measure = measure or Measure(self.good, self.bad)
        x = np.array([measure.features(t) for t in texts]).reshape(-1, 3)
        return 1 / (1 + np.exp(-np.clip(self._design(x) @ self.weights, -30, 30)))


def train(texts: list[tuple[bytes, int]], share: dict[int, float] | None = None, ridge: float = 1.0, train_bytes: int = TRAIN_BYTES) -> QualityModel:
    """``texts`` in any fixed order; two of three build the dictionaries, the third calibrates. ``share``: each label's share of all labelled rows."""
    by = {q: [t for t, label in texts if label == q] for q in (0, 1)}
    total = len(by[0]) + len(by[1])
    share = share or {q: len(by[q]) / max(1, total) for q in by}
    if not by[0] or not by[1]:
        return QualityModel(prior=len(by[1]) / total if total else 0.5)
    learn, calibrate = {}, {}
    for q, rows in by.items():
        learn[q] = [t for k, t in enumerate(rows) if k % 3 != 2]
        calibrate[q] = [t for k, t in enumerate(rows) if k % 3 == 2] or rows
        room, kept = train_bytes, []
        for t in learn[q]:
            room -= len(t)
            if room < 0 and kept:
                break
            kept.append(t)
        learn[q] = kept
    model = QualityModel(build_dictionary(learn[1]), build_dictionary(learn[0]))
    measure = Measure(model.good, model.bad)
    x = np.array([measure.features(t) for q in (0, 1) for t in calibrate[q]])
    y = np.array([q for q in (0, 1) for _ in calibrate[q]], dtype=float)
    model.centre, model.spread = x.mean(axis=0), x.std(axis=0) + 1e-9
    # Each label weighs as much as it does among all labelled rows, so that scores are probabilities.
    row = np.where(y == 1, share[1] / len(calibrate[1]), share[0] / len(calibrate[0])) * len(y)
    design = model._design(x)
    w = np.zeros(design.shape[1])
    for _ in range(40):
        p = 1 / (1 + np.exp(-np.clip(design @ w, -30, 30)))
        slope = design.T @ (row * (y - p)) - ridge * w
        curve = (design * (row * p * (1 - p))[:, None]).T @ design + ridge * np.eye(len(w))
        step = np.linalg.solve(curve, slope)
        w += step * min(1.0, 4 / max(1e-9, np.abs(step).max()))
    model.weights = w
    return model


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", sample: int = SAMPLE, train_bytes: int = TRAIN_BYTES) -> QualityModel:
    """Learn from about ``sample`` labelled documents per class outside the held-out fold, dictionaries from ``train_bytes`` of their text at most.

    Labelled rows whose text is null are no examples; they count in each label's share.
    """
    known = labels.where(F.col(label).isin(0, 1) & (fold(F.col("doc_id"), 3) != 1)).select(F.col("doc_id").alias("of"), F.col(label).cast("int").alias("label"))
    per = {r.label: r.n for r in known.groupBy("label").agg(F.count(F.lit(1)).alias("n")).collect()}
    total = max(1, sum(per.values()))
    chance = {q: min(1.0, sample / max(1, per.get(q, 0))) for q in (0, 1)}
    key = uniform(F.col("of"), salt="quality")
    picked = known.where(key < F.when(F.col("label") == 1, chance[1]).otherwise(chance[0])).dropDuplicates(["of", "label"])
    # The sample is bounded by the parameter, so it may be broadcast.
    rows = docs.where(F.col("text").isNotNull()).join(F.broadcast(picked), F.col("doc_id") == F.col("of"))
    got = sorted({(r.key, r.of, r.text, r.label) for r in rows.select(key.alias("key"), "of", "text", "label").collect()})
    return train([(t.encode(), q) for _, _, t, q in got], {q: per.get(q, 0) / total for q in (0, 1)}, train_bytes=train_bytes)


def _score_batches(shared):
    def run(batches):
        model = shared.value
        measure = Measure(model.good, model.bad) if model.weights is not None else None
        for batch in slices(batches, 512):
            score = model.score([t or b"" for t in batch.column(1).to_pylist()], measure)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(score)], names=["doc_id", "score"])

    return run


def score(docs: DataFrame, model: QualityModel) -> DataFrame:
    """doc_id, score (probability of label 1), predicted of every row's whole text."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    picked = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("text"))
    found = picked.mapInArrow(_score_batches(shared), "doc_id long, score double")
    return found.withColumn("predicted", (F.col("score") >= 0.5).cast("int"))
