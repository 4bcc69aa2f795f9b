"""Byte-pair encoding and decoding with numpy merge rounds.

Texts are normalised (NFC, white space, lower case by character) and cut to
words; words not met before by this worker are encoded together: the symbols of
all of them stand in one flat array, each round looks up all adjacent pairs by
binary search over the sorted pair keys and merges, in every word, the pair of
lowest rank. Encoded words are kept in a bounded table per worker.

Defined results: null and empty texts have no tokens (digests of the empty
string). Literal special tokens in a text become their ids, as the tokenizers
library does by default. Other columns are ignored.
"""

from __future__ import annotations

import hashlib
import json
import unicodedata

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import slices, worker_table

#: White space of the tokenizer's pattern engine.
_SPACE = r"\t-\r \x85\xa0  -     　"
_WORDS = regex.compile(rf"'s|'t|'re|'ve|'m|'ll|'d|\p{{L}}+|\p{{N}}|[^{_SPACE}\p{{L}}\p{{N}}]+")
#: Steps of a vocabulary file that this module takes: normalisers, then cutters.
STEPS = [("NFC", None), ("Replace", r"\s+"), ("Lowercase", None)]
CUTS = [("Split", "Removed", True, None), ("ByteLevel", None, None, False)]
_NONE = np.iinfo(np.int64).max
#: Encoded words that a worker keeps at most; beyond it the table starts anew.
WORDS_KEPT = 300_000


def default_vocabulary() -> str:
    """The tokenizer file of the installed public package."""
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def byte_letters() -> list[str]:
    """The printable stand-in of each byte: itself where printable, else the next letter from U+0100."""
    kept = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = iter(range(256, 512))
    return [chr(b) if b in kept else chr(next(rest)) for b in range(256)]


def check_steps(spec: dict) -> None:
    """A file whose steps aren't those that this module takes is refused, not encoded wrongly."""
    normal = [(n["type"], n.get("pattern", {}).get("Regex")) for n in (spec["normalizer"] or {}).get("normalizers", [])]
    cuts = [(c["type"], c.get("behavior"), c.get("invert"), c.get("add_prefix_space")) for c in (spec["pre_tokenizer"] or {}).get("pretokenizers", [])]
    model = spec["model"]
    plain = not any(model.get(k) for k in ("dropout", "continuing_subword_prefix", "byte_fallback", "ignore_merges")) and not spec.get("decoder")
    special = all(not t["normalized"] and not any(t[k] for k in ("single_word", "lstrip", "rstrip")) for t in spec["added_tokens"])
    if normal != STEPS or cuts != CUTS or model["type"] != "BPE" or not plain or not special:
        raise ValueError("this vocabulary file has other steps than NFC, white space, lower case, word cutting and byte letters")


class WordBpe:
    """Encoder and decoder of one vocabulary file."""

    def __init__(self, definition: bytes):
        spec = json.loads(definition)
        check_steps(spec)
        vocab = dict(spec["model"]["vocab"])
        end = spec["model"].get("end_of_word_suffix") or ""
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.tokens = {i: t for t, i in vocab.items()} | {i: t for t, i in self.special.items()}
        self._cut = regex.compile("(" + "|".join(map(regex.escape, self.special)) + ")") if self.special else None
        letters = byte_letters()
        self._inner = np.array([vocab[c] for c in letters], dtype=np.int64)
        self._final = np.array([vocab[c + end] for c in letters], dtype=np.int64)
        self.size = max(vocab.values()) + 1
        pairs = [m if isinstance(m, list) else m.split(" ") for m in spec["model"]["merges"]]
        keys = np.array([vocab[a] * self.size + vocab[b] for a, b in pairs], dtype=np.int64)
        made = np.array([vocab[a + b] for a, b in pairs], dtype=np.int64)
        order = np.argsort(keys)
        self._keys, self._rank, self._made = keys[order], order, made[order]
        self.known: dict[str | int, bytes] = {}

    def encode_words(self, words: list[str]) -> list[np.ndarray]:
        """Ids of each word, by merge rounds over all words at once."""
        if not words:
            return []
        raw = [w.encode() for w in words]
        sizes = np.array([len(r) for r in raw])
        flat = np.frombuffer(b"".join(raw), dtype=np.uint8)
        owner = np.repeat(np.arange(len(raw)), sizes)
        symbols = self._inner[flat]
        ends = np.cumsum(sizes) - 1
        symbols[ends] = self._final[flat[ends]]
        out: list = [None] * len(words)
        while len(symbols):
            key = symbols[:-1] * self.size + symbols[1:]
            at = np.minimum(np.searchsorted(self._keys, key), len(self._keys) - 1)
            hit = (self._keys[at] == key) & (owner[:-1] == owner[1:])
            rank = np.full(len(symbols), _NONE)
            rank[:-1][hit] = self._rank[at[hit]]
            starts = np.nonzero(np.concatenate([[True], owner[1:] != owner[:-1]]))[0]
            best = np.minimum.reduceat(rank, starts)
            counts = np.diff(np.concatenate([starts, [len(symbols)]]))
            over = best == _NONE
            if over.any():  # finished words leave the array
                for s, n in zip(starts[over], counts[over]):
                    out[owner[s]] = symbols[s : s + n]
                stay = ~np.repeat(over, counts)
                symbols, owner, rank = symbols[stay], owner[stay], rank[stay]
                best, counts = best[~over], counts[~over]
                at = np.concatenate([at, [0]])[stay]
                if not len(symbols):
                    break
            else:
                at = np.concatenate([at, [0]])
            merge = np.nonzero(rank == np.repeat(best, counts))[0]
            # In a run of overlapping pairs every second one merges, from the left.
            gaps = np.concatenate([[True], np.diff(merge) > 1])
            first = np.maximum.accumulate(np.where(gaps, np.arange(len(merge)), 0))
            merge = merge[(np.arange(len(merge)) - first) % 2 == 0]
            symbols[merge] = self._made[at[merge]]
            left = np.ones(len(symbols), dtype=bool)
            left[merge + 1] = False
            symbols, owner = symbols[left], owner[left]
        return out

    def pieces(self, text: str | None) -> list[str | int]:
        """Words of a text in order; special tokens as their ids."""
        if not text:
            return []
        parts = self._cut.split(text) if self._cut is not None else [text]
        found: list[str | int] = []
        for part in parts:
            if part in self.special:
                found.append(self.special[part])
            elif part:
                # U+03A3 first: lower-casing by character knows no final sigma.
                found += _WORDS.findall(unicodedata.normalize("NFC", part).replace("Σ", "σ").lower())
        return found

    def learn(self, pieces: set[str | int]) -> None:
        """Encode what isn't known yet; known holds ids as little-endian words."""
        if len(self.known) > WORDS_KEPT:
            self.known.clear()
        fresh = [p for p in pieces if p not in self.known]
        words = [p for p in fresh if isinstance(p, str)]
        for at in range(0, len(words), 50_000):
            part = words[at : at + 50_000]
            for word, ids in zip(part, self.encode_words(part)):
                self.known[word] = ids.astype("<u4").tobytes()
        for p in fresh:
            if not isinstance(p, str):
                self.known[p] = p.to_bytes(4, "little")

    def encode(self, text: str | None) -> np.ndarray:
        pieces = self.pieces(text)
        self.learn(set(pieces))
        return np.frombuffer(b"".join(self.known[p] for p in pieces), dtype="<u4")

    def decode(self, ids) -> str:
        """Tokens joined by spaces; the vocabulary has no decoder of its own. Unknown ids are skipped."""
        return " ".join(self.tokens[int(i)] for i in ids if int(i) in self.tokens)


def _worker_bpe(definition: bytes) -> WordBpe:
    return worker_table(f"bpe {hashlib.sha256(definition).hexdigest()}", lambda: WordBpe(definition))


def _digests(shared):
    def run(batches):
        bpe = _worker_bpe(shared.value)
        sha = lambda data: hashlib.sha256(data).hexdigest()
        for batch in slices(batches, 64):
            rows = []
            texts = [bpe.pieces(t) for t in batch.column(1).to_pylist()]
            bpe.learn(set().union(*texts))
            known = bpe.known
            for pieces in texts:
                ids = b"".join([known[p] for p in pieces])
                decoded = " ".join(map(bpe.tokens.__getitem__, np.frombuffer(ids, dtype="<u4").tolist()))
                rows.append((len(ids) // 4, sha(ids), sha(decoded.encode())))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), *(pa.array(c) for c in zip(*rows))], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
            )

    return run


def round_trip(docs: DataFrame, vocabulary: str | None = None) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of every row's whole text."""
    with open(vocabulary or default_vocabulary(), "rb") as f:  # a file of the driver's installation; workers get its bytes
        shared = docs.sparkSession.sparkContext.broadcast(f.read())
    picked = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return picked.mapInArrow(_digests(shared), "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def _encode_batches(shared):
    def run(batches):
        bpe = _worker_bpe(shared.value)
        for batch in slices(batches, 64):
            texts = [bpe.pieces(t) for t in batch.column(1).to_pylist()]
            bpe.learn(set().union(*texts))
            ids = [np.frombuffer(b"".join(bpe.known[p] for p in x), dtype="<u4").astype(np.int32) for x in texts]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(ids, type=pa.list_(pa.int32()))], names=["doc_id", "ids"])

    return run


def encode(docs: DataFrame, vocabulary: str | None = None) -> DataFrame:
    """doc_id and ids (array of int) of every row's whole text."""
    with open(vocabulary or default_vocabulary(), "rb") as f:
        shared = docs.sparkSession.sparkContext.broadcast(f.read())
    picked = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return picked.mapInArrow(_encode_batches(shared), "doc_id long, ids array<int>")


def _decode_batches(shared):
    def run(batches):
        bpe = _worker_bpe(shared.value)
        for batch in slices(batches, 256):
            texts = [bpe.decode(x or ()) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, type=pa.string())], names=["doc_id", "text"])

    return run


def decode(encoded: DataFrame, vocabulary: str | None = None) -> DataFrame:
    """doc_id and text of rows with ids; null ids give the empty text."""
    with open(vocabulary or default_vocabulary(), "rb") as f:
        shared = encoded.sparkSession.sparkContext.broadcast(f.read())
    return encoded.select("doc_id", "ids").mapInArrow(_decode_batches(shared), "doc_id long, text string")
