"""Near-duplicates by SimHash and measured similarity: texts whose sets of five-word
shingles have a Jaccard similarity of at least 0.8, grouped by reachability.

Plan
----
1. One Arrow pass over whole texts gives each row a key (digest of its shingle set), a SimHash of
   ``BITS`` bits of the set, and ``BANDS`` block numbers, each made of ``DEEP`` minima of the set under
   fixed hash orders. Two sets of similarity s share a block with probability 1 - (1 - s^DEEP)^BANDS, which
   is 0.99999 at 0.8 and more above.
2. Equal keys collapse; only blocks with several keys go on.
3. Inside a block, SimHashes are compared as tiles with exclusive-or and bit counts, ordered by size of set; tiles
   whose sizes rule 0.8 out are skipped. A pair is a candidate at ``radius`` bits or fewer, which two sets
   of similarity 0.8 exceed with a probability of about 1 in 100,000. A block with more than ``TILE_ROWS`` keys is dealt to
   several tasks as pairs of tiles.
4. Candidates are verified: sets of 64-bit shingle hashes are read again for the keys concerned and intersected.
   First each key meets its smallest candidate, then twice its nearest of another group, then all
   that are left in other groups, these by ``WIDE`` bits; so every candidate is verified, already in one group, or ruled out exactly: shingles that no
   other key of these has are common with nobody, and too many of them leave no room for a similarity of 0.8. A group
   of near copies thus costs few pairs beyond its size, and different texts that share a passage are told apart by
   their SimHashes before any pair becomes a row.

Three bits of 64, as op4 links, are far too few for a similarity of 0.8 (about 10 of 64 differ), and blocks of
SimHash bits alone would need hundreds per text at such a radius; hence the wider fingerprint and the blocks of minima.

Defined results: texts without words have the empty set and are equal; a text
of up to five words is one shingle. ASCII case and white space don't count.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import TEXT_ROWS, record_batch, sieve, slices, spool, worker_table
from .simhash import components, kept_of, row_name, text_digest

WIDTH, SIMILAR = 5, 0.8
BANDS, DEEP = 30, 5
BITS, WIDE, TILE, TILE_ROWS = 512, 4096, 512, 4096
_SEED = 42
_RNG = np.random.default_rng(11)
_TURN = _RNG.integers(0, 1 << 64, BANDS * DEEP, dtype=np.uint64)
_SPREAD = _RNG.integers(0, 1 << 64, BANDS * DEEP, dtype=np.uint64) | np.uint64(1)
_CHUNK = 1024
_MIX = _RNG.integers(0, 1 << 64, (2, WIDE // 64), dtype=np.uint64) | np.uint64(1)
_PAIRS = pa.schema([("u", pa.int64()), ("v", pa.int64())])


def shingle_set(text: bytes | None) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the shingles of one UTF-8 text."""
    words = (text or b"").lower().split()  # bytes: ASCII case and ASCII white space only
    if not words:
        return np.empty(0, np.uint64)
    shingles = [b" ".join(words)] if len(words) <= WIDTH else set(map(b" ".join, zip(*(words[i:] for i in range(WIDTH)))))
    return np.unique(np.array([xxhash.xxh64_intdigest(s, _SEED) for s in shingles], dtype=np.uint64))


def set_key(hashes: np.ndarray) -> int:
    return xxhash.xxh64_intdigest(hashes.tobytes(), _SEED)


def buckets(hashes: np.ndarray) -> list[int]:
    """One number per band; the empty set is in no bucket, as equal keys join it already."""
    if not len(hashes):
        return []
    low = np.full(BANDS * DEEP, np.iinfo(np.uint64).max)
    for at in range(0, len(hashes), _CHUNK):
        np.minimum(low, ((hashes[at : at + _CHUNK, None] ^ _TURN) * _SPREAD).min(axis=0), out=low)
    return [xxhash.xxh64_intdigest(part.tobytes(), k) for k, part in enumerate(low.reshape(BANDS, DEEP))]


def fingerprint(hashes: np.ndarray, bits: int = BITS) -> bytes:
    """SimHash of a set: a bit is 1 if it is set in over half of its hashes, each mixed to ``bits`` bits."""
    ones = np.zeros(bits, dtype=np.int64)
    mix = _MIX[:, : bits // 64]
    for at in range(0, len(hashes), _CHUNK):
        h = hashes[at : at + _CHUNK, None] * mix[0]
        h = (h ^ (h >> np.uint64(29))) * mix[1]
        h = np.ascontiguousarray(h ^ (h >> np.uint64(32)))
        for part in np.split(h, range(255, len(h), 255)):  # sums of up to 255 bits, eight to a word
            ones += np.unpackbits(part.view(np.uint8), axis=1).view(np.uint64).sum(axis=0).view(np.uint8)
    return np.packbits(ones * 2 > len(hashes)).tobytes()


def radius(size: np.ndarray, bits: int = BITS) -> np.ndarray:
    """Bits in which two sets of similarity 0.8, the smaller of ``size``, differ at most but for 1 case in 100,000.

    A bit differs with a probability of at most 0.1875 at 4 shingles, 0.162 up to 63 and 0.154 above (summed
    exactly for all sizes up to 63 and some up to 600); 4.5 standard deviations are added.
    """
    p = np.where(size < 5, 0.1875, np.where(size < 64, 0.162, 0.154))
    return np.ceil(bits * p + 4.5 * np.sqrt(bits * p * (1 - p))).astype(int)


def _signed(values) -> np.ndarray:
    return np.array(values, dtype=np.uint64).view(np.int64)


def _marks(batches):
    worker_table("similar", dict)  # keeps nothing, but tables of a stage before are dropped
    for batch in slices(batches, 1024):
        sets = [shingle_set(t) for t in batch.column(1).to_pylist()]
        keys, bands = pa.array(_signed([set_key(s) for s in sets])), [_signed(buckets(s)) for s in sets]
        prints, sizes = pa.array([fingerprint(s) for s in sets], pa.binary()), pa.array([len(s) for s in sets], pa.int64())
        yield pa.RecordBatch.from_arrays([batch.column(0), keys, pa.array(bands, pa.list_(pa.int64())), batch.column(2), prints, sizes], names=["doc_id", "fp", "bands", "digest", "sim", "size"])


def _sets(batches):
    seen = set()
    for batch in slices(batches, 256):
        sets = {set_key(s): s for s in map(shingle_set, batch.column(0).to_pylist())}
        keys, sets = [k for k in sets if k not in seen], [s for k, s in sets.items() if k not in seen]
        seen.update(keys)
        yield pa.RecordBatch.from_arrays([pa.array(_signed(keys)), pa.array([s.view(np.int64) for s in sets], pa.list_(pa.int64()))], names=["fp", "hashes"])


def _wide(batches):
    for batch in slices(batches, 256):
        prints = [fingerprint(np.array(h, dtype=np.int64).view(np.uint64), WIDE) for h in batch.column(1).to_pylist()]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(prints, pa.binary())], names=["fp", "sim"])


def _verified(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """Of the pairs (u, v) of keys those that are similar."""
    both = pairs.join(sets.select(F.col("fp").alias("u"), F.col("hashes").alias("a")), "u").join(sets.select(F.col("fp").alias("v"), F.col("hashes").alias("b")), "v")
    common = F.size(F.array_intersect("a", "b"))
    return both.where(100 * common >= round(100 * SIMILAR) * (F.size("a") + F.size("b") - common)).select("u", "v")


def _sets_of(texts: DataFrame, chosen: DataFrame) -> DataFrame:
    """fp, hashes, one row per set, of the texts whose row is ``chosen``, and of the few others that its sieve lets through."""
    found = sieve(chosen)(texts, F.xxhash64(row_name(F.col("doc_id")))).select("text").mapInArrow(_sets, "fp long, hashes array<long>")
    found = spool(found.withColumn("at", F.monotonically_increasing_id()), "sets", rows=TEXT_ROWS)
    twice = found.groupBy("fp").agg(F.count(F.lit(1)).alias("n"), F.min("at").alias("least")).where("n > 1").select("fp", "least")
    twice = spool(twice, "twice")  # equal rows that several tasks read
    if twice.take(1):
        found = found.join(twice, "fp", "left").where("least is null or at = least")
    return found.select("fp", "hashes")


def near_pairs(sim: np.ndarray, size: np.ndarray, room: np.ndarray, root: np.ndarray, form: str, slot: np.ndarray | None = None):
    """Index pairs (i, j) of one block within the radius and in different groups, i after j; with ``slot`` only pairs across slots.

    ``sim`` has a row of words per key; ``room`` bounds what a key can have in common with others. Form first: each key's first candidate; nearest: its nearest; all: every pair.
    """
    order = np.argsort(size, kind="stable")
    f, n, m, r = sim[order], size[order], room[order], root[order]
    part, width = round(100 * SIMILAR), 64 * f.shape[1]
    reach = radius(n, width)
    q = slot[order] if slot is not None else None
    first = np.full(len(f), len(f))
    best, least = np.full(len(f), -1), np.full(len(f), width + 1)
    left, right = [], []
    for a in range(0, len(f), TILE):
        x = slice(a, a + TILE)
        top = n[min(a + TILE, len(f)) - 1]
        for b in range(a, len(f), TILE):
            if 100 * top < part * n[b]:
                break
            y = slice(b, b + TILE)
            bits = sum(np.bitwise_count(f[x, None, w] ^ f[None, y, w]).astype(np.int16) for w in range(f.shape[1]))
            near = (bits <= reach[x, None]) & (r[x, None] != r[None, y]) & ((100 + part) * np.minimum(m[x, None], m[None, y]) >= part * (n[x, None] + n[None, y]))
            if q is not None:
                near &= q[x, None] != q[None, y]
            if a == b:
                near &= np.tri(near.shape[0], near.shape[1], -1, dtype=bool).T
            if form == "nearest":
                bits = np.where(near, bits, width + 1)
                for span, axis, shift in ((x, 1, b), (y, 0, a)):
                    low = bits.min(axis=axis)
                    better = low < least[span]
                    best[span] = np.where(better, bits.argmin(axis=axis) + shift, best[span])
                    least[span] = np.minimum(least[span], low)
                continue
            i, j = np.nonzero(near)
            i, j = order[i + a], order[j + b]
            if form == "first":
                np.minimum.at(first, np.maximum(i, j), np.minimum(i, j))
            else:
                left.append(np.maximum(i, j))
                right.append(np.minimum(i, j))
    if form == "first":
        i = np.nonzero(first < len(f))[0]
        return i, first[i]
    if form == "nearest":
        i = np.nonzero(best >= 0)[0]
        i, j = order[i], order[best[i]]
        return np.maximum(i, j), np.minimum(i, j)
    return (np.concatenate(left), np.concatenate(right)) if left else (np.empty(0, int), np.empty(0, int))


def _compare(form: str):
    """Rows (bucket, pair, fp, root, size, room, slot, sim) come sorted by (bucket, pair, fp); each run of equal bucket and pair is one group of bounded size."""

    def solved(held):
        fp, root, size, room, slot = (np.concatenate([h.column(k).to_numpy() for h in held]) for k in range(2, 7))
        if len(fp) < 2 or (root == root[0]).all():
            return []
        sim = np.frombuffer(b"".join(s for h in held for s in h.column(7).to_pylist()), dtype=np.uint64).reshape(len(fp), -1)
        i, j = near_pairs(sim, size, room, root, form, slot if (slot != slot[0]).any() else None)
        return [(fp[i], fp[j])] if len(i) else []

    def run(batches):
        held, held_key = [], None
        for batch in batches:
            if not batch.num_rows:
                continue
            out = []
            key = np.stack([batch.column(k).to_numpy() for k in (0, 1)], axis=1)
            cuts = [0, *(np.nonzero((key[1:] != key[:-1]).any(axis=1))[0] + 1), len(key)]
            for a, b in zip(cuts, cuts[1:]):
                if tuple(key[a]) != held_key:
                    out += solved(held) if held else []
                    held, held_key = [], tuple(key[a])
                held.append(batch.slice(a, b - a))
            if out:
                yield record_batch(_PAIRS, *(np.concatenate(c) for c in zip(*out)))
        if out := solved(held) if held else []:
            yield record_batch(_PAIRS, *out[0])

    return run


def candidates(members: DataFrame, large: DataFrame, form: str) -> DataFrame:
    """Distinct (u, v), v < u, of ``members`` (bucket, fp, root, size, room, sim); ``large`` has the slots of blocks that are dealt to several tasks."""
    dealt = members.join(large, "bucket", "left")
    slot = F.coalesce(F.pmod(F.xxhash64("fp"), F.col("slots")), F.lit(0)).cast("long")
    meet = F.when(F.col("slots").isNull(), F.array(F.lit(0).cast("long"))).otherwise(F.sequence(F.lit(0).cast("long"), F.col("slots") - 1))
    spread = dealt.withColumn("slot", slot).withColumn("other", F.explode(meet))
    # Pairs of different slots only compare across them; a slot with itself compares inside.
    pair = F.least("slot", "other") * (1 << 31) + F.greatest("slot", "other")
    rows = spread.select("bucket", pair.alias("pair"), "fp", "root", "size", "room", "slot", "sim")
    rows = rows.repartition("bucket", "pair").sortWithinPartitions("bucket", "pair", "fp")
    return rows.mapInArrow(_compare(form), "u long, v long").distinct()


def _groups(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(doc_id, fp, digest) of every row, and fp, root (smallest key reachable), component_id of every key."""
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("text"), text_digest().alias("digest"))
    marks = spool(texts.mapInArrow(_marks, "doc_id long, fp long, bands array<long>, digest string, sim binary, size long"), "marks", rows=TEXT_ROWS)
    prints = marks.select("doc_id", "fp", "digest")
    row = F.xxhash64(row_name(F.col("doc_id")))
    firsts = spool(prints.groupBy("fp").agg(F.min("doc_id").alias("first_id"), F.min(row).alias("row")), "firsts")
    placed = marks.select("fp", F.explode("bands").alias("bucket"))
    shared = spool(placed.groupBy("bucket").agg(F.min("fp").alias("leader"), F.max("fp").alias("top")).where("leader < top").select("bucket"), "shared")
    members = spool(sieve(shared)(placed, F.col("bucket")).distinct().join(shared, "bucket", "left_semi"), "members")
    # Fingerprints of the keys concerned.
    concerned = spool(members.select("fp").distinct(), "concerned")
    known = sieve(concerned)(marks.select("fp", "size", F.col("size").alias("room"), "sim"), F.col("fp"))
    known = spool(known.dropDuplicates(["fp"]).join(concerned, "fp", "left_semi"), "known")
    large = members.groupBy("bucket").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > TILE_ROWS)
    large = spool(large.select("bucket", F.ceil(F.col("n") / F.lit(TILE_ROWS // 2)).cast("long").alias("slots")), "large")
    node = edges = done = sets = None
    for form in ("first", "nearest", "nearest again", "all"):
        if node is None:
            here = members.join(known.withColumn("root", F.col("fp")), "fp")
        else:  # only blocks that still hold several groups
            now = known.join(node.withColumnRenamed("node", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
            here = spool(members.join(now, "fp"), "placed")
            split = spool(here.groupBy("bucket").agg(F.min("root").alias("a"), F.max("root").alias("b")).where("a < b").select("bucket"), "split")
            here = here.join(split, "bucket", "left_semi")
        found = spool(candidates(here, large, form.split()[0]), "candidates")
        pairs = found if done is None else spool(found.join(done, ["u", "v"], "left_anti"), "pairs")
        done = pairs if done is None else done.union(pairs)
        # The sets of the keys of these pairs that aren't there yet, each from one of its texts.
        ends = spool(pairs.select(F.explode(F.array("u", "v")).alias("fp")).distinct(), "ends")
        wanted = ends if sets is None else ends.join(sets.select("fp"), "fp", "left_anti")
        chosen = spool(firsts.join(wanted, "fp", "left_semi").select("row"), "chosen")
        if sets is None or chosen.take(1):
            more = _sets_of(texts, chosen)
            sets = more if sets is None else sets.union(more)
        links = spool(_verified(pairs, sieve(ends)(sets, F.col("fp"))).distinct(), "links")
        edges = links if edges is None else edges.union(links)
        if node is None or links.take(1):
            node = spool(components(edges), "nodes")
        if form.startswith("nearest"):
            # Every key that has a candidate left is in one of these pairs, so a shingle that only one of them has is in no pair's intersection.
            touched = spool(found.select(F.explode(F.array("u", "v")).alias("fp")).distinct(), "touched")
            near = sieve(touched)(sets, F.col("fp")).join(touched, "fp", "left_semi")
            one = near.select("fp", F.explode("hashes").alias("h")).groupBy("h").agg(F.min("fp").alias("fp"), F.max("fp").alias("top")).where("fp = top")
            alone = spool(one.groupBy("fp").agg(F.count(F.lit(1)).alias("alone")), "alone")
            known = known.select("fp", "size").join(touched, "fp", "left_semi").join(alone, "fp", "left").withColumn("room", F.col("size") - F.coalesce("alone", F.lit(0))).drop("alone")
            known = spool(known.where(100 * F.col("room") >= round(100 * SIMILAR) * F.col("size")), "room")
            # The few keys left get wider fingerprints, from the sets at hand.
            known = spool(known.join(near.mapInArrow(_wide, "fp long, sim binary").dropDuplicates(["fp"]), "fp"), "known", rows=TEXT_ROWS)
    linked = firsts.join(node, firsts.fp == node.node).select("fp", "root", "first_id")
    smallest = linked.groupBy("root").agg(F.min("first_id").alias("least_id"))
    grouped = spool(linked.join(smallest, "root").select("fp", "root", "least_id"), "grouped")
    ids = firsts.join(grouped, "fp", "left").select("fp", F.coalesce("root", "fp").alias("root"), F.when(F.col("root").isNull(), F.col("first_id")).otherwise(F.col("least_id")).alias("component_id"))
    return prints, spool(ids, "ids")


def similar_groups(docs: DataFrame) -> DataFrame:
    """doc_id, component_id (the smallest id of the group) for every row."""
    prints, ids = _groups(docs)
    return prints.join(ids, "fp").select("doc_id", "component_id")


def keep_first(docs: DataFrame) -> DataFrame:
    """The row of the smallest id of each group, with the columns of ``docs`` (rows without id and repeated ids as in simhash.keep_first)."""
    prints, ids = _groups(docs)
    return kept_of(docs, prints, ids)
