"""SimHash near-duplicates: 64-bit fingerprints of word shingles, linked at a
small Hamming radius by tiled exact comparison, grouped by reachability.

Plan
----
1. One Arrow pass over whole texts gives a fingerprint per row; the small
   (id, fingerprint) table is written once.
2. Equal fingerprints collapse by a partial aggregate, so copies cost nothing
   further however many there are.
3. Cutting 64 bits into ``blocks`` parts, two fingerprints within radius r
   agree on at least blocks - r parts. Each distinct fingerprint is keyed by
   every choice of that many parts; only equal keys are compared. This is
   exact, no link is lost.
4. Keys are compared as tiles with exclusive-or and bit counts; tiles are
   ordered by population count, and tile pairs further apart than the radius
   are skipped. A key with more than ``tile_rows`` fingerprints is dealt to
   several tasks as pairs of tiles, again only those within the radius.
   A task emits a spanning forest of what it links, never all pairs.
5. Reachability by alternating large-star and small-star rounds on the edge
   table; every round is written to the shared folder.

Defined results: a null text and a text with no word have fingerprint zero,
linked like any other; rows with a null id take part in linking, but an id of
null is never a component's smallest; repeated rows each get a row.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import record_batch, sieve, slices, spool

_EDGES = pa.schema([("u", pa.int64()), ("v", pa.int64())])
_CHUNK = 1 << 15


def fingerprint(text: bytes | None, width: int = 3, seed: int = 42) -> int:
    """Unsigned 64-bit SimHash of one UTF-8 text."""
    words = (text or b"").lower().split()  # bytes: ASCII case and ASCII white space only
    if not words:
        return 0
    if len(words) <= width:
        hashes = [xxhash.xxh64_intdigest(b" ".join(words), seed)]
    else:
        digest = xxhash.xxh64_intdigest
        hashes = [digest(s, seed) for s in map(b" ".join, zip(*(words[i:] for i in range(width))))]
    h = np.array(hashes, dtype="<u8")
    ones = np.zeros(64, dtype=np.int64)
    for at in range(0, len(h), _CHUNK):
        part = h[at : at + _CHUNK].view(np.uint8).reshape(-1, 8)
        ones += np.unpackbits(part, axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    bits = (ones * 2 > len(h)).astype(np.uint8)
    return int(np.packbits(bits, bitorder="little").view("<u8")[0])


def _fingerprint_batches(width: int, seed: int):
    def run(batches):
        for batch in slices(batches, 2048):
            values = [fingerprint(t.as_py(), width, seed) for t in batch.column(1)]
            signed = np.array(values, dtype=np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(signed), batch.column(2)], names=["doc_id", "fp", "digest"])

    return run


def text_digest() -> Column:
    """A digest of the text that tells null from empty texts."""
    return F.coalesce(F.md5(F.col("text").cast("binary")), F.lit("-"))


def fingerprints(docs: DataFrame, width: int = 3, seed: int = 42) -> DataFrame:
    """(doc_id, fp, digest) of every row; fp is the fingerprint as a signed long, digest that of the text."""
    picked = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("text"), text_digest().alias("digest"))
    return picked.mapInArrow(_fingerprint_batches(width, seed), "doc_id long, fp long, digest string")


def _roots(n: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Smallest reachable index of each of n items, by hooking and pointer jumping."""
    root = np.arange(n)
    while len(i):
        low = np.minimum(root[i], root[j])
        before = root.copy()
        np.minimum.at(root, root[i], low)
        np.minimum.at(root, root[j], low)
        while not np.array_equal(root, root[root]):
            root = root[root]
        if np.array_equal(before, root):
            break
    return root


def linked_pairs(fps: np.ndarray, radius: int, tile: int = 512, side: np.ndarray | None = None):
    """Index pairs (i, j) of fingerprints at most ``radius`` bits apart.

    ``fps`` (unsigned) is taken in order of population count; tile pairs whose
    counts differ beyond the radius are skipped. With ``side``, only pairs of
    different sides are returned.
    """
    pop = np.bitwise_count(fps).astype(np.int64)
    order = np.argsort(pop, kind="stable")
    f, p = fps[order], pop[order]
    s = side[order] if side is not None else None
    left, right = [], []
    for a in range(0, len(f), tile):
        last = p[min(a + tile, len(f)) - 1]
        for b in range(a, len(f), tile):
            if p[b] - last > radius:
                break
            near = np.bitwise_count(f[a : a + tile, None] ^ f[None, b : b + tile]) <= radius
            if s is not None:
                near &= s[a : a + tile, None] != s[None, b : b + tile]
            i, j = np.nonzero(near)
            i, j = i + a, j + b
            keep = i < j
            left.append(order[i[keep]])
            right.append(order[j[keep]])
    if not left:
        return np.empty(0, int), np.empty(0, int)
    return np.concatenate(left), np.concatenate(right)


def _forest(fps: np.ndarray, side: np.ndarray, radius: int):
    """Edges (member, root) that connect exactly what is linked inside one group."""
    own = np.unique(side)
    i, j = linked_pairs(fps, radius, side=side if len(own) > 1 else None)
    if not len(i):
        return None
    root = _roots(len(fps), i, j)
    moved = np.nonzero(root != np.arange(len(fps)))[0]
    signed = fps.view(np.int64)
    return signed[moved], signed[root[moved]]


def _compare_groups(radius: int):
    """Rows come sorted by (key columns); each run of equal keys is one group of bounded size."""

    def flush(parts, out):
        if sum(len(x[1]) for x in parts) > 1:
            fps = np.concatenate([x[1] for x in parts])
            got = _forest(fps.view(np.uint64), np.concatenate([x[2] for x in parts]), radius)
            if got is not None:
                out.append(got)

    def run(batches):
        held, held_key = [], None
        for batch in batches:
            if not batch.num_rows:
                continue
            out = []
            key = np.stack([batch.column(k).to_numpy().astype(np.int64) for k in range(3)], axis=1)
            fp = batch.column(3).to_numpy()
            side = batch.column(4).to_numpy()
            cuts = np.nonzero((key[1:] != key[:-1]).any(axis=1))[0] + 1
            starts = np.concatenate([[0], cuts])
            ends = np.concatenate([cuts, [len(key)]])
            last = len(starts) - 1
            for g in np.unique(np.concatenate([[0, last], np.nonzero(ends - starts > 1)[0]])):
                a, b = starts[g], ends[g]
                here = tuple(key[a])
                if here != held_key:
                    flush(held, out)
                    held, held_key = [], here
                held.append((here, fp[a:b], side[a:b]))
                if g != last:
                    flush(held, out)
                    held, held_key = [], None
            if out:
                yield record_batch(_EDGES, np.concatenate([x[0] for x in out]), np.concatenate([x[1] for x in out]))
        out = []
        flush(held, out)
        if out:
            yield record_batch(_EDGES, out[0][0], out[0][1])

    return run


def _signed(mask: int) -> int:
    return mask - (1 << 64) if mask >> 63 else mask


def block_masks(blocks: int, radius: int) -> list[int]:
    """Bit masks of every choice of blocks - radius out of ``blocks`` nearly equal parts of 64 bits."""
    edges = [round(64 * k / blocks) for k in range(blocks + 1)]
    parts = [((1 << (b - a)) - 1) << a for a, b in zip(edges, edges[1:])]
    return [_signed(sum(c)) for c in combinations(parts, blocks - radius)]


def links(fps: DataFrame, radius: int = 3, blocks: int = 5, tile_rows: int = 2048) -> DataFrame:
    """Edges (u, v) between distinct fingerprints, enough to connect all that are linked."""
    keyed = fps.select(
        "fp", F.posexplode(F.array(*[F.col("fp").bitwiseAND(F.lit(m).cast("long")) for m in block_masks(blocks, radius)])).alias("part", "bucket")
    )
    large = spool(keyed.groupBy("part", "bucket").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > tile_rows), "large")
    # Written first, so its size is known: Spark broadcasts it below its threshold, else joins by sorting.
    dealt = keyed.join(large, ["part", "bucket"], "left")
    slots = F.ceil(F.col("n") / F.lit(tile_rows // 4)).cast("int")
    pop, slot = F.bit_count("fp"), F.pmod(F.xxhash64("fp"), slots).cast("int")
    tile = F.when(F.col("n").isNull(), F.lit(0)).otherwise(pop * slots + slot).cast("long")
    dealt = dealt.select("part", "bucket", "fp", tile.alias("tile"), F.coalesce(slots, F.lit(0)).alias("slots"))
    # The other tiles a tile has to meet: all slots of population counts within the radius.
    low, high = F.greatest(F.lit(0), F.col("tile") - (radius + 1) * F.col("slots")), F.col("tile") + (radius + 1) * F.col("slots")
    other = F.when(F.col("slots") == 0, F.array(F.lit(0).cast("long"))).otherwise(F.sequence(low, high))
    spread = dealt.select("*", F.explode(other).alias("other")).where(
        (F.col("slots") == 0) | (F.abs(F.floor(F.col("tile") / F.col("slots")) - F.floor(F.col("other") / F.col("slots"))) <= radius)
    )
    pair = F.when(F.col("slots") == 0, F.lit(0)).otherwise(F.least("tile", "other") * 100_000_000 + F.greatest("tile", "other"))
    grouped = spread.select(F.col("part").cast("long").alias("part"), "bucket", pair.cast("long").alias("pair"), "fp", "tile")
    grouped = grouped.repartition("part", "bucket", "pair").sortWithinPartitions("part", "bucket", "pair")
    return grouped.mapInArrow(_compare_groups(radius), "u long, v long")


def components(edges: DataFrame, max_rounds: int = 40) -> DataFrame:
    """(node, root): the smallest node reachable, for every node that has an edge.

    Alternates large-star and small-star until the edge set is a set of stars.
    Joins are against tables already written, so that hot nodes are split by
    the adaptive skew join.
    """
    edges = spool(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
    mark = None
    for _ in range(max_rounds):
        both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = spool(both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")), "low")
        wide = both.join(low, "u").where("v > u and v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        wide = spool(wide.distinct(), "wide")
        low = spool(wide.groupBy("u").agg(F.min("v").alias("m")), "low")
        pairs = F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))
        near = wide.join(low, "u").select(F.inline(pairs)).where("u <> v").distinct()
        edges = spool(near, "edges")
        now = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == mark:
            break
        mark = now
    else:
        raise RuntimeError("components did not settle; raise max_rounds")
    return edges.select(F.col("u").alias("node"), F.col("v").alias("root")).union(
        edges.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()
    )


def _groups(docs: DataFrame, width: int = 3, radius: int = 3, blocks: int = 5, tile_rows: int = 2048) -> tuple[DataFrame, DataFrame]:
    """(doc_id, fp, digest) of every row, and fp, root (smallest fingerprint reachable), component_id of every fingerprint."""
    prints = spool(fingerprints(docs, width), "prints")
    firsts = spool(prints.groupBy("fp").agg(F.min("doc_id").alias("first_id")), "firsts")
    node = spool(components(links(firsts, radius, blocks, tile_rows)), "nodes")
    linked = firsts.join(node, firsts.fp == node.node).select("fp", "root", "first_id")
    smallest = linked.groupBy("root").agg(F.min("first_id").alias("least_id"))
    named = spool(linked.join(smallest, "root").select("fp", "root", "least_id"), "named")
    ids = firsts.join(named, "fp", "left").select("fp", F.coalesce("root", "fp").alias("root"), F.coalesce("least_id", "first_id").alias("component_id"))
    return prints, spool(ids, "ids")


def near_duplicates(docs: DataFrame, **options) -> DataFrame:
    """doc_id, fp, component_id for every row of ``docs`` (see module text)."""
    prints, ids = _groups(docs, **options)
    return prints.join(ids, "fp").select("doc_id", "fp", "component_id")


def keep_first(docs: DataFrame, **options) -> DataFrame:
    """One row per component, with the columns of ``docs``: that of the smallest id.

    Rows without id come after all ids; of rows with the same id the one whose text has the
    smallest digest stays, of rows with the same id and text any one.
    """
    prints, ids = _groups(docs, **options)
    return kept_of(docs, prints, ids)


def row_name(doc_id: Column) -> Column:
    """One value that says which row it is, by its id and the column digest; only repeated rows share it."""
    return F.concat_ws(":", F.coalesce(doc_id.cast("string"), F.lit("")), "digest")


def kept_of(docs: DataFrame, prints: DataFrame, ids: DataFrame) -> DataFrame:
    """The kept rows by (doc_id, fp, digest of the text) of every row and (fp, root).

    Only rows that may go (of a name that isn't kept, or repeated) are shuffled; all others stay where they are read.
    """
    name = row_name(F.col("doc_id"))
    place = F.struct(F.col("doc_id").isNull().alias("nameless"), F.col("doc_id").alias("id"), "digest", name.alias("name"))
    least = prints.groupBy("fp").agg(F.min(place).alias("k"))  # copies collapse before the join
    first = least.join(ids.select("fp", "root"), "fp").groupBy("root").agg(F.min("k").alias("k"))
    keep = spool(first.select("k.name", F.xxhash64("k.name").alias("h")), "keep")
    zero, one = F.lit(0).cast("long"), F.lit(1).cast("long")
    seen = prints.select(F.xxhash64(name).alias("h"), one.alias("rows"), zero.alias("kept")).union(keep.select("h", zero, one))
    doubt = spool(seen.groupBy("h").agg(F.sum("rows").alias("rows"), F.sum("kept").alias("kept")).where("rows > 1 or kept = 0").select("h"), "doubt")
    passed = sieve(doubt)
    rows = docs.select(F.col("doc_id").cast("long").alias("id"), text_digest().alias("digest"), F.struct(*docs.columns).alias("row"))
    rows = rows.select(row_name(F.col("id")).alias("name"), "row")
    sure = passed(rows, F.xxhash64("name"), "left_anti").select("row")
    # One column says which row it is, so that the join and the removal of repeated rows share a distribution.
    held = passed(rows, F.xxhash64("name")).join(passed(keep, F.col("h")).select("name"), "name", "left_semi").dropDuplicates(["name"])
    return sure.union(held.select("row")).select("row.*")
