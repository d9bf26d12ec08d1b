"""SimHash near-duplicates by vantage-point trees over Hamming distance.

Fingerprints are made of the XXH64 hashes of word shingles. Equal fingerprints are first reduced to one, so copies are
no hot spot. A tree of vantage points, fitted on a sample (SAMPLE fingerprints, or PER_SHARD a shard where that is more), cuts the space
into shards, of some candidates by the vantage point with the fewest fingerprints in reach of both sides; each fingerprint has one home shard and visits every nearer shard that the triangle bound cannot rule
out, so that each linking pair meets in the home shard of one of its two. Within a shard the same cutting
goes on in memory down to LEAF fingerprints, which are compared in blocks. A shard returns a spanning star of each of
its linked sets, never all pairs; the sets are then joined by distributed connected components.

Lower-casing is A-Z only; words are runs without ASCII white space. A text with fewer words than a shingle has one
shingle, all of them; a text without words and a null text have fingerprint zero, linked like any other. A component's
id is its smallest doc_id, ignoring nulls. Repeated rows are rows of one component. An empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathlore.llm.common import attach_groups, connected_components, map_batches, stage

WORDS_IN_SHINGLE, SEED, RADIUS = 3, 42, 2
#: Fingerprints on which the upper tree is fitted, at least and for each shard; fingerprints compared in a block; vantage points tried.
SAMPLE, PER_SHARD, LEAF, TRIED = 20_000, 16, 256, 6
#: Home fingerprints of a shard: SHARD until there are MANY shards, then more, up to LARGEST.
SHARD, MANY, LARGEST = 30_000, 4096, 1_000_000


def fingerprint(text: str | None, words_in_shingle: int = WORDS_IN_SHINGLE, seed: int = SEED) -> int:
    """The 64-bit SimHash of a text: a bit is 1 if more than half of the shingles' hashes have it."""
    words = (text or "").encode("utf-8", "replace").lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    if len(words) <= words_in_shingle:
        return xxhash.xxh64_intdigest(joined, seed)
    lens = np.fromiter(map(len, words), "int64", len(words))
    ends = np.cumsum(lens + 1) - 1
    starts = (ends - lens)[: len(words) - words_in_shingle + 1].tolist()
    digest = xxhash.xxh64_intdigest
    n = len(starts)
    hashes = np.fromiter([digest(joined[a:b], seed) for a, b in zip(starts, ends[words_in_shingle - 1 :].tolist(), strict=True)], "uint64", n)
    return bits_over_half(hashes)


def bits_over_half(hashes: np.ndarray) -> int:
    bits = np.unpackbits(hashes.astype("<u8").view("uint8").reshape(-1, 8), axis=1, bitorder="little")
    over = bits.sum(axis=0, dtype="int64") * 2 > len(hashes)
    return int(np.packbits(over, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id and fp (the fingerprint as a signed long) of each document."""

    def work(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        fps = np.fromiter((fingerprint(t.as_py()) for t in batch.column("text")), "uint64", batch.num_rows)
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(fps.view("int64"))], ["doc_id", "fp"])

    return map_batches(docs.select("doc_id", "text"), work, "doc_id long, fp long")


def split(points: np.ndarray, seed: int, radius: int = RADIUS, tried: int = 1) -> tuple[np.uint64, int, np.ndarray] | None:
    """A vantage point, the distance that about halves the points, and the points' distances; None if no distance parts them.

    Of several vantage points and cuts that leave a third on either side, the pair with the fewest points that must visit the other side.
    """
    best = None
    for k in range(tried):
        vantage = points[(seed * 0x9E3779B1 + k * 0x85EBCA6B) % len(points)]
        d = np.bitwise_count(points ^ vantage)
        at = int(np.median(d))
        sizes = np.cumsum(np.bincount(d, minlength=at + radius + 3))  # points within each distance
        for cut in (at, at - 1, at + 1, *([at - 2, at + 2] if tried > 1 else [])):
            if cut < 0 or not 0 < sizes[cut] < len(points):
                continue
            visitors = int(sizes[min(cut + radius, len(sizes) - 1)] - sizes[cut])
            lopsided = 3 * min(sizes[cut], len(points) - sizes[cut]) < len(points)
            if best is None or (lopsided, visitors) < best[0]:
                best = ((lopsided, visitors), vantage, cut, d)
            if tried == 1:
                break
        if tried == 1 and best:
            break
    return best and best[1:]


def grow(sample: np.ndarray, leaves: int, radius: int = RADIUS, seed: int = 1) -> tuple | None:
    """The upper tree: (vantage, cut, near, far), None for a shard. Leaves are dealt to the two sides by their sizes."""
    if leaves <= 1 or len(sample) < 8 or (s := split(sample, seed, radius, TRIED)) is None:
        return None
    vantage, cut, d = s
    near = min(leaves - 1, max(1, round(leaves * np.count_nonzero(d <= cut) / len(d))))
    return int(vantage), cut, grow(sample[d <= cut], near, radius, 2 * seed), grow(sample[d > cut], leaves - near, radius, 2 * seed + 1)


def shards_for(count: int) -> int:
    return max(min(-(-count // SHARD), MANY), -(-count // LARGEST), 1)


def copies_per_point(tree: tuple | None, points: np.ndarray, radius: int = RADIUS) -> float:
    """In how many shards a fingerprint is, home and visits, on average."""
    return sum(len(home) + len(visit) for _, home, visit in route(tree, points, radius)) / max(1, len(points))


def route(tree: tuple | None, points: np.ndarray, radius: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(shard, indices of its home points, indices of its visitors)."""

    def down(node, home: np.ndarray, visit: np.ndarray, name: int):
        if node is None:
            yield name, home, visit
            return
        vantage, cut, near, far = node
        dh, dv = (np.bitwise_count(points[i] ^ np.uint64(vantage)).astype("int16") for i in (home, visit))
        #: Points within ``radius`` of a near point are at most cut + radius away, of a far point at least cut + 1 - radius.
        #: Two home points on either side meet once, on the near side.
        yield from down(near, home[dh <= cut], np.concatenate([home[(dh > cut) & (dh <= cut + radius)], visit[dv <= cut + radius]]), 2 * name)
        yield from down(far, home[dh > cut], visit[dv > cut - radius], 2 * name + 1)

    yield from down(tree, np.arange(len(points)), np.zeros(0, "int64"), 1)


class Links:
    """Roots of linked points, smallest first."""

    def __init__(self, n: int):
        self.root = np.arange(n)

    def join(self, a: np.ndarray, b: np.ndarray) -> None:
        root = self.root
        while True:
            x, y = root[a], root[b]
            apart = x != y
            if not apart.any():
                return
            x, y, a, b = x[apart], y[apart], a[apart], b[apart]
            np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
            while True:
                up = root[root]
                if (up == root).all():
                    break
                root[:] = up


def link_within(points: np.ndarray, home: np.ndarray, visit: np.ndarray, radius: int, links: Links, seed: int = 1) -> None:
    """Join every home point with every home point or visitor within ``radius``."""
    if not len(home) or len(home) + len(visit) < 2:
        return
    s = split(points[home], seed, radius) if len(home) > LEAF else None
    if s is None:
        both = np.concatenate([home, visit])
        step = max(1, (1 << 22) // len(home))
        for at in range(0, len(both), step):
            some = both[at : at + step]
            i, j = np.nonzero(np.bitwise_count(points[some][:, None] ^ points[home][None, :]) <= radius)
            links.join(some[i], home[j])
        return
    vantage, cut, dh = s
    dh = dh.astype("int16")
    dv = np.bitwise_count(points[visit] ^ vantage).astype("int16")
    #: A pair of two home points on either side of the cut meets once, on the near side.
    link_within(points, home[dh <= cut], np.concatenate([home[(dh > cut) & (dh <= cut + radius)], visit[dv <= cut + radius]]), radius, links, 2 * seed)
    link_within(points, home[dh > cut], visit[dv > cut - radius], radius, links, 2 * seed + 1)


def link_shard(radius: int):
    def work(shard: pa.Table) -> pa.Table:
        points = shard.column("fp").to_numpy().view("uint64")
        home = np.flatnonzero(shard.column("home").to_numpy(zero_copy_only=False))
        visit = np.setdiff1d(np.arange(len(points)), home)
        links = Links(len(points))
        link_within(points, home, visit, radius, links)
        moved = np.flatnonzero(links.root != np.arange(len(points)))
        return pa.table({"a": points[moved].view("int64"), "b": points[links.root[moved]].view("int64")})

    return work


def link_fingerprints(distinct: DataFrame, count: int, radius: int = RADIUS) -> DataFrame:
    """(node, root) of the linked fingerprints of a table with distinct fp; those without a link are absent."""
    leaves = shards_for(count)
    chosen = distinct.orderBy(F.xxhash64("fp"), "fp").limit(max(SAMPLE, PER_SHARD * leaves)).select("fp")  # a part in 10,000 or less once there are many
    tree = grow(chosen.toArrow().column("fp").to_numpy().view("uint64"), leaves, radius)

    def work(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        points = batch.column("fp").to_numpy().view("uint64")
        for name, home, visit in route(tree, points, radius):
            at = np.concatenate([home, visit])
            if len(at):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), name, "int64")), pa.array(points[at].view("int64")), pa.array(np.arange(len(at)) < len(home))], ["shard", "fp", "home"])

    routed = map_batches(distinct.select("fp"), work, "shard long, fp long, home boolean")
    return connected_components(routed.groupBy("shard").applyInArrow(link_shard(radius), "a long, b long"))


def near_duplicates(docs: DataFrame, radius: int = RADIUS) -> DataFrame:
    """doc_id, fingerprint (hex), component_id, and component_size in documents: one row a document."""
    rows = stage(fingerprints(docs), "fingerprints")
    distinct = stage(rows.groupBy("fp").agg(F.min("doc_id").alias("first_id"), F.count("*").alias("copies")), "distinct")
    n = distinct.agg(F.count("*").alias("n"), F.coalesce(F.sum("copies"), F.lit(0)).alias("rows")).first()
    links = link_fingerprints(distinct, n.n, radius)
    rooted = distinct.join(links, distinct.fp == links.node, "left").select("fp", "first_id", "copies", F.coalesce("root", "fp").alias("root"))
    rooted = stage(rooted, "rooted")
    ids = rooted.groupBy("root").agg(F.min("first_id").alias("component_id"), F.sum("copies").alias("component_size"), F.count("*").alias("members"))
    groups = attach_groups(rooted.select("fp", "copies", "root"), ids, "root", "members", n.n)
    out = attach_groups(rows, groups.select("fp", "copies", "component_id", "component_size"), "fp", "copies", n.rows)
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id", "component_size")


def keep_one_of_near(docs: DataFrame, radius: int = RADIUS) -> DataFrame:
    """The documents whose id is that of their component, all columns unchanged. Rows without an id cannot be named and stay."""
    stay = near_duplicates(docs, radius).where("doc_id = component_id").select("doc_id").distinct()
    named = docs.where(F.col("doc_id").isNotNull()).join(stay, "doc_id", "left_semi")
    return named.select(*docs.columns).unionByName(docs.where(F.col("doc_id").isNull()))
