"""Near copies by the similarity of word shingles: of each component of documents that are alike enough one row stays.

Two texts are linked when the sets of their five-word shingles have a Jaccard similarity of 0.8 or more. Candidates are
first the texts whose SimHash fingerprints of these shingles differ in RADIUS bits or fewer, found by the vantage-point
tree of ``simhash``. Fingerprints of two texts at 0.8 differ in about ten of 64 bits, and a radius that finds them all leaves
a tree nothing to rule out, so min-hashes complete the candidates beyond the tree's radius: BANDS bands of ROWS each; a pair at
0.8 shares no band with a probability of 1.3e-7, a closer pair with a smaller one. Rows that share a band are joined
to the band's first row, linked fingerprints to their set's first, never all to one another, and the clusters of these edges are
found by distributed connected components. Within a cluster every pair whose sizes allow it is compared exactly unless
both are in one component by then. No task holds more than two blocks of BLOCK_ROWS rows: a larger cluster is first resolved block by block, then its
components' first rows are, and at last all rows outside the largest component meet the blocks of that component and one
another. So a large group of near copies costs in proportion to its size.

Lower-casing is A-Z only; words are runs without ASCII white space. A text with fewer words than a shingle has one
shingle, all of them; texts without words and null texts are alike. Of a component the row with the smallest doc_id
stays, then that with the smallest key (a digest of id and text); null ids lose to any other. Exactly one row a
component stays, also of repeated rows and of different texts under one id. An empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pathlore.llm import simhash
from pathlore.llm.common import attach_groups, connected_components, map_batches, stage, text_or_empty

WORDS_IN_SHINGLE, SEED = 5, 42
#: Differing bits up to which fingerprints make candidates.
RADIUS = 4
#: Least similarity, as a fraction.
PART, WHOLE = 4, 5
BANDS, ROWS = 40, 5
_RANDOM = np.random.default_rng(SEED)
_FLIPS = _RANDOM.integers(0, 1 << 32, (BANDS * ROWS, 1), "uint32")
_FACTORS = _RANDOM.integers(0, 1 << 32, (BANDS * ROWS, 1), "uint32") | np.uint32(1)
#: Shingles that are min-hashed at once; rows of a block of a cluster.
CHUNK, BLOCK_ROWS = 2048, 4000


def shingles(text: str | None) -> np.ndarray:
    """The sorted distinct XXH64 hashes of a text's word shingles."""
    words = (text or "").encode("utf-8", "replace").lower().split()
    joined = b" ".join(words)
    if len(words) <= WORDS_IN_SHINGLE:
        return np.array([xxhash.xxh64_intdigest(joined, SEED)], "uint64")
    lens = np.fromiter(map(len, words), "int64", len(words))
    ends = np.cumsum(lens + 1) - 1
    starts = (ends - lens)[: len(words) - WORDS_IN_SHINGLE + 1].tolist()
    digest = xxhash.xxh64_intdigest
    return np.unique(np.fromiter([digest(joined[a:b], SEED) for a, b in zip(starts, ends[WORDS_IN_SHINGLE - 1 :].tolist(), strict=True)], "uint64", len(starts)))


def bands(hashes: np.ndarray) -> np.ndarray:
    """A key for each band of the set's min-hashes."""
    short, least = (hashes >> np.uint64(32)).astype("uint32"), None
    for at in range(0, len(short), CHUNK):
        some = ((short[None, at : at + CHUNK] ^ _FLIPS) * _FACTORS).min(axis=1)
        least = some if least is None else np.minimum(least, some)
    key = np.arange(1, BANDS + 1, dtype="uint64")
    for column in least.reshape(BANDS, ROWS).T.astype("uint64"):
        key = (key ^ column) * np.uint64(0x9E3779B97F4A7C15)
        key ^= key >> np.uint64(29)
    return key.view("int64")


def components(sets: list[np.ndarray]) -> np.ndarray:
    """The component of each set, exactly: each one found is compared with all that are still outside, within the sizes that can be alike."""
    label = np.full(len(sets), -1)
    sizes = np.array([len(s) for s in sets])
    left = np.argsort(sizes, kind="stable")
    codes = np.unique(np.concatenate(sets), return_inverse=True)[1].astype("int32")
    begin = np.cumsum(sizes) - sizes
    codes_of = lambda i: codes[begin[i] : begin[i] + sizes[i]]
    flat, mine = np.concatenate([codes_of(i) for i in left]), np.zeros(int(codes.max()) + 1, bool)
    while len(left):
        label[left[0]], queue = left[0], [left[0]]
        flat, left = flat[sizes[left[0]] :], left[1:]
        while queue and len(left):
            one = queue.pop()
            n, of = sizes[one], sizes[left]
            lo, hi = np.searchsorted(of, -(-n * PART // WHOLE)), np.searchsorted(of, n * WHOLE // PART, "right")
            if lo == hi:
                continue
            at = np.cumsum(of) - of
            mine[codes_of(one)] = True
            end = at[hi - 1] + of[hi - 1]
            both = np.add.reduceat(mine[flat[at[lo] : end]], at[lo:hi] - at[lo], dtype="int64")
            mine[codes_of(one)] = False
            alike = np.zeros(len(left), bool)
            alike[lo:hi] = both * (PART + WHOLE) >= PART * (n + of[lo:hi])
            if alike.any():
                label[left[alike]] = label[one]
                queue += left[alike].tolist()
                flat, left = flat[np.repeat(~alike, of)], left[~alike]
    return label


def row_key() -> Column:
    """A digest of id and text: rows that have it in common are copies of one another."""
    return F.unhex(F.sha2(F.concat(F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.lit(":"), text_or_empty()).cast("binary"), 256))


def sketches(docs: DataFrame) -> DataFrame:
    """near_key, the fingerprint of its shingles, and the keys of its bands."""

    def work(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        sets = [shingles(t.as_py()) for t in batch.column("text")]
        fps = np.fromiter(map(simhash.bits_over_half, sets), "uint64", len(sets))
        keys = np.concatenate([bands(s) for s in sets])
        lists = pa.ListArray.from_arrays(pa.array(np.arange(0, len(keys) + 1, BANDS, dtype="int32")), pa.array(keys))
        yield pa.RecordBatch.from_arrays([batch.column("near_key"), pa.array(fps.view("int64")), lists], ["near_key", "fp", "bands"])

    return map_batches(docs.select(row_key().alias("near_key"), "text"), work, "near_key binary, fp long, bands array<long>")


def resolve(rows: pa.Table) -> pa.Table:
    """node and root of rows of a cluster: the least node that a chain of similar rows among these leads to."""
    nodes = rows.column("node").to_numpy()
    found = components([shingles(t.as_py()) for t in rows.column("text")])
    least = np.full(len(nodes), np.iinfo("int64").max)
    np.minimum.at(least, found, nodes)
    return pa.table({"node": nodes, "root": least[found]})


def fingerprint_edges(rows: DataFrame, count: int, radius: int = RADIUS) -> DataFrame:
    """(a, b): each row and the first of the rows whose fingerprints a chain within the radius joins to its own."""
    distinct = stage(rows.groupBy("fp").agg(F.min("node").alias("first"), F.count("*").alias("copies")), "fingerprints")
    linked = simhash.link_fingerprints(distinct, distinct.count(), radius)
    heads = distinct.join(linked, distinct.fp == linked.node, "left").select("fp", "first", "copies", F.coalesce("root", "fp").alias("root"))
    of_root = distinct.select(F.col("fp").alias("root"), F.col("first").alias("head"))
    heads = stage(heads.join(of_root, "root").select("fp", "first", "copies", "head"), "heads")
    own = attach_groups(rows.select("node", "fp"), heads.where("copies > 1").select("fp", "first", "copies"), "fp", "copies", count)
    between = heads.where("first <> head").select(F.col("first").alias("a"), F.col("head").alias("b"))
    return own.where("node <> first").select(F.col("node").alias("a"), F.col("first").alias("b")).unionByName(between)


def clusters(docs: DataFrame) -> DataFrame:
    """near_key, node (a number) and cluster of the rows that are candidates with another; copies of a row have one node."""
    rows = stage(sketches(docs).withColumn("node", F.monotonically_increasing_id()), "sketches")
    banded = rows.select("node", F.explode("bands").alias("band"))
    firsts = stage(banded.groupBy("band").agg(F.min("node").alias("first"), F.count("*").alias("members")).where("members > 1"), "bands")
    n = rows.count()
    alike = fingerprint_edges(rows, n)
    edges = attach_groups(banded, firsts, "band", "members", n * BANDS).where("node <> first")
    links = connected_components(alike.unionByName(edges.select(F.col("node").alias("a"), F.col("first").alias("b"))))
    return rows.select("near_key", "node").join(links, "node").groupBy("near_key").agg(F.min("node").alias("node"), F.min("root").alias("cluster"))


def in_blocks(rows: DataFrame, size: str, name: str) -> DataFrame:
    """With the number of blocks that ``size`` rows make, and the block of each."""
    number = F.ceil(F.col(size) / BLOCK_ROWS).cast("int")
    return rows.withColumn(f"{name}s", number).withColumn(name, F.pmod(F.xxhash64("node"), F.greatest(number, F.lit(1))).cast("int"))


def with_size(rows: DataFrame, key: str, name: str) -> DataFrame:
    """With the number of rows that have the same key."""
    return attach_groups(rows, rows.groupBy(key).agg(F.count("*").alias(name)), key, name, rows.count())


def resolve_large(members: DataFrame, first: DataFrame) -> DataFrame:
    """node and root of the rows of clusters of several blocks; ``first``: their roots within their blocks."""
    links, heads = [first], first
    while True:  # the first rows of the components found so far, until these no longer become fewer
        at = stage(members.join(heads.where("node = root").select("node"), "node", "left_semi"), "heads")
        n = at.count()
        heads = stage(in_blocks(with_size(at.drop("size", "block", "blocks"), "cluster", "size"), "size", "block").groupBy("cluster", "block").applyInArrow(resolve, "node long, root long"), "roots")
        links.append(heads)
        if heads.where("node = root").count() > 0.9 * n:
            break
    edges = lambda parts: reduce(DataFrame.unionByName, parts).where("node <> root").select(F.col("node").alias("a"), F.col("root").alias("b"))
    so_far = connected_components(edges(links))
    grouped = stage(members.select("node", "cluster", "text").join(so_far, "node", "left").withColumn("root", F.coalesce("root", "node")), "grouped")
    sizes = grouped.groupBy("cluster", "root").agg(F.count("*").alias("n"))
    main = stage(sizes.groupBy("cluster").agg(F.max(F.struct("n", F.col("root").alias("main"))).alias("m"), F.sum("n").alias("size")).select("cluster", "m.main", F.col("m.n").alias("n_main"), (F.col("size") - F.col("m.n")).alias("n_rest"), "size"), "main")
    rows = attach_groups(grouped, main, "cluster", "size", grouped.count()).where("n_rest > 0")
    rows = in_blocks(in_blocks(rows, "n_main", "m"), "n_rest", "r")
    is_main = F.col("root") == F.col("main")
    pair = lambda kind, x, y: F.struct(F.lit(kind).alias("kind"), x.alias("x"), y.alias("y"))
    others = lambda n: F.sequence(F.lit(0), F.col(n) - 1)
    meets = F.when(is_main, F.transform(others("rs"), lambda r: pair("main", F.col("m"), r))).otherwise(
        F.concat(F.transform(others("ms"), lambda m: pair("main", m, F.col("r"))), F.transform(others("rs"), lambda r: pair("rest", F.least(F.col("r"), r), F.greatest(F.col("r"), r))))
    )
    met = rows.select("cluster", "node", "text", F.explode(meets).alias("meets")).select("cluster", "node", "text", "meets.*")
    links.append(stage(met.groupBy("cluster", "kind", "x", "y").applyInArrow(resolve, "node long, root long"), "roots"))
    return members.select("node").join(connected_components(edges(links)), "node", "left").withColumn("root", F.coalesce("root", "node"))


def keep_one_of_alike(docs: DataFrame) -> DataFrame:
    """One row of each component of texts that are alike, all columns unchanged."""
    found = stage(clusters(docs), "clusters")
    found = in_blocks(with_size(found, "cluster", "size"), "size", "block")
    keyed = docs.withColumn("near_key", row_key())
    members = stage(keyed.select("near_key", "doc_id", "text").join(found, "near_key").dropDuplicates(["near_key"]), "members")
    roots = stage(members.groupBy("cluster", "block").applyInArrow(resolve, "node long, root long"), "roots")
    large = members.where("blocks > 1")
    if not large.isEmpty():
        own = roots.join(large.select("node"), "node", "left_semi")
        roots = stage(roots.join(large.select("node"), "node", "left_anti").unionByName(resolve_large(large, own)), "roots")
    ranked = members.select("near_key", "node", F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "near_key").alias("rank")).join(roots, "node")
    best = ranked.groupBy("root").agg(F.min("rank").alias("best"), F.count("*").alias("n"))
    gone = attach_groups(ranked, best, "root", "n", members.count()).where("best.near_key <> near_key").select("near_key")
    stay = keyed.join(gone, "near_key", "left_anti")
    again = Window.partitionBy("near_key").orderBy("near_key")
    return stay.withColumn("near_copy", F.row_number().over(again)).where("near_copy = 1").select(*docs.columns)
