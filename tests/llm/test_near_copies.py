"""The near-duplicate stage against brute force over all pairs."""

import random
from collections import Counter

import corpus_pipeline
import numpy as np
import pytest
from test_operators import empty, fold, some_docs

from pathlore.llm import exact_dedup, near_copies
from pathlore.llm.common import stage

WHITE = " \t\n\r\x0b\x0c"


def brute_shingles(t):
    words = fold(t or "")
    for c in WHITE:
        words = words.replace(c, " ")
    words = [w for w in words.split(" ") if w]
    return {" ".join(words[i : i + 5]) for i in range(max(1, len(words) - 4))}


def brute_components(texts):
    """The component of each text by all pairs with Jaccard 0.8 or more, and the number of such pairs."""
    sets, root, pairs = [brute_shingles(t) for t in texts], list(range(len(texts))), 0

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, a in enumerate(sets):
        for j in range(i):
            b = sets[j]
            if 5 * min(len(a), len(b)) >= 4 * max(len(a), len(b)) and 5 * len(a & b) >= 4 * len(a | b):
                pairs += 1
                root[find(i)] = find(j)
    return [find(i) for i in range(len(texts))], pairs


def stage_of(spark, docs):
    return dict(corpus_pipeline.STAGES)["simhash_near_dedup"](spark, docs, None)


def edited(rng, words, edits):
    words = list(words)
    for _ in range(edits):
        words[rng.randrange(len(words))] = f"edit{rng.randrange(10**6)}"
    return " ".join(words)


def test_sets_equal_brute_force():
    rng = random.Random(3)
    base = [f"w{i}" for i in range(120)]
    texts = [edited(rng, base, rng.randint(0, 4)) for _ in range(80)] + ["", None, " ", "a b", "A  b", "a b c d e", *[f"x{i} " * 9 for i in range(5)]]
    want, _ = brute_components(texts)
    got = near_copies.components([near_copies.shingles(t) for t in texts]).tolist()
    assert len(set(zip(want, got, strict=True))) == len(set(want)) == len(set(got))


@pytest.mark.parametrize("sf", ["sf0.001", "sf0.01"])
def test_documents_equal_brute_force(spark, sf):
    docs = exact_dedup.keep_first_of_equal(spark.read.parquet(f"/root/testdata/{sf}/documents.parquet"))
    docs = stage(docs, "deduplicated")
    rows = docs.collect()
    root, pairs = brute_components([r.text for r in rows])
    best = {}
    for r, c in zip(rows, root, strict=True):
        best[c] = min(r.doc_id, best.get(c, r.doc_id))
    got = stage_of(spark, docs)
    assert got.columns == docs.columns and sorted(r.doc_id for r in got.collect()) == sorted(best.values())
    assert sf != "sf0.01" or pairs


@pytest.mark.parametrize("block", [4000, 40, 3])
def test_edges_and_large_groups(spark, monkeypatch, block):
    monkeypatch.setattr(near_copies, "BLOCK_ROWS", block)
    docs, rows = some_docs(spark)
    rng = random.Random(5)
    base = [f"w{i}" for i in range(200)]
    rows = rows + [(1000 + i, edited(rng, base, i % 5)) for i in range(150)]
    docs = docs.unionByName(spark.createDataFrame([(*r, "en", "s", 1, "d", 2, "k", 0.5, "z", "k", "b") for r in rows[-150:]], docs.schema))
    got = stage_of(spark, docs)
    assert got.columns == docs.columns
    best = {}
    root, _ = brute_components([t for _, t in rows])
    for (i, t), c in zip(rows, root, strict=True):
        best.setdefault(c, []).append((i is None, i or 0))
    assert Counter((r.doc_id is None, r.doc_id or 0) for r in got.collect()) == Counter(min(x) for x in best.values())
    assert stage_of(spark, empty(spark)).count() == 0


def test_bands_find_pairs_at_the_threshold():
    rng = np.random.default_rng(1)
    for _ in range(300):
        common, a, b = np.split(np.unique(rng.integers(0, 1 << 63, 100, "uint64")), [80, 90])
        assert (near_copies.bands(np.union1d(common, a)) == near_copies.bands(np.union1d(common, b))).any()


def test_chains_across_blocks(spark, monkeypatch):
    """Rows that are alike to their neighbours only, and others near them: components that no single block shows."""
    monkeypatch.setattr(near_copies, "BLOCK_ROWS", 5)
    rng = random.Random(2)
    words, rows = [f"w{i}" for i in range(150)], []
    for i in range(60):
        words[(7 * i) % 150] = f"step{i}"
        words[(7 * i + 75) % 150] = f"turn{i}"
        rows.append((i, " ".join(words)))
    rows += [(100 + i, edited(rng, [f"w{k}" for k in range(150)], 12 + i % 9)) for i in range(30)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    root, _ = brute_components([t for _, t in rows])
    best = {}
    for (i, _), c in zip(rows, root, strict=True):
        best[c] = min(i, best.get(c, i))
    assert 2 < len(best) < 60
    assert sorted(r.doc_id for r in stage_of(spark, docs).collect()) == sorted(best.values())


def test_the_fingerprint_tree_makes_candidates_of_its_own(spark, monkeypatch):
    """With the min-hash bands off, close copies still go: by fingerprints within the radius and the exact comparison."""
    rng = random.Random(3)
    words = [f"w{rng.randrange(10_000)}" for _ in range(900)]
    near, far = [*words[:-1], "other"], [f"v{rng.randrange(10_000)}" for _ in range(900)]
    monkeypatch.setattr(near_copies, "sketches", lambda docs, own=near_copies.sketches: own(docs).withColumn("bands", near_copies.F.array().cast("array<long>")))
    docs = spark.createDataFrame([(1, " ".join(words)), (2, " ".join(near)), (3, " ".join(far))], "doc_id long, text string")
    assert sorted(r.doc_id for r in near_copies.keep_one_of_alike(docs).collect()) == [1, 3]
