"""The pipeline against brute force, stage by stage."""

import hashlib
import re
from collections import Counter

import corpus_pipeline
import duckdb
import numpy as np
from test_operators import WORD_BPE, check_pieces, fold

from pathlore.llm import toxicity
from pathlore.llm.common import stage

SF = "/root/testdata/sf0.01"


def removed(rows):
    """Text without the characters wholly covered by a 50-byte string that a smaller id has too."""
    least = {}
    for i, t in rows:
        b = t.encode()
        for k in range(len(b) - 49):
            w = b[k : k + 50]
            least[w] = min(i, least.get(w, i))
    out = {}
    for i, t in rows:
        b = t.encode()
        gone = np.zeros(len(b), bool)
        for k in range(len(b) - 49):
            if least[b[k : k + 50]] < i:
                gone[k : k + 50] = True
        at, kept = 0, []
        for c in t:
            n = len(c.encode())
            if not gone[at : at + n].all():
                kept.append(c)
            at += n
        out[i] = "".join(kept)
    return out


def shingles(t):
    words = re.findall(r"[^\x20\x09-\x0D]+", fold(t))
    return {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))}


def least_of_alike(rows):
    """The smallest id of each component of texts whose sets of five-word shingles have a similarity of 0.8 or more."""
    root = {i: i for i, _ in rows}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    sets = sorted(((len(s), i, s) for i, s in ((i, shingles(t)) for i, t in rows)), key=lambda x: x[:2])
    for k, (n, i, a) in enumerate(sets):
        for m, j, b in sets[k + 1 :]:
            if 4 * m > 5 * n:
                break
            both = len(a & b)
            if 5 * both >= 4 * (n + m - both):
                x, y = sorted((find(i), find(j)))
                root[y] = x
    return {find(i) for i in root}


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    before = docs
    columns = docs.columns
    for name, work in corpus_pipeline.STAGES[:-1]:
        after = stage(work(spark, before, SF), name)
        assert after.columns == columns
        a, b = {r.doc_id: r for r in before.collect()}, {r.doc_id: r for r in after.collect()}
        if name == "toxicity":
            model = toxicity.train(before, spark.read.parquet(f"{SF}/labels.parquet"))
            assert set(b) == {i for i, r in a.items() if model.score(r.text)[0] < corpus_pipeline.TOXIC}
            labels = duckdb.sql(f"SELECT doc_id, toxic FROM '{SF}/labels.parquet'").fetchall()
            clean = [i for i, t in labels if not t]
            assert sum(i in b for i in clean) >= 0.99 * len(clean)
        elif name == "exact_dedup":
            best = {}
            for i, r in a.items():
                h = hashlib.sha256(fold(r.text).encode()).digest()
                best[h] = max(i, best.get(h, i))
            assert set(b) == set(best.values())
        elif name == "simhash_near_dedup":
            assert set(b) == least_of_alike([(i, r.text) for i, r in a.items()])
        else:
            want = removed([(i, r.text) for i, r in a.items()])
            assert {i: r.text for i, r in b.items()} == want and all(r.n_chars == len(r.text) for r in b.values())
        before = after
    pieces = corpus_pipeline.STAGES[-1][1](spark, before, SF).collect()
    check_pieces(pieces, [(r.doc_id, r.text) for r in before.collect()])
    assert Counter(map(tuple, corpus_pipeline.run(spark, SF).collect())) == Counter(map(tuple, pieces))
    assert WORD_BPE and corpus_pipeline.ORACLE_SQL is None
