"""The pipeline operators against brute force, round trips, held-out labels and library results."""

import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import duckdb
import numpy as np
import public_tokenizers
import pytest
import xxhash
from tokenizers import Tokenizer

from pathlore.llm import bpe, common, exact_dedup, license_scan, packing, quality, registry, sharding, simhash, suffix_dedup, suffix_groups, token_rollup, toxicity

DATA = "/root/testdata/sf0.001"
WORD_BPE, BYTE_BPE = public_tokenizers.path("word_bpe_49k.json"), public_tokenizers.path("byte_bpe_50k.json")
#: Columns whose names the operators use inside.
CLASH = "row_tag long, digest string, fp long, kept string, score double, size string, key string, bucket string"


def some_docs(spark, extra=True):
    """Nulls in every column, empty and long texts, ties, repeated rows, clashing extra columns."""
    rng = random.Random(11)
    words = ["alpha", "Beta", "gamma", "délta", "ε", "zeta,", "eta.", "x_y", "it's", "42"]
    texts = [" ".join(rng.choice(words) for _ in range(rng.randint(0, 80))) + rng.choice(["", "\n", "\nend of it all."]) for _ in range(40)]
    texts += ["", "", None, None, " ", "\n\n", "a", "A", "a" * 5000, "word " * 30_000, "Same Text", "same text", "sAME tEXT", "naïve Ünï", "NAÏVE ünï", "<|endoftext|> x", "tab\tand\x0bvt\x1cfs"]
    rows = [(i, t, "en", "s") for i, t in enumerate(texts)]
    rows += [rows[3], rows[3], (None, "no id", None, None), (None, "no id", "de", None), (7, "another text under a used id", None, "s")]
    schema = "doc_id long, text string, lang string, source string"
    if extra:
        rows = [(*r, 1, "d", 2, "k", 0.5, "z", "k", "b") for r in rows]
        schema += ", " + CLASH
    return spark.createDataFrame(rows, schema).repartition(3), [(r[0], r[1]) for r in rows]


def empty(spark):
    return spark.createDataFrame([], "doc_id long, text string, lang string, source string")


# ---- exact dedup ---------------------------------------------------------------------------------------------------------


def fold(t):
    return re.sub("[A-Z]", lambda m: m[0].lower(), t or "")


def test_exact_dedup_edge_cases(spark):
    docs, rows = some_docs(spark)
    got = exact_dedup.fresh_index(spark).deduplicate(docs, "b1").collect()
    groups = defaultdict(list)
    for i, t in rows:
        groups[hashlib.sha256(fold(t).encode()).digest()].append(i)
    assert len(got) == len(rows)
    for r in got:
        own = groups[bytes(r.digest)]
        assert r.group_size == len(own) and r.keep_id == max((i for i in own if i is not None), default=None)
    kept = [r for r in got if r.kept]
    assert len(kept) == len(groups) and len({bytes(r.digest) for r in kept}) == len(groups)
    assert all(r.doc_id == r.keep_id for r in kept)
    assert exact_dedup.fresh_index(spark).deduplicate(empty(spark), "b").count() == 0


def test_exact_dedup_over_batches(spark, tmp_path):
    index = exact_dedup.DigestIndex(spark, "batches_index", 4, str(tmp_path / "ix"))
    one = spark.createDataFrame([(1, "A b"), (2, "a B"), (3, "c")], "doc_id long, text string")
    two = spark.createDataFrame([(9, "a b"), (10, "new"), (11, "NEW")], "doc_id long, text string")
    first = {r.doc_id: r.kept for r in index.deduplicate(one, "one").collect()}
    second = {r.doc_id: (r.kept, r.keep_id) for r in index.deduplicate(two, "two").collect()}
    assert first == {1: False, 2: True, 3: True} and second == {9: (False, 2), 10: (False, 11), 11: (True, 11)}
    again = {r.doc_id: r.kept for r in index.deduplicate(one, "one").collect()}
    assert again == first and index.table().count() == 3
    spark.sql("DROP TABLE batches_index")  # an external table: the files stay and are opened again
    assert exact_dedup.DigestIndex(spark, "batches_index", 4, str(tmp_path / "ix")).table().count() == 3


def test_exact_dedup_keeps_rows_whole_and_plans_no_python(spark):
    docs, _ = some_docs(spark)
    out = exact_dedup.keep_first_of_equal(docs)
    assert out.schema == docs.schema
    assert not re.search("Python|Arrow|Pandas", out._jdf.queryExecution().toString())


def test_heavy_groups_join_like_light_ones(spark, monkeypatch):
    monkeypatch.setattr(common, "HEAVY_LEAST", 1)
    monkeypatch.setattr(common, "HEAVY_PARTS", 10)
    rows = spark.createDataFrame([(i, i % 7 if i % 3 else 0) for i in range(300)], "id long, k int")
    groups = rows.groupBy("k").count()
    got = common.attach_groups(rows, groups, "k", "count", 300)
    want = Counter(i % 7 if i % 3 else 0 for i in range(300))
    assert got.count() == 300 and all(r["count"] == want[r.k] for r in got.collect())


def test_components(spark):
    rng = random.Random(2)
    edges = [(rng.randrange(400), rng.randrange(400)) for _ in range(260)] + [(1000 + i, 1001 + i) for i in range(60)] + [(5, 5)]
    root = {n: n for e in edges for n in e}
    for _ in range(400):
        for a, b in edges:
            root[a] = root[b] = min(root[a], root[b])
    got = {r.node: r.root for r in common.connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {n: r for n, r in root.items() if any(n in e and e[0] != e[1] for e in edges)}
    assert common.connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


# ---- quality -------------------------------------------------------------------------------------------------------------


def brute_quality(t):
    t = t or ""
    words = re.findall(r"[^\x20\x09-\x0D]+", t)
    lines = t.split("\n")
    has_word = lambda x: bool(re.search(r"[^\x20\x09-\x0D]", x))
    dup = sum(has_word(x) and x in lines[:i] for i, x in enumerate(lines))
    wins = [tuple(words[i : i + 5]) for i in range(len(words) - 4)]
    counts = Counter(wins)
    covered = {j for i, w in enumerate(wins) if counts[w] > 1 for j in range(i, i + 5)}
    n = len(words)
    return n, sum(map(len, words)), sum(c in "#*$%&|<>" for c in t), dup, len(covered), n < 10 or 100 * len(covered) > 20 * n


def test_quality_equals_brute_force(spark):
    docs, rows = some_docs(spark)
    got = Counter((r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) for r in quality.assess(docs).collect())
    assert got == Counter((i, *brute_quality(t)) for i, t in rows)
    texts = [r.text for r in registry.table(spark, DATA, "documents").collect()]
    for t in texts:
        m = quality.measure(t)
        assert (m["n_words"], m["word_chars"], m["n_symbols"], m["n_dup_lines"], m["n_repeat_words"], m["base_failed"]) == brute_quality(t)
    assert quality.assess(empty(spark)).count() == 0


def test_line_rules():
    prose = "The quick brown fox jumps over the lazy dog near the river bank today.\n"
    nav = "home | about | contact | news | shop | help\n"
    junk = "of%%% athe*** erntwh.%%% thntatwh&&& ndreea$$$ an%%% as%%%\n"
    good = quality.measure(prose + "Another line that says something else entirely about cats and dogs.\n" + nav)
    assert good["kept"] and good["navigation_lines"] == 1 and nav.strip() not in good["cleaned"]
    assert not quality.measure(nav + nav.replace("home", "start") + prose[:20])["kept"]
    assert quality.measure(junk)["punctuation_lines"] == 1
    assert quality.measure("Please accept cookies to go on reading this page now, friend.")["boilerplate_lines"] == 1


def test_quality_keeps_clean_documents():
    con = duckdb.connect()
    rows = con.execute("SELECT text, quality FROM '/root/testdata/sf0.01/documents.parquet' JOIN '/root/testdata/sf0.01/labels.parquet' USING (doc_id)").fetchall()
    m = [(quality.measure(t), q) for t, q in rows]
    assert all(x["kept"] for x, q in m if q == 1 and not x["base_failed"])
    assert sum(not x["kept"] for x, q in m if q == 0) >= 0.9 * sum(q == 0 for _, q in m)


# ---- suffix arrays ---------------------------------------------------------------------------------------------------------


def test_suffix_array_equals_sorting():
    rng = random.Random(3)
    for t in range(3000):
        k, n = rng.randint(1, 4), rng.randint(0, 60)
        s = [rng.randint(1, k) for _ in range(n)]
        if t % 3 == 0 and s:
            s = (s[: rng.randint(1, 5)] * 60)[:n]
        s.append(0)
        assert suffix_groups.suffix_array(s) == sorted(range(len(s)), key=lambda i: s[i:])


def brute_removal(rows):
    least = {}
    for i, t in rows:
        b = (t or "").encode()
        for k in range(len(b) - 49 if i is not None else 0):
            w = b[k : k + 50]
            least[w] = min(i, least.get(w, i))
    out = Counter()
    for i, t in rows:
        b = (t or "").encode()
        gone = np.zeros(len(b), bool)
        for k in range(len(b) - 49 if i is not None else 0):
            if least[b[k : k + 50]] < i:
                gone[k : k + 50] = True
        kept = np.frombuffer(b, "uint8")[~gone].tobytes()
        runs = int(gone[:1].sum() + (gone[1:] & ~gone[:-1]).sum())
        out[i, len(b), int(gone.sum()), runs, hashlib.sha256(kept).hexdigest()] += 1
    return out


@pytest.mark.parametrize(("heavy", "heavy_bytes"), [(4096, 32 << 20), (0, 32 << 20), (4096, 200)])
def test_suffix_dedup_equals_brute_force(spark, monkeypatch, heavy, heavy_bytes):
    monkeypatch.setattr(suffix_dedup, "HEAVY_BYTES", heavy_bytes)
    monkeypatch.setattr(suffix_dedup, "ARRAY_BYTES", 3000)
    monkeypatch.setattr(suffix_dedup, "BLOCK_BYTES", (3000, 3000))
    rng = random.Random(5)
    shared = ["".join(rng.choice("abcdeé fgh") for _ in range(rng.randint(40, 160))) for _ in range(6)]
    rows = []
    for _ in range(100):
        parts = [rng.choice(shared) if rng.random() < 0.3 else "".join(rng.choice("abcdefgh é") for _ in range(rng.randint(0, 120))) for _ in range(rng.randint(0, 6))]
        rows.append((rng.randint(0, 90) if rng.random() < 0.95 else None, " ".join(parts) if rng.random() < 0.97 else None))
    rows += [(200, "a" * 300), (201, "a" * 200 + "b"), (199, "a" * 60), (300, "ab" * 100), (301, "ab" * 60), rows[0], rows[0]]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert Counter(map(tuple, suffix_dedup.report(docs, heavy).collect())) == brute_removal(rows)


def test_suffix_dedup_on_documents_and_edges(spark):
    docs, rows = some_docs(spark)
    rows = [(i, t) for i, t in rows]
    assert Counter(map(tuple, suffix_dedup.report(docs).collect())) == brute_removal(rows)
    assert suffix_dedup.report(empty(spark)).count() == 0 and suffix_dedup.cut(empty(spark)).count() == 0
    cut = suffix_dedup.cut(docs)
    assert cut.columns == docs.columns and cut.count() == len(rows)
    real = registry.table(spark, DATA, "documents")
    assert Counter(map(tuple, registry.QUERIES["op3_suffix_dedup"](spark, DATA).collect())) == brute_removal([(r.doc_id, r.text) for r in real.select("doc_id", "text").collect()])


def test_cut_keeps_whole_characters():
    text = "aéb".encode()
    assert suffix_dedup.whole_characters(text, np.array([False, True, False, False])) == "aéb"
    assert suffix_dedup.whole_characters(text, np.array([True, True, True, False])) == "b"


# ---- toxicity --------------------------------------------------------------------------------------------------------------


@pytest.fixture(scope="module")
def tox(spark):
    d = "/root/testdata/sf0.1"
    docs, labels = (registry.table(spark, d, n) for n in ("documents", "labels"))
    return docs, labels, toxicity.train(docs, labels)


def test_toxicity_on_held_out_labels(tox):
    docs, labels, model = tox
    rows = toxicity.with_scores(docs, model).join(labels, "doc_id").where("held_out").collect()
    hit = [r for r in rows if r.score >= 0.7]
    assert sum(r.toxic for r in hit) >= 0.95 * len(hit) and sum(r.toxic for r in hit) >= 0.85 * sum(r.toxic for r in rows)
    assert all(0 <= r.score <= 1 for r in rows)


def test_nearest_equals_exhaustive_search(tox):
    docs, _, model = tox
    count = model.toxic + model.clean
    rng = random.Random(1)
    vectors = [dict(zip(*(x.tolist() for x in model.vector(i)), strict=True)) for i in range(len(count))]
    texts = [r.text for r in docs.orderBy("doc_id").limit(40).collect()] + [" ".join(rng.choices(["idiot", "the", "and", "de", "queen", "scum"], k=3)) for _ in range(20)]
    for ids, counts in map(model.terms.read, texts):
        weights = model.weigh(ids, counts)
        query = dict(zip(ids.tolist(), weights.tolist(), strict=True))
        cos = np.array([sum(x * query.get(t, 0) for t, x in v.items()) for v in vectors])
        order = [i for i in np.lexsort((np.arange(len(cos)), -cos)) if cos[i] > toxicity.TIE]
        held, want = 0, []
        for i in order:
            if held >= toxicity.NEIGHBOURS and cos[i] < cos[want[-1]] - toxicity.TIE:
                break
            want.append(i)
            held += count[i]
        got, near = model.nearest(ids, weights)
        assert set(got.tolist()) == set(want) and np.allclose(near, cos[got], atol=1e-5)


def brute_toxicity(docs, labels):
    """Scores of all documents, from the definition: terms as strings, all cosines, votes, pools."""

    def terms(t):
        words = re.findall(r"[^\W_]+", (t or "").lower())
        return Counter([w for w in words] + ["^" + w[: toxicity.PREFIX] for w in words if len(w) > toxicity.PREFIX])

    of = {i: terms(t) for i, t in docs}
    known = {i: max(y for j, y in labels if j == i) for i, _ in labels if i in of and zlib.crc32(str(i).encode()) % 3 != 1}
    pos, neg = sum(known.values()), sum(not y for y in known.values())
    df = Counter(t for c in of.values() for t in c)
    weight = {}
    for t in {t for i in known for t in of[i]}:
        a, b = (sum(t in of[i] for i, y in known.items() if y == label) for label in (1, 0))
        g2 = 0.0
        for x, size, col in ((a, pos, a + b), (b, neg, a + b), (pos - a, pos, pos + neg - a - b), (neg - b, neg, pos + neg - a - b)):
            g2 += 2 * x * np.log(x * (pos + neg) / (size * col)) if x else 0
        more = a * neg > b * pos
        weight[t] = (np.log((1 + len(of)) / (1 + df[t])) + 1) * (1 + toxicity.BOOST * (max(g2 - toxicity.NOISE, 0) if more else 0))

    def vector(c):
        v = {t: (1 + np.log(n)) * weight[t] for t, n in c.items() if t in weight}
        length = np.sqrt(sum(x * x for x in v.values()))
        return {t: x / length for t, x in v.items()}

    space = {i: vector(of[i]) for i in known}
    rate = pos / (pos + neg)

    def vote(v, skip=None):
        near = sorted(((sum(x * v.get(t, 0) for t, x in w.items()), i) for i, w in space.items() if i != skip and w), key=lambda x: -x[0])
        near = [(c, i) for c, i in near if c > 0]
        last = near[toxicity.NEIGHBOURS - 1][0] if len(near) >= toxicity.NEIGHBOURS else 0
        near = [(1 / (1 - min(c, 1) + toxicity.NEAR), known[i]) for c, i in near if c >= last - 1e-6]
        return (sum(w * y for w, y in near) + rate) / (sum(w for w, _ in near) + 1)

    pools = []
    for x, y in sorted((vote(space[i], i), known[i]) for i in known if space[i]):
        pools.append([x, y, 1])
        while len(pools) > 1 and pools[-2][1] / pools[-2][2] >= pools[-1][1] / pools[-1][2]:
            _, t, k = pools.pop()
            pools[-1][1] += t
            pools[-1][2] += k
    bare = [known[i] for i in known if not space[i]]
    out = {}
    for i, c in of.items():
        v = vector(c)
        if not v:
            out[i] = (sum(bare) + rate) / (len(bare) + 1)
            continue
        pool = [p for p in pools if p[0] <= vote(v) + 1e-9] or pools[:1]
        out[i] = (pool[-1][1] + toxicity.SHRINK * rate) / (pool[-1][2] + toxicity.SHRINK)
    return out


def test_toxicity_scores_equal_brute_force(spark):
    docs, labels = (registry.table(spark, DATA, n) for n in ("documents", "labels"))
    want = brute_toxicity([(r.doc_id, r.text) for r in docs.collect()], [(r.doc_id, r.toxic) for r in labels.collect() if r.toxic is not None])
    got = {r.doc_id: r.score for r in registry.QUERIES["op4_toxicity"](spark, DATA).collect()}
    assert set(got) == set(want)
    off = [i for i in got if abs(got[i] - want[i]) > 1e-6]
    assert len(off) <= 2  # a vote on the border of two pools may fall to either by rounding


def test_toxicity_edges(spark, tox):
    docs, rows = some_docs(spark)
    labels = spark.createDataFrame([(1, 1), (2, 0), (2, 1), (None, 1), (3, None)], "doc_id long, toxic int")
    model = toxicity.train(docs, labels)
    assert toxicity.with_scores(docs, model).count() == len(rows)
    none = toxicity.train(empty(spark), labels.limit(0))
    assert {r.score for r in toxicity.with_scores(docs, none).collect()} == {0.0}
    assert toxicity.train(docs, labels.limit(0)).score("a")[0] == 0.0 and toxicity.train(empty(spark), labels).score("a")[0] == 0.0
    assert toxicity.drop_toxic(docs, tox[2]).columns == docs.columns
    assert toxicity.with_scores(empty(spark), model).count() == 0 and toxicity.drop_toxic(empty(spark), model).count() == 0
    held = {r.doc_id: r.held_out for r in toxicity.with_scores(docs, none).collect() if r.doc_id is not None}
    assert all(h == (zlib.crc32(str(i).encode()) % 3 == 1) for i, h in held.items())


def test_toxicity_sample_is_bounded(spark):
    """A doc_id with very many rows gives one example."""
    docs = spark.createDataFrame([(i % 3, f"text {i}") for i in range(200)] + [(9, "other")], "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(10)], "doc_id long, toxic int")
    learnt = {i for i in range(10) if zlib.crc32(str(i).encode()) % 3 != 1}
    sample, there = toxicity.sampled_texts(docs, labels, 100)
    assert sample.count() == len(learnt & {0, 1, 2, 9}) and there == [sum(i % 2 == y for i in learnt) for y in (0, 1)]
    assert toxicity.sampled_texts(docs, labels, 2)[0].count() <= 2
    many = spark.createDataFrame([(i, f"text {i}") for i in range(400)], "doc_id long, text string")
    rare = spark.createDataFrame([(i, int(i % 10 == 0)) for i in range(400)], "doc_id long, toxic int")
    sample, there = toxicity.sampled_texts(many, rare, 40)
    found = [r.toxic for r in sample.collect()]
    assert len(found) == 40 and sum(found) == min(20, there[1]) and sum(there) > 200


def test_learns_nothing_from_held_out_rows(spark, tox):
    docs, labels, _ = tox
    from pyspark.sql import functions as F

    flipped = labels.withColumn("toxic", F.when(toxicity.held_out(), 1 - F.col("toxic")).otherwise(F.col("toxic")))
    a, b = toxicity.train(docs, labels, 500), toxicity.train(docs, flipped, 500)
    assert a.terms == b.terms
    for name in ("weights", "vector_ids", "vector_weights", "levels", "cuts"):
        assert np.array_equal(getattr(a, name), getattr(b, name))


# ---- packing ---------------------------------------------------------------------------------------------------------------


def test_chunk_tokenizer_equals_library():
    tok = packing.ChunkTokenizer(WORD_BPE)
    rng = random.Random(1)
    signs = "ab cdeth ingABéÉ ñ\n\t  '!?.,sté漢字🙂12  ́aΣß|)_"
    texts = ["".join(rng.choice(signs) for _ in range(rng.randint(0, 60))) for _ in range(6000)] + ["<|endoftext|>x <|endoftext|>", "   ", "", "a\x1c.\x1c b", "it's l'été d'A", "a_. b", "İ", "x²½"]
    for x, e in zip(tok.encode_batch(texts), tok.model.encode_batch(texts, add_special_tokens=False), strict=True):
        assert x.tolist() == e.ids


def test_hilbert_neighbours():
    import itertools

    for dims, bits in ((2, 3), (3, 2), (4, 2)):
        cells = np.array(list(itertools.product(range(1 << bits), repeat=dims)))
        key = packing.hilbert_key(cells, bits)
        assert sorted(key.tolist()) == list(range(len(cells)))
        assert np.abs(np.diff(cells[np.argsort(key)], axis=0)).sum(axis=1).max() == 1


def check_pieces(pieces, rows):
    tok = Tokenizer.from_file(WORD_BPE)
    want = Counter()
    full = Counter()
    for i, t in rows:
        full[i, len(tok.encode(t or "", add_special_tokens=False).ids) + 1] += 1
    by_seq = defaultdict(list)
    for p in pieces:
        by_seq[p.sequence_id].append((p.offset, p.length))
        want[p.doc_id, p.doc_tokens] += p.length
    for s, parts in by_seq.items():
        at = 0
        for off, n in sorted(parts):
            assert off == at and n > 0
            at += n
        assert at == 2048 or s == max(by_seq) and at <= 2048
    assert sorted(by_seq) == list(range(len(by_seq)))
    assert want == Counter({k: k[1] * n for k, n in full.items()})


def test_packing(spark):
    docs, rows = some_docs(spark)
    check_pieces(packing.pack(docs, WORD_BPE).collect(), rows)
    assert packing.pack(empty(spark), WORD_BPE).count() == 0
    real = registry.table(spark, DATA, "documents").collect()
    pieces = packing.pack(registry.table(spark, DATA, "documents"), WORD_BPE, with_ids=True).collect()
    check_pieces(pieces, [(r.doc_id, r.text) for r in real])
    tok = Tokenizer.from_file(WORD_BPE)
    ids = {r.doc_id: np.array([*tok.encode(r.text, add_special_tokens=False).ids, 1], "<u4") for r in real}
    for p in pieces:
        part = ids[p.doc_id][p.start : p.start + p.length].tobytes()
        assert bytes(p.piece_ids) == part and p.ids_crc32 == zlib.crc32(part)


# ---- sharding --------------------------------------------------------------------------------------------------------------


def test_differencing_beats_dealing():
    rng = random.Random(4)
    sizes = [int(rng.paretovariate(1.3) * 1000) for _ in range(400)]
    place = sharding.difference([[s] + [0] * 7 for s in sizes], 8)
    sums, dealt = [0] * 8, [0] * 8
    for i, (s, p) in enumerate(zip(sizes, place, strict=True)):
        sums[p[0]] += s
        dealt[i % 8] += s
        assert sorted(p) == list(range(8))
    assert max(sums) - min(sums) <= max(dealt) - min(dealt) and max(sums) <= max(max(sizes), sum(sizes) / 8 * 1.02)
    assert sharding.difference([], 4) == []


def test_shards(spark):
    docs, rows = some_docs(spark)
    got = sharding.shard_by_bytes(docs, 4).collect()
    assert Counter((r.doc_id, r.size, r.text_crc32) for r in got) == Counter((i, len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for i, t in rows)
    for s in range(4):
        own = sorted(r.slot for r in got if r.shard == s)
        assert own == list(range(len(own)))
    assert len({(r.text_crc32, r.shard) for r in got}) == len({r.text_crc32 for r in got})
    assert sharding.shard_by_bytes(empty(spark), 4).count() == 0
    real = registry.QUERIES["op6_differencing_shards"](spark, "/root/testdata/sf0.01").collect()
    sums = Counter()
    for r in real:
        sums[r.shard] += r.size
    assert len(sums) == 16 and max(sums.values()) - min(sums.values()) <= 0.01 * max(sums.values())


# ---- token counts, encoding ------------------------------------------------------------------------------------------------


def test_rollup_of_signed_batches(spark, tmp_path):
    count = {"w": token_rollup.count_words, "b": token_rollup.count_bpe(BYTE_BPE)}
    r = token_rollup.TokenRollup(spark, str(tmp_path / "r"))
    assert r.totals().count() == 0
    first = spark.createDataFrame([("s", "en", "a b c", 1), ("s", "en", "d", 1), ("t", None, None, 1)], "source string, lang string, text string, sign int")
    assert r.commit("1", first, count) and not r.commit("1", first, count)
    assert r.commit("2", spark.createDataFrame([("s", "en", "a b c", -1), ("s", "en", "a b", 1)], first.schema), count)
    found = {(x.source, x.lang, x.tokenizer): (x.n_docs, x.n_tokens) for x in r.totals().collect()}
    assert found[("s", "en", "w")] == (2, 3) and found[("t", None, "w")] == (1, 0)
    assert r.commit("3", first.withColumn("sign", -first.sign), count)
    c = r.compact(str(tmp_path / "c"))
    assert {tuple(x) for x in c.totals().collect()} == {tuple(x) for x in r.totals().collect()}
    assert not c.commit("2", first, count)


def test_rollup_query_equals_a_recount(spark):
    t = Tokenizer.from_file(BYTE_BPE)
    counts = {"byte_bpe_50k/1": lambda x: len(t.encode(x, add_special_tokens=False).ids), "words/1": lambda x: len(re.findall(r"[^\x20\x09-\x0D]+", x))}
    want = defaultdict(lambda: [0, 0, 0])
    for r in registry.table(spark, DATA, "documents").collect():
        state = {0: r.text, 1: None if len(r.text) < 60 else re.sub(r"[#*$%&|<>]", "", r.text)}
        for version, text in state.items():
            for name, count in counts.items():
                if text is not None:
                    for k, n in enumerate((1, count(text), len(text.encode()))):
                        want[version, r.source, r.lang, name][k] += n
    got = {(r.version, r.source, r.lang, r.tokenizer): [r.n_docs, r.n_tokens, r.n_bytes] for r in registry.QUERIES["op7_token_rollup"](spark, DATA).collect()}
    assert got == dict(want) and {v for v, *_ in got} == {0, 1} and any(got[k] != got.get((1, *k[1:])) for k in got if k[0] == 0)


def test_rollup_edges(spark, tmp_path):
    count = {"w": token_rollup.count_words}
    r = token_rollup.TokenRollup(spark, str(tmp_path / "r"))
    assert r.commit("a/b=c", empty(spark), count) and r.committed() == ["a/b=c"] and r.totals().count() == 0
    docs, rows = some_docs(spark)
    assert r.commit("docs", docs, count) and not r.commit("docs", docs, count)
    assert sum(x.n_docs for x in r.totals().collect()) == len(rows) and any(x.source is None for x in r.totals().collect())
    gone = docs.selectExpr("*", "-1 AS sign")
    #: Another writer placed the batch, and its totals are not folded yet.
    assert r._place("batch=gone", {"sums": token_rollup.batch_sums(gone, count)}) and not r._place("batch=gone", {"sums": token_rollup.batch_sums(gone, count)})
    assert r.totals().count() == 0 and r.totals(r.versions()[-1]).count() > 0
    r.fold()
    assert r.totals(r.versions()[-1]).count() == 0 and not r.commit("gone", gone, count)
    assert not [n for n in (tmp_path / "r").iterdir() if n.name.startswith("aside")]


def test_speculative_bpe_equals_library():
    t, b = Tokenizer.from_file(BYTE_BPE), bpe.SpeculativeBpe(BYTE_BPE)
    rng = random.Random(1)
    signs = "ab cdeth ingABé ñ\n\t  '!?sté漢字🙂12  ́a\x1c\xa0"
    texts = ["".join(rng.choice(signs) for _ in range(rng.randint(0, 60))) for _ in range(6000)]
    texts += ["".join(rng.choice("ahetinso") for _ in range(rng.randint(1, 25))) for _ in range(8000)]
    texts += ["a" * n for n in range(1, 70)] + ["ab" * 40, "<|endoftext|>x <|endoftext|>", "   ", "", "\n\n\n  a", "²½ ٣"]
    for x, e in zip(b.encode_batch(texts), t.encode_batch(texts, add_special_tokens=False), strict=True):
        assert x.tolist() == e.ids and b.decode(x) == t.decode(e.ids, skip_special_tokens=False)


def test_bpe_pair_checks_equal_merging():
    b = bpe.SpeculativeBpe(BYTE_BPE)
    rng = random.Random(2)
    ids = list(b.whole.values())
    pairs = [(rng.choice(ids[:3000]), rng.choice(ids[:3000])) for _ in range(4000)]
    good = b.compatible(*(np.array(x) for x in zip(*pairs, strict=True)))
    assert good.tolist() == [b.exact(b.pieces[x] + b.pieces[y]) == [x, y] for x, y in pairs]


def test_bpe_long_text_in_pieces(monkeypatch):
    b, t = bpe.SpeculativeBpe(BYTE_BPE), Tokenizer.from_file(BYTE_BPE)
    rng = random.Random(3)
    text = "".join(rng.choice(["word", " ", "  ", "\n", "it's", " 12", "é", " !"]) for _ in range(20_000))
    monkeypatch.setattr(bpe, "PIECE", 500)
    assert b.encode(text).tolist() == t.encode(text, add_special_tokens=False).ids


def test_encode_tables(spark):
    docs, rows = some_docs(spark)
    t = Tokenizer.from_file(BYTE_BPE)
    got = Counter((r.doc_id, tuple(r.ids), r.decoded) for r in bpe.encode_table(docs, BYTE_BPE).collect())
    assert got == Counter((i, tuple(t.encode(x or "", add_special_tokens=False).ids), x or "") for i, x in rows)
    assert bpe.encode_digests(docs, BYTE_BPE).count() == len(rows) and bpe.encode_digests(empty(spark), BYTE_BPE).count() == 0


# ---- SimHash ---------------------------------------------------------------------------------------------------------------


def brute_fingerprint(t):
    words = re.findall(rb"[^\x20\x09-\x0D]+", (t or "").encode().lower())
    shingles = [b" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))] if words else []
    hs = [xxhash.xxh64_intdigest(s, 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs)) if hs else 0


def brute_components(fps, radius):
    keys = sorted(set(fps))
    root = {k: k for k in keys}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, a in enumerate(keys):
        for b in keys[i + 1 :]:
            if (a ^ b).bit_count() <= radius:
                root[find(a)] = find(b)
    return {k: find(k) for k in keys}


def test_fingerprints_equal_brute_force():
    rng = random.Random(6)
    texts = [None, "", "  ", "A", "a b", "a b c", "É é", "x\x0by z\x1cq"] + [" ".join(rng.choice("ABcdé") for _ in range(rng.randint(1, 50))) for _ in range(200)]
    assert [simhash.fingerprint(t) for t in texts] == [brute_fingerprint(t) for t in texts]


def test_simhash_equals_brute_force(spark, monkeypatch):
    monkeypatch.setattr(simhash, "LEAF", 4)
    monkeypatch.setattr(simhash, "SHARD", 12)
    docs, rows = some_docs(spark)
    real = [(r.doc_id + 1000, r.text) for r in registry.table(spark, DATA, "documents").collect()]
    docs = docs.select("doc_id", "text").unionByName(spark.createDataFrame(real, "doc_id long, text string"))
    rows = rows + real
    root = brute_components([brute_fingerprint(t) for _, t in rows], 2)
    least = defaultdict(list)
    for i, t in rows:
        if i is not None:
            least[root[brute_fingerprint(t)]].append(i)
    want = Counter((i, f"{brute_fingerprint(t):016x}", min(least[root[brute_fingerprint(t)]], default=None)) for i, t in rows)
    assert Counter((r.doc_id, r.fingerprint, r.component_id) for r in simhash.near_duplicates(docs).collect()) == want
    assert simhash.near_duplicates(empty(spark)).count() == 0


@pytest.mark.parametrize("radius", [0, 2, 3])
def test_vantage_tree_finds_every_link(spark, monkeypatch, radius):
    monkeypatch.setattr(simhash, "LEAF", 8)
    monkeypatch.setattr(simhash, "SHARD", 60)
    rng = random.Random(radius)
    points = set()
    for _ in range(250):
        p = rng.getrandbits(64)
        for _ in range(rng.choice([1, 1, 2, 5])):
            points.add(p)
            for _ in range(rng.randint(1, 3)):
                p ^= 1 << rng.randrange(64)
    signed = [(p - (1 << 64) if p >> 63 else p,) for p in points]
    got = {r.node & (2**64 - 1): r.root & (2**64 - 1) for r in simhash.link_fingerprints(spark.createDataFrame(signed, "fp long"), len(points), radius).collect()}
    root = brute_components(points, radius)
    parts = defaultdict(set)
    for p in points:
        parts[got.get(p, p)].add(p)
    want = defaultdict(set)
    for p in points:
        want[root[p]].add(p)
    assert sorted(map(sorted, parts.values())) == sorted(map(sorted, want.values()))


# ---- licenses --------------------------------------------------------------------------------------------------------------


def test_licenses():
    index = license_scan.LicenseIndex.build(license_scan.TEMPLATES)
    for name, text in license_scan.TEMPLATES.items():
        where = "Some words before. " + text + " and after."
        best = [x for x in index.scan(where) if x[0] == name]
        assert best and best[0][1] == 1.0 and where[best[0][3] : best[0][4]].lower().startswith(license_scan.words_of(text)[0])
    words = license_scan.TEMPLATES["mit-grant"].split()
    broken = " ".join(w for i, w in enumerate(words) if i % 11 != 5)
    assert index.scan(broken)[0][0] == "mit-grant" and 0.8 <= index.scan(broken)[0][1] < 1
    assert index.scan(None) == [] and index.scan("licensed under the sea by the general public") == []
    assert index.scan("İ Released under the MIT License.")[0][3:] == (2, 32)


def test_alignment_is_the_longest_common_subsequence_in_the_band():
    rng = random.Random(9)
    for _ in range(300):
        a, b = [rng.randint(1, 4) for _ in range(rng.randint(1, 8))], [rng.randint(1, 4) for _ in range(rng.randint(1, 8))]
        best = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i in range(len(a)):
            for j in range(len(b)):
                best[i + 1][j + 1] = max(best[i][j + 1], best[i + 1][j], best[i][j] + (a[i] == b[j]))
        assert license_scan.align(a, b, 0)[0] == best[-1][-1]


def test_license_query(spark):
    docs, rows = some_docs(spark)
    assert license_scan.scan_licenses(docs).count() == 0 and license_scan.scan_licenses(empty(spark)).count() == 0
    texts = {r.doc_id: r.text for r in registry.table(spark, "/root/testdata/sf0.01", "documents").collect()}
    found = registry.QUERIES["op10_license_scan"](spark, "/root/testdata/sf0.01").collect()
    assert {r.doc_id for r in found} == {i for i, t in texts.items() if re.search(r"[Ll]icensed under|MIT License", t)}


# ---- registered queries ------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("name", sorted(registry.ORACLES))
def test_registered_query_equals_sql(spark, name):
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{DATA}/documents.parquet'")
    found = con.execute(registry.ORACLES[name])
    names = [d[0] for d in found.description]
    rows = registry.QUERIES[name](spark, DATA)
    assert sorted(rows.columns) == sorted(names)
    assert sorted(repr({n: r[n] for n in names}) for r in rows.collect()) == sorted(repr(dict(zip(names, r, strict=True))) for r in found.fetchall())
