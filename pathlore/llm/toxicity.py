"""Toxicity by nearest labelled examples under exact TF-IDF cosine, with a block-max inverted index.

Terms are words and the first PREFIX letters of longer words. A bounded sample of labelled rows (EXAMPLES rows, by
hash order of the id, half of them toxic where there are as many, one text a doc_id; an example stands for as many labelled rows of its label
as the sample leaves out) gives the examples, and every term of theirs counts; document frequencies of these terms are
counted over all documents. A term's weight is (1 + ln tf) * idf, times 1 + BOOST * (G2 - NOISE) where the log-likelihood ratio G2
says that the term is more frequent in toxic examples beyond NOISE. The index holds, for each term, the largest weight in each block
of BLOCK examples: blocks are visited in order of their upper bound until it falls below the NEIGHBOURS-th best cosine, so results are
those of an exhaustive search (cosines are summed in single precision; those within TIE are ties). Terms that more than one in COMMON examples has are
rows of a matrix instead of postings: their part of the cosines is known before blocks are chosen. Votes are weighted by distance and mapped to a probability by an isotonic fit to leave-one-out votes of the
examples, which are found in tasks.

A text without any term of the examples (empty and null texts too) has no neighbour; its score is the share of toxic ones among the examples
without terms, drawn towards that of all. Labels without doc_id or toxic are ignored; of repeated labels the larger holds, of different texts of one
labelled doc_id the last in byte order. Without any usable label every score is 0. Very long texts are taken whole. Empty
tables give empty results; other columns and the order of rows have no influence.
"""

from __future__ import annotations

import itertools
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pathlore.llm.common import give_back, map_batches, partitions_for, release, stage, unload

#: Labelled rows of the sample, at most.
EXAMPLES = 2_000
NEIGHBOURS, BLOCK, NEAR, TIE, COMMON = 7, 64, 0.05, 1e-6, 16
PREFIX, BOOST, NOISE = 5, 0.05, 8.0
#: Imagined examples of the overall rate in each pool of the calibration: the boosts were found on the same examples.
SHRINK = 1
WORD = re.compile(r"[^\W_]+")


def words_of(text: str | None) -> list[str]:
    return WORD.findall((text or "").lower())


@dataclass
class Terms:
    """Numbers of words and of beginnings."""

    words: dict[str, int] = field(default_factory=dict)
    beginnings: dict[str, int] = field(default_factory=dict)

    def __len__(self) -> int:
        return len(self.words) + len(self.beginnings)

    def learn(self, counts: dict[str, int]) -> tuple[np.ndarray, np.ndarray]:
        """The terms of an example (new ones get the next numbers) and how often they occur."""
        out: dict[int, int] = {}
        for w, n in counts.items():
            out[self.words.setdefault(w, len(self))] = n
        for w, n in counts.items():
            if len(w) > PREFIX:
                t = self.beginnings.setdefault(w[:PREFIX], len(self))
                out[t] = out.get(t, 0) + n
        ids = np.fromiter(out, "int64", len(out))
        order = np.argsort(ids)
        return ids[order], np.fromiter(out.values(), "int64", len(out))[order]

    def read(self, text: str | None) -> tuple[np.ndarray, np.ndarray]:
        """The terms of a text in ascending order, and how often they occur; others are left out."""
        ws = words_of(text)
        find, none = self.beginnings.get, itertools.repeat(-1)
        found = [*map(self.words.get, ws, none), *[find(w[:PREFIX], -1) for w in ws if len(w) > PREFIX]]
        ids = np.array(found, "int64")
        return np.unique(ids[ids >= 0], return_counts=True)


def held_out(doc_id: str = "doc_id") -> Column:
    """Rows whose labels are never learnt from."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 3 == 1, F.lit(False))


def runs(starts: np.ndarray, lens: np.ndarray) -> np.ndarray:
    """The places start, start + 1, ... of each run."""
    ends = np.cumsum(lens)
    return np.arange(int(ends[-1]) if len(ends) else 0) + np.repeat(starts - (ends - lens), lens)


@dataclass
class ToxicityModel:
    """Example vectors (distinct, of unit length) by term and block, and the calibration."""

    terms: Terms
    weights: np.ndarray  # of a term: idf and boost
    rate: float = 0.0  # share of toxic ones among the labelled rows
    shares: tuple[float, float] = (1.0, 1.0)  # labelled rows that a clean and a toxic example stand for
    without: float = 0.0  # score of a text without terms
    toxic: np.ndarray = field(default_factory=lambda: np.zeros(0, "int64"))  # examples with a vector, by label
    clean: np.ndarray = field(default_factory=lambda: np.zeros(0, "int64"))
    evidence: np.ndarray = field(default_factory=lambda: np.zeros(0, "int64"))  # an example's doc_id
    cuts: np.ndarray = field(default_factory=lambda: np.zeros(0))
    levels: np.ndarray = field(default_factory=lambda: np.zeros(1))

    def weigh(self, ids: np.ndarray, counts: np.ndarray) -> np.ndarray:
        w = (1 + np.log(counts)) * self.weights[ids]
        length = float(np.sqrt((w * w).sum()))
        return w / length if length else w

    def index(self, vectors: list[tuple[np.ndarray, np.ndarray]]) -> None:
        """Postings by term and example; of each term and block, where the postings begin and their largest weight; common terms apart."""
        lens = np.array([len(ids) for ids, _ in vectors], "int64")
        self.vector_starts = np.concatenate([[0], np.cumsum(lens)])
        self.vector_ids = np.concatenate([np.zeros(0, "int32"), *(ids for ids, _ in vectors)]).astype("int32")
        self.vector_weights = np.concatenate([np.zeros(0, "float32"), *(w for _, w in vectors)]).astype("float32")
        owner = np.repeat(np.arange(len(vectors), dtype="int32"), lens)
        self.blocks = -(-len(vectors) // BLOCK)
        is_common = np.bincount(self.vector_ids, minlength=len(self.terms)) * COMMON > max(BLOCK, len(vectors))
        self.common = np.where(is_common, np.cumsum(is_common) - 1, -1)
        mine = is_common[self.vector_ids]
        self.matrix = np.zeros((int(is_common.sum()), self.blocks * BLOCK), "float32")
        self.matrix[self.common[self.vector_ids[mine]], owner[mine]] = self.vector_weights[mine]
        rare = np.flatnonzero(~mine)
        order = rare[np.argsort(self.vector_ids[rare], kind="stable")]
        term, self.post_ids, self.post_weights = self.vector_ids[order], owner[order], self.vector_weights[order]
        block = self.post_ids // BLOCK
        new = np.flatnonzero(np.concatenate([[True], (term[1:] != term[:-1]) | (block[1:] != block[:-1])])) if len(term) else np.zeros(0, "int64")
        self.entry_blocks = block[new]
        self.entry_tops = np.maximum.reduceat(self.post_weights, new) if len(new) else np.zeros(0, "float32")
        self.entry_starts = np.append(new, len(term))
        self.term_starts = np.searchsorted(term[new], np.arange(len(self.terms) + 1))

    def vector(self, i: int) -> tuple[np.ndarray, np.ndarray]:
        at = slice(self.vector_starts[i], self.vector_starts[i + 1])
        return self.vector_ids[at], self.vector_weights[at].astype("float64")

    def nearest(self, ids: np.ndarray, weights: np.ndarray, skip: int = -1) -> tuple[np.ndarray, np.ndarray]:
        """Distinct example vectors in falling order of cosine, as many as hold NEIGHBOURS examples, with all ties of the last."""
        rows = self.common[ids]
        base = weights[rows >= 0].astype("float32") @ self.matrix[rows[rows >= 0]]
        ids, weights = ids[rows < 0], weights[rows < 0]
        first = self.term_starts[ids]
        n = self.term_starts[ids + 1] - first
        entry, query = runs(first, n), np.repeat(weights, n)
        block = self.entry_blocks[entry]
        base = base.reshape(self.blocks, BLOCK)
        upper = np.bincount(block, query * self.entry_tops[entry], self.blocks) + base.max(axis=1) + TIE
        order = np.argsort(-upper, kind="stable")
        held = self.toxic + self.clean
        found_i, found_c, least = np.zeros(0, "int64"), np.zeros(0), TIE
        done, size = 0, 8
        rank = np.empty(self.blocks, "int64")
        while done < self.blocks:
            some = order[done : done + size]
            some = some[upper[some] > least - TIE]
            if not len(some):
                break
            done, size = done + size, 4 * size
            rank[:] = -1
            rank[some] = np.arange(len(some))
            mine = np.flatnonzero(rank[block] >= 0)
            starts = self.entry_starts[entry[mine]]
            lens = self.entry_starts[entry[mine] + 1] - starts
            at = runs(starts, lens)
            local = self.post_ids[at] % BLOCK + BLOCK * np.repeat(rank[block[mine]], lens)
            cosine = np.bincount(local, self.post_weights[at] * np.repeat(query[mine], lens), len(some) * BLOCK) + base[some].ravel()
            hit = np.flatnonzero(cosine > least - TIE if len(found_i) else cosine > TIE)
            found_i = np.concatenate([found_i, some[hit // BLOCK] * BLOCK + hit % BLOCK])
            found_c = np.concatenate([found_c, cosine[hit]])
            best = np.lexsort((found_i, -found_c))
            found_i, found_c = found_i[best], found_c[best]
            so_far = np.cumsum(held[found_i] - (found_i == skip))
            if so_far.size and so_far[-1] >= NEIGHBOURS:
                least = max(TIE, found_c[np.searchsorted(so_far, NEIGHBOURS)])
                keep = found_c >= least - TIE
                found_i, found_c = found_i[keep], found_c[keep]
        return found_i, found_c

    def vote(self, ids: np.ndarray, weights: np.ndarray, skip: int = -1, skip_toxic: bool = False) -> tuple[float, np.ndarray]:
        """The share of the distance-weighted votes that says toxic; ``skip``: without one example, with that label, of this vector."""
        i, cosine = self.nearest(ids, weights, skip)
        w = 1 / (1 - np.minimum(cosine, 1) + NEAR)
        toxic, clean = self.toxic[i].astype(float), self.clean[i].astype(float)
        if skip >= 0:
            (toxic if skip_toxic else clean)[i == skip] -= 1
        toxic, clean = toxic * self.shares[1], clean * self.shares[0]
        return (float((w * toxic).sum()) + self.rate) / (float((w * (toxic + clean)).sum()) + 1), i

    def calibrate(self, votes: list[tuple[float, float, float]]) -> None:
        """Isotonic fit (pool adjacent violators) to votes: vote, toxic examples, all examples, each for what it stands for."""
        pools: list[list[float]] = []
        for vote, toxic, n in sorted(votes):
            pools.append([vote, toxic, n])
            while len(pools) > 1 and pools[-2][1] * pools[-1][2] >= pools[-1][1] * pools[-2][2]:
                _, t, k = pools.pop()
                pools[-1][1] += t
                pools[-1][2] += k
        self.cuts = np.array([p[0] for p in pools][1:])
        self.levels = np.array([(p[1] + SHRINK * self.rate) / (p[2] + SHRINK) for p in pools]) if pools else np.array([self.without])

    def score_terms(self, ids: np.ndarray, counts: np.ndarray) -> tuple[float, list[int]]:
        """Score and the doc_ids of the nearest examples."""
        if not len(ids) or not len(self.toxic):
            return self.without, []
        vote, near = self.vote(ids, self.weigh(ids, counts))
        level = float(self.levels[np.searchsorted(self.cuts, vote, side="right")])
        return min(1.0, max(0.0, level)), self.evidence[near[:3]].tolist()

    def score(self, text: str | None) -> tuple[float, list[int]]:
        return self.score_terms(*self.terms.read(text))


def boosts(toxic_with: np.ndarray, clean_with: np.ndarray, toxic: int, clean: int) -> np.ndarray:
    """Of terms by the toxic and clean examples that have them: 1 and more, the more G-squared says that toxic ones do."""
    part = lambda x, expected: np.where(x > 0, 2 * x * np.log(np.maximum(x, 1) / np.maximum(expected, 1e-12)), 0.0)
    n, seen = toxic + clean, toxic_with + clean_with
    g2 = part(toxic_with, seen * toxic / n) + part(clean_with, seen * clean / n) + part(toxic - toxic_with, (n - seen) * toxic / n) + part(clean - clean_with, (n - seen) * clean / n)
    return 1 + BOOST * np.where(toxic_with * clean > clean_with * toxic, np.maximum(g2 - NOISE, 0), 0)


def sum_by_term(rows: DataFrame, column: str, terms: Terms, read, shared: Broadcast | None = None) -> tuple[np.ndarray, int]:
    """In how many rows each term is, and the number of rows; ``read`` gives the terms of a value, by ``shared``."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        df, seen = np.zeros(size + 1, "int64"), 0
        for batch in batches:
            seen += batch.num_rows
            for value in batch.column(column):
                df[read(value)] += 1
        df[-1] = seen
        some = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array(some.astype("int32")), pa.array(df[some])], ["term", "df"])
        if shared is not None:
            unload(shared)
        give_back()

    size = len(terms)
    found = rows.select(column).mapInArrow(count, "term int, df long").groupBy("term").agg(F.sum("df").alias("df")).toArrow()  # a row a term
    df = np.zeros(size + 1, "int64")
    df[found.column("term").to_numpy()] = found.column("df").to_numpy()
    return df[:-1], int(df[-1])


def document_frequencies(docs: DataFrame, terms: Terms) -> tuple[np.ndarray, int]:
    """In how many of all documents each term is, and the number of documents."""
    shared = docs.sparkSession.sparkContext.broadcast(terms)  # bounded by the sampled texts
    found = sum_by_term(docs, "text", terms, lambda text: shared.value.read(text.as_py())[0], shared)
    shared.unpersist()
    return found


def term_rows(docs: DataFrame, terms: Terms) -> DataFrame:
    """doc_id, held_out, and the text's terms and how often they occur, as little-endian 32-bit integers."""
    shared = docs.sparkSession.sparkContext.broadcast(terms)

    def work(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        found = [shared.value.read(t.as_py()) for t in batch.column("text")]
        blobs = (pa.array([x[k].astype("<i4").tobytes() for x in found], pa.binary()) for k in (0, 1))
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), *blobs], ["doc_id", "held_out", "ids", "counts"])

    return map_batches(docs.select("doc_id", "text", held_out().alias("held_out")), work, "doc_id long, held_out boolean, ids binary, counts binary", shared)


def sampled_texts(docs: DataFrame, labels: DataFrame, examples: int) -> tuple[DataFrame, list[int]]:
    """doc_id, toxic, text of at most ``examples`` labelled documents that are not held out; and how many there are, clean and toxic."""
    known = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~held_out()).groupBy("doc_id").agg((F.max("toxic") > 0).cast("int").alias("toxic"))
    counts = {r.toxic: r.n for r in known.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    there = [counts.get(0, 0), counts.get(1, 0)]
    toxic = min(there[1], max(examples // 2, examples - there[0]))
    by_hash = lambda label, n: known.where(F.col("toxic") == label).orderBy(F.xxhash64("doc_id"), "doc_id").limit(n)
    chosen = by_hash(1, toxic).unionByName(by_hash(0, examples - toxic))  # the stated bound
    return docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").groupBy("doc_id").agg(F.max("toxic").alias("toxic"), F.max("text").alias("text")), there


@dataclass
class Sample:
    """The examples: doc_id, label, terms and counts of each; and how many labelled rows there are, clean and toxic."""

    terms: Terms
    rows: list[tuple[int, bool, np.ndarray, np.ndarray]]
    there: list[int]


def examples_of(docs: DataFrame, labels: DataFrame, examples: int = EXAMPLES) -> Sample:
    def take_apart(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        found = [Counter(words_of(t.as_py())) for t in batch.column("text")]
        words, counts = (pa.array([" ".join(c) for c in found], pa.string()), pa.array([np.fromiter(c.values(), "int32", len(c)).tobytes() for c in found], pa.binary()))
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("toxic").cast(pa.int32()), words, counts], ["doc_id", "toxic", "words", "counts"])

    sample, there = sampled_texts(docs, labels, examples)
    staged = stage(map_batches(sample, take_apart, "doc_id long, toxic int, words string, counts binary"), "examples")
    terms, rows = Terms(), []
    for r in staged.orderBy("doc_id").collect():  # ``examples`` rows at most
        rows.append((r.doc_id, bool(r.toxic), *terms.learn(dict(zip(r.words.split(), np.frombuffer(r.counts, "int32").tolist(), strict=True)))))
    release(staged)
    return Sample(terms, rows, there)


def fit(spark: SparkSession, sample: Sample, df: np.ndarray, n: int) -> ToxicityModel:
    """The model of the examples, given in how many of ``n`` documents each term is."""
    terms, rows = sample.terms, sample.rows
    model = ToxicityModel(terms, np.ones(len(terms)))
    if not rows:
        return model
    label = np.array([y for _, y, _, _ in rows], bool)
    toxic, clean = int(label.sum()), int((~label).sum())
    model.shares = (sample.there[0] / clean if clean else 1.0, sample.there[1] / toxic if toxic else 1.0)
    model.rate = sample.there[1] / sum(sample.there)
    bare = [model.shares[y] * np.array([1, y]) for _, y, t, _ in rows if not len(t)]
    all_bare, toxic_bare = sum(bare, np.zeros(2)).tolist()
    model.without = (toxic_bare + model.rate) / (all_bare + 1)
    if not len(terms):
        return model
    number, in_toxic = np.concatenate([t for _, _, t, _ in rows]), np.repeat(label, [len(t) for _, _, t, _ in rows])
    by_label = [np.bincount(number[in_toxic == y], minlength=len(terms)) for y in (True, False)]
    boost = boosts(*by_label, toxic, clean) if toxic and clean else np.ones(len(terms))
    model.weights = (np.log((1 + n) / (1 + df)) + 1) * boost
    groups: dict[tuple[bytes, bytes], list] = {}
    for i, y, ids, c in rows:
        if len(ids):
            groups.setdefault((ids.tobytes(), c.tobytes()), [0, 0, i, ids, c])[y] += 1
    #: Neighbouring numbers share their most frequent terms and their heaviest one, so the block bounds are tight.
    held = []
    for no, yes, i, ids, c in groups.values():
        w = model.weigh(ids, c)
        common = ids[np.lexsort((ids, -df[ids]))[:2]].tolist()
        held.append(((int(boost[ids].max() > 1.5), *common, int(ids[np.argmax(w)]), i), no, yes, i, ids, w))
    held.sort(key=lambda h: h[0])
    model.clean, model.toxic, model.evidence = (np.array([h[k] for h in held], "int64") for k in (1, 2, 3))
    model.index([(h[4], h[5]) for h in held])
    model.calibrate(own_votes(spark, model))
    return model


def train(docs: DataFrame, labels: DataFrame, examples: int = EXAMPLES) -> ToxicityModel:
    sample = examples_of(docs, labels, examples)
    return fit(docs.sparkSession, sample, *document_frequencies(docs, sample.terms))


def train_and_score(docs: DataFrame, labels: DataFrame, examples: int = EXAMPLES) -> DataFrame:
    """``with_scores`` of a model of the same documents, reading each text once: its terms are staged between counting and scoring."""
    sample = examples_of(docs, labels, examples)
    rows = stage(term_rows(docs, sample.terms), "terms")
    model = fit(docs.sparkSession, sample, *sum_by_term(rows, "ids", sample.terms, lambda ids: np.frombuffer(ids.as_buffer(), "<i4")))
    return score_rows(rows, model, ["ids", "counts"], lambda m, ids, counts: m.score_terms(np.frombuffer(ids.as_buffer(), "<i4"), np.frombuffer(counts.as_buffer(), "<i4")))


def own_votes(spark: SparkSession, model: ToxicityModel) -> list[tuple[float, float, float]]:
    """For each vector and label: the vote without one such example, and how many of them are toxic and are there. Found in tasks."""
    shared = spark.sparkContext.broadcast(model)

    def work(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        m = shared.value
        out = [(m.vote(*m.vector(i), i, label)[0], n * m.shares[1] if label else 0.0, n * m.shares[label]) for i in batch.column("id").to_pylist() for label, n in ((True, int(m.toxic[i])), (False, int(m.clean[i]))) if n]
        yield pa.RecordBatch.from_arrays([pa.array(c, pa.float64()) for c in zip(*out, strict=True)], ["vote", "toxic", "all"])

    n = len(model.toxic)
    found = map_batches(spark.range(0, n, 1, max(1, min(partitions_for(spark), n // 200))), work, "vote double, toxic double, all double", shared).collect()  # two rows a vector at most
    shared.unpersist()
    return [tuple(r) for r in found]


def score_rows(rows: DataFrame, model: ToxicityModel, columns: list[str], score) -> DataFrame:
    shared = rows.sparkSession.sparkContext.broadcast(model)  # bounded by the sampled texts

    def work(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        found = [score(shared.value, *x) for x in zip(*(batch.column(c) for c in columns), strict=True)]
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array([s for s, _ in found], pa.float64()), pa.array([e for _, e in found], pa.list_(pa.int64()))], ["doc_id", "held_out", "score", "evidence"])

    return map_batches(rows.select("doc_id", "held_out", *columns), work, "doc_id long, held_out boolean, score double, evidence array<long>", shared)


def with_scores(docs: DataFrame, model: ToxicityModel) -> DataFrame:
    """doc_id, held_out, score, and evidence (doc_ids of near examples)."""
    return score_rows(docs.select("doc_id", "text", held_out().alias("held_out")), model, ["text"], lambda m, text: m.score(text.as_py()))


def drop_toxic(docs: DataFrame, model: ToxicityModel, least: float = 0.7) -> DataFrame:
    """The documents with a score below ``least``, all columns unchanged."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def work(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        yield batch.filter(pa.array([shared.value.score(t.as_py())[0] < least for t in batch.column("text")], pa.bool_()))

    return map_batches(docs, work, docs.schema, shared)
