"""Packing along a space-filling curve.

A document's token counts, hashed, are projected to DIMS dimensions; each projection is replaced by its rank among
QUANTILES cuts taken over all documents, and the ranks give a Hilbert key. Documents are range-sorted by
that key and laid end to end along the curve; every 2048 tokens start the next sequence. So neighbours
on the curve share sequences, and only the last sequence has padding.

The range of a row depends on the key and, where many rows share a key, on a hash of the row, so a third
of all rows with one text spreads over many ranges. The number of ranges grows with the tokens (SPAN_TOKENS a range). A null text counts as empty and has the end token alone; null and
repeated doc_ids are packed as any other row; an empty table gives an empty result.
"""

from __future__ import annotations

import functools
import itertools
import json
import re
import unicodedata
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathlore.llm.bpe import MergeTable, byte_symbols
from pathlore.llm.common import give_back, map_batches, partitions_for, stage, with_row_tag

DIMS, BITS = 4, 8
QUANTILES = (1 << BITS) - 1
#: Bits of the key that hold a hash of the row.
SPREAD = 24
#: Words that a worker remembers, and chunks of text between white space.
REMEMBERED, CHUNKS = 300_000, 300_000
#: Bytes of text whose chunks are looked up together.
AT_ONCE = 2 << 20
#: Tokens of a span of the curve, which one task lays out; and the finest rank that its borders are sought to.
SPAN_TOKENS, FINEST = 16 << 20, 1_000_000
#: Runs of these alone are one word.
SIGNS = frozenset(".,;:!?()|-/") | frozenset((".,", "!!", "...", "--"))
WORD = re.compile(r"\w+|[^\w\s]+|\n")


def spread(starts: np.ndarray, lens: np.ndarray) -> np.ndarray:
    """The places start, start + 1, ... of each run."""
    ends = np.cumsum(lens)
    return np.arange(int(ends[-1]) if len(ends) else 0) + np.repeat(starts - (ends - lens), lens)


@functools.cache
def odd_signs() -> re.Pattern:
    """Signs that Python and the library may read differently: some separators, letters whose lower case depends on
    the place or is longer, and code points that Python's tables don't assign but the library's may; and all beyond U+FFFF."""
    unassigned = [c for c in map(chr, range(0x80, 0x10000)) if unicodedata.category(c) == "Cn"]
    return re.compile("[\x1c-\x1fΣİ" + "".join(unassigned) + "\U00010000-\U0010ffff]")


class Memory:
    """Ids of strings, end to end; a string's number gives where they start and how many they are."""

    def __init__(self) -> None:
        self.flat, self.used = np.zeros(1 << 16, "uint32"), 0
        self.starts, self.lens = np.zeros(0, "int64"), np.zeros(0, "int64")

    def add(self, flat: np.ndarray, lens: np.ndarray) -> None:
        n = len(flat)
        while self.used + n > len(self.flat):
            self.flat = np.concatenate([self.flat, np.zeros_like(self.flat)])
        self.flat[self.used : self.used + n] = flat
        self.starts = np.concatenate([self.starts, self.used + np.cumsum(lens) - lens])
        self.lens = np.concatenate([self.lens, lens])
        self.used += n

    def gather(self, at: np.ndarray, lens: np.ndarray) -> np.ndarray:
        return self.flat[spread(self.starts[at], lens)]


class ChunkTokenizer:
    """Ids of the tokenizers library, remembered by lower-case word, and by chunk between white space.

    The vocabulary's normalizer and word pattern never look across white space, nor across the border of letters and digits
    to other signs, but for apostrophes and underscores; so a text's ids are those of its words, or, with such signs, of
    what white space parts. Where Python and the library may differ about white space, case, normal form or what a code point is,
    the library takes the text.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.model = Tokenizer.from_file(path)
        self.size = self.model.get_vocab_size(with_added_tokens=True)
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)["model"]
        vocab, end = spec["vocab"], spec["end_of_word_suffix"] or ""
        symbols = byte_symbols()
        self.inner, self.last = (np.array([vocab.get(c + e, -1) for c in symbols]) for e in ("", end))
        pairs = [p if isinstance(p, list) else p.split(" ") for p in spec["merges"]]
        self.table = MergeTable([(vocab[a], vocab[b]) for a, b in pairs], [vocab[a + b] for a, b in pairs], self.size)
        self.simple = (self.inner >= 0).all() and (self.last >= 0).all()
        self.added = [t.content for t in self.model.get_added_tokens_decoder().values()]
        self.forget()

    def forget(self) -> None:
        self.words, self.known = Memory(), {"\n": 0}  # this parts chunks, and has no ids
        self.words.add(np.zeros(0, "uint32"), np.zeros(1, "int64"))
        self.forget_chunks()

    def forget_chunks(self) -> None:
        self.chunks, self.known_chunks = Memory(), pa.array([], pa.string())

    def learn(self, words: list[str]) -> None:
        # Letters alone and signs alone are one word of the vocabulary's pattern: their merges are made together.
        # The rest (digits, apostrophes, odd signs) goes to the library.
        one, rest = [], []
        for w in words:
            (one if w.isalpha() or w in SIGNS else rest).append(w)
        if not self.simple:
            one, rest = [], words
        raw = [w.encode() for w in one]
        sizes = np.fromiter(map(len, raw), "int64", len(raw))
        data = np.frombuffer(b"".join(raw), "uint8")
        ids = self.inner[data]
        tails = np.cumsum(sizes) - 1
        ids[tails] = self.last[data[tails]]
        merged, merged_lens = self.table.merge_all(ids, np.repeat(np.arange(len(raw)), sizes), len(raw))
        found = [e.ids for e in self.model.encode_batch(rest, add_special_tokens=False)] if rest else []
        words = one + rest
        lens = np.concatenate([merged_lens, np.fromiter(map(len, found), "int64", len(found))])
        flat = np.concatenate([merged, np.fromiter(itertools.chain.from_iterable(found), "int64")]) if found else merged
        self.known.update(zip(words, range(len(self.known), len(self.known) + len(words)), strict=True))
        self.words.add(flat, lens)

    def lookup(self, words: list[str]) -> np.ndarray:
        """Numbers of words in the memory; new ones are learnt."""
        at = np.fromiter(map(self.known.get, words, itertools.repeat(-1)), "int64", len(words))
        missing = np.flatnonzero(at < 0)
        if len(missing):
            new = [words[i] for i in missing.tolist()]
            self.learn(list(dict.fromkeys(new)))
            at[missing] = np.fromiter(map(self.known.__getitem__, new), "int64", len(new))
        return at

    def lookup_chunks(self, distinct: pa.StringArray) -> np.ndarray:
        """Numbers of distinct chunks in the memory; only new ones are parted into words."""
        at = pc.index_in(distinct, value_set=self.known_chunks).fill_null(-1).to_numpy(zero_copy_only=False).astype("int64")
        missing = np.flatnonzero(at < 0)
        if len(missing):
            new = distinct.take(pa.array(missing))
            at[missing] = np.arange(len(self.known_chunks), len(self.known_chunks) + len(new))
            self.chunks.add(*self.encode_chunks(new))
            self.known_chunks = pa.concat_arrays([self.known_chunks, new])
        return at

    def encode_chunks(self, distinct: pa.StringArray) -> tuple[np.ndarray, np.ndarray]:
        """Flat ids and lengths of distinct chunks."""
        chunks = distinct.to_pylist()
        where = np.flatnonzero(pc.or_(pc.match_substring(distinct, "'"), pc.match_substring(distinct, "_")))
        plain = list(chunks)
        for i in where.tolist():
            plain[i] = ""
        words = WORD.findall("\n".join(plain))
        at = self.lookup(words)
        ends = np.flatnonzero(at == self.known["\n"])
        lens = self.words.lens[at]
        total = np.concatenate([[0], np.cumsum(lens)])
        bounds = np.concatenate([[0], total[ends], total[-1:]])
        flat, sizes = self.words.gather(at, lens), np.diff(bounds)
        if len(where):
            at = self.lookup([chunks[i] for i in where.tolist()])
            more = self.words.lens[at]
            owner = np.concatenate([np.repeat(np.arange(len(chunks)), sizes), np.repeat(where, more)])
            flat = np.concatenate([flat, self.words.gather(at, more)])[np.argsort(owner, kind="stable")]
            sizes[where] = more
        return flat, sizes

    def encode_batch(self, texts: list[str]) -> Iterator[np.ndarray]:
        ids, bounds = self.encode_flat(texts)
        for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
            yield ids[a:b]

    def encode_flat(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all texts end to end, and where each begins and the last ends."""
        if len(self.known) > REMEMBERED:
            self.forget()
        if len(self.known_chunks) > CHUNKS:
            self.forget_chunks()
        plain = [self.is_plain(t) and not any(a in t for a in self.added) for t in texts]
        parts = pc.utf8_split_whitespace(pa.array([t.lower() if p else "" for t, p in zip(texts, plain, strict=True)], pa.string()))
        chunks = parts.flatten().dictionary_encode()
        at = self.lookup_chunks(chunks.dictionary)[chunks.indices.to_numpy()]
        lens = self.chunks.lens[at]
        ids = self.chunks.gather(at, lens)
        bounds = np.concatenate([[0], np.cumsum(lens)])[parts.offsets.to_numpy()]
        if not all(plain):
            each = [ids[a:b] if p else np.array(self.model.encode(t, add_special_tokens=False).ids, "uint32") for a, b, p, t in zip(bounds[:-1], bounds[1:], plain, texts, strict=True)]
            ids, bounds = np.concatenate(each), np.cumsum([0, *map(len, each)])
        return ids, bounds

    @staticmethod
    def is_plain(t: str) -> bool:
        """Whether Python and the library agree about the text's white space, case, letters and normal form."""
        if t.isascii():
            return not any(c in t for c in "\x1c\x1d\x1e\x1f")
        found = odd_signs().search(t)
        if found:  # beyond U+FFFF each sign is looked at
            odd = set(odd_signs().findall(t)) if found[0] > "\uffff" else found[0]
            if any(c <= "\uffff" or unicodedata.category(c) == "Cn" for c in odd):
                return False
        return unicodedata.is_normalized("NFC", t)


_LOADED: dict[str, ChunkTokenizer] = {}


def tokenizer(path: str) -> ChunkTokenizer:
    if path not in _LOADED:
        _LOADED[path] = ChunkTokenizer(path)
    return _LOADED[path]


def forget_tokenizers() -> None:
    """A worker whose next tasks need no tokenizer returns the memory of the last."""
    if _LOADED:
        _LOADED.clear()
        give_back()


def hashed_directions(size: int, dims: int) -> np.ndarray:
    """A sign for each token id and dimension, from a hash of the id."""
    x = np.arange(size, dtype="uint64") * np.uint64(0x9E3779B97F4A7C15)
    x ^= x >> np.uint64(29)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(32)
    return (((x[:, None] >> (np.arange(dims, dtype="uint64") * np.uint64(7) + np.uint64(11))) & np.uint64(1)).astype("int8") * 2 - 1).astype("int8")


def hilbert_key(cells: np.ndarray, bits: int) -> np.ndarray:
    """Index along the Hilbert curve of each row of ``cells`` (n x dims, ``bits`` bits each)."""
    x = cells.astype("uint64").T.copy()
    dims = len(x)
    one = np.uint64(1)
    for level in range(bits - 1, 0, -1):
        q = one << np.uint64(level)
        low = q - one
        for d in range(dims):
            set_ = (x[d] & q) != 0
            swap = np.where(set_, np.uint64(0), (x[0] ^ x[d]) & low)
            x[0] ^= np.where(set_, low, swap)
            x[d] ^= swap
    for d in range(1, dims):
        x[d] ^= x[d - 1]
    flip = np.zeros(x.shape[1], "uint64")
    for level in range(bits - 1, 0, -1):
        q = one << np.uint64(level)
        flip ^= np.where((x[dims - 1] & q) != 0, q - one, np.uint64(0))
    x ^= flip
    key = np.zeros(x.shape[1], "uint64")
    for level in range(bits - 1, -1, -1):
        for d in range(dims):
            key = (key << one) | ((x[d] >> np.uint64(level)) & one)
    return key.astype("int64")


def id_kind(size: int) -> str:
    return "<u2" if size <= 1 << 16 else "<u4"


def slices(batch: pa.RecordBatch, most: int) -> Iterator[pa.RecordBatch]:
    """The batch in parts of that many bytes of text, or of one row."""
    ends, at = np.cumsum(pc.binary_length(batch.column("text")).fill_null(0).to_numpy(zero_copy_only=False), dtype="int64"), 0
    while at < batch.num_rows:
        to = max(at + 1, int(np.searchsorted(ends, most + (ends[at - 1] if at else 0), side="right")))
        yield batch.slice(at, to - at)
        at = to


def tokenize(docs: DataFrame, path: str, end_id: int = 1) -> DataFrame:
    """doc_id, n_tokens, the projections p0..., and ids as little-endian 16- or 32-bit integers."""

    def work(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        tok = tokenizer(path)
        signs = np.ascontiguousarray(hashed_directions(tok.size, DIMS).T).astype("int32")
        kind = id_kind(tok.size)
        for part in slices(batch, AT_ONCE):
            flat, bounds = tok.encode_flat([t or "" for t in part.column("text").to_pylist()])
            n = np.diff(bounds)
            # Sums of signs up to each token: a row's projection is the difference of two of them, over its length.
            sums, proj = np.zeros(len(flat) + 1, "int32"), []
            for d in range(DIMS):
                np.cumsum(signs[d][flat], out=sums[1:])
                proj.append((sums[bounds[1:]] - sums[bounds[:-1]]) / np.maximum(n, 1))
            laid = np.full(len(flat) + len(n), end_id, kind)
            laid[np.arange(len(flat)) + np.repeat(np.arange(len(n)), n)] = flat
            ends = (bounds[1:] + np.arange(1, len(n) + 1)) * laid.itemsize
            raw, ids = laid.tobytes(), []
            for a, b in zip(np.concatenate([[0], ends[:-1]]).tolist(), ends.tolist(), strict=True):
                ids.append(raw[a:b])
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(n + 1, pa.int64()), pa.array(ids, pa.binary()), *(pa.array(proj[d], pa.float32()) for d in range(DIMS))], ["doc_id", "n_tokens", "ids", *(f"p{d}" for d in range(DIMS))])

    return map_batches(docs.select("doc_id", "text"), work, "doc_id long, n_tokens long, ids binary, " + ", ".join(f"p{d} float" for d in range(DIMS)))


def pack(docs: DataFrame, path: str, length: int = 2048, end_id: int = 1, ranges: int = 0, with_ids: bool = False) -> DataFrame:
    """One row a piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, and piece_ids if asked for."""
    rows = stage(with_row_tag(tokenize(docs, path, end_id)), "tokens")
    return pack_tokens(rows, id_kind(tokenizer(path).size), length, ranges, with_ids)


def pack_tokens(rows: DataFrame, kind: str, length: int = 2048, ranges: int = 0, with_ids: bool = False) -> DataFrame:
    """Lay staged rows of ``tokenize`` along the curve."""
    spark = rows.sparkSession
    cuts = [i / (QUANTILES + 1) for i in range(1, QUANTILES + 1)]
    stats = rows.agg(*(F.percentile_approx(f"p{d}", cuts, 10000).alias(f"p{d}") for d in range(DIMS)), F.sum("n_tokens").alias("tokens")).first()
    ranges = 1 if stats.tokens is None else ranges or max(2 * partitions_for(spark), -(-stats.tokens // SPAN_TOKENS))
    bounds = [np.array(stats[d] or [0.0], "float32") for d in range(DIMS)]

    def curve(*p: pd.Series) -> np.ndarray:
        cells = np.stack([np.searchsorted(b, x.to_numpy("float32"), side="right") for b, x in zip(bounds, p, strict=True)], axis=1)
        return hilbert_key(np.minimum(cells, (1 << BITS) - 1), BITS)

    def key_of(p0: pd.Series, p1: pd.Series, p2: pd.Series, p3: pd.Series, spread: pd.Series) -> pd.Series:
        forget_tokenizers()  # the ids are made
        return pd.Series((curve(p0, p1, p2, p3) << SPREAD) + spread.to_numpy("int64"))

    columns = ["p0", "p1", "p2", "p3", F.pmod(F.xxhash64("row_tag"), F.lit(1 << SPREAD))]
    keys = rows.select(F.pandas_udf(key_of, "long")(*columns).alias("key"))
    inner = keys.agg(F.percentile_approx("key", [i / ranges for i in range(1, ranges)], min(100 * ranges, FINEST)).alias("q")).first().q if ranges > 1 else []
    place = np.array(sorted(set(inner or [])), "int64")

    def place_of(p0: pd.Series, p1: pd.Series, p2: pd.Series, p3: pd.Series, spread: pd.Series) -> pd.DataFrame:
        key = key_of(p0, p1, p2, p3, spread).to_numpy()
        return pd.DataFrame({"key": key, "span": np.searchsorted(place, key, side="right").astype("int32")})

    # One Python worker a task: a join by span would put a filter below the projection, and with it a second run of the function.
    placed = rows.withColumn("at", F.pandas_udf(place_of, "key long, span int")(*columns))
    placed = placed.select("doc_id", "row_tag", "n_tokens", "ids", "at.key", "at.span")
    totals = {r.span: r.n for r in placed.groupBy("span").agg(F.sum("n_tokens").alias("n")).collect()}  # a number for each range
    first, starts = 0, {}
    for span in sorted(totals):
        starts[span], first = first, first + totals[span]
    keyed = placed.select("span", "key", "doc_id", "row_tag", "ids")
    fields = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]

    def lay(table: pa.Table) -> pa.Table:
        table = table.sort_by([("key", "ascending"), ("row_tag", "ascending")])
        ids = [np.frombuffer(x.as_buffer(), kind) for x in table.column("ids")]
        n = np.array([len(x) for x in ids])
        ends = starts[table.column("span")[0].as_py()] + np.cumsum(n)
        out: dict[str, list] = {f: [] for f in [*fields, "piece_ids"]}
        for doc, x, end in zip(table.column("doc_id").to_pylist(), ids, ends.tolist(), strict=True):
            at, done = end - len(x), 0
            while done < len(x):
                seq, off = divmod(at + done, length)
                take = min(length - off, len(x) - done)
                piece = x[done : done + take].astype("<u4").tobytes()
                for f, v in zip(fields, (doc, done, take, zlib.crc32(piece), len(x), seq, off), strict=True):
                    out[f].append(v)
                if with_ids:
                    out["piece_ids"].append(piece)
                done += take
        cols = [pa.array(out[f], pa.int64()) for f in fields]
        return pa.table([*cols, pa.array(out["piece_ids"], pa.binary())] if with_ids else cols, [*fields, "piece_ids"] if with_ids else fields)

    schema = ", ".join(f"{f} long" for f in fields) + (", piece_ids binary" if with_ids else "")
    return keyed.groupBy("span").applyInArrow(lay, schema)
