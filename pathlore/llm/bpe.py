"""Byte-pair encoding by speculation and verification, and decoding.

For each distinct word: a greedy longest match proposes tokens; vectorised checks test every adjacent pair of the
proposal; words with a pair that fails are merged exactly. A sequence of tokens is what byte-pair merging gives if
and only if each adjacent pair, taken alone, would stay the pair: undoing merges from the latest on, no merge across
the boundary may come before the merges that close the boundary off.

The encoder reads a byte-level vocabulary file of the tokenizers library; its path is a parameter. A null text counts
as empty; an empty text has no tokens. Texts are taken in pieces at places where no word can go on, so memory does
not grow with a text's length. Added tokens named in the file are cut out first, as the library does.
"""

from __future__ import annotations

import hashlib
import itertools
import json
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from pathlore.llm.common import map_batches

#: The word pattern of the byte-level vocabulary.
WORDS = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Characters of text that are split into words at once, and words whose tokens are remembered.
PIECE, REMEMBERED = 1 << 20, 1_000_000
NEVER = np.iinfo(np.int64).max


def byte_symbols() -> list[str]:
    """The printable character that stands for each byte: itself where printable in Latin-1, else the next from 256 on."""
    out, nxt = [], 256
    for b in range(256):
        if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255:
            out.append(chr(b))
        else:
            out.append(chr(nxt))
            nxt += 1
    return out


class MergeTable:
    """The merges of a vocabulary by pair of ids, for many words at once."""

    def __init__(self, pairs: list[tuple[int, int]], products: list[int], size: int):
        self.size = size
        self.keys = np.array([a * size + b for a, b in pairs] + [-1])
        self.ranks = np.append(np.arange(len(pairs)), NEVER)
        self.products = np.array([*products, 0])
        # Open addressing: a slot holds the number of a merge, or that of the last, empty entry.
        self.mask = (1 << max(8, (16 * len(pairs)).bit_length())) - 1
        self.slots = np.full(self.mask + 1, len(pairs), "int32")
        todo = np.arange(len(pairs))
        at = self.hash(self.keys[:-1])
        while len(todo):
            free = self.slots[at] == len(pairs)
            self.slots[at[free]] = todo[free]
            lost = self.slots[at] != todo
            todo, at = todo[lost], (at[lost] + 1) & self.mask

    def hash(self, key: np.ndarray) -> np.ndarray:
        x = key * 0x9E3779B97F4A7
        return (x ^ (x >> 23)) & self.mask

    def look_up(self, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rank of the merge of each pair, and the token that it makes."""
        key = a * self.size + b
        at = self.hash(key)
        found = self.slots[at].astype("int64")
        empty = len(self.keys) - 1
        wrong = np.flatnonzero((self.keys[found] != key) & (found != empty))
        while len(wrong):
            at[wrong] = (at[wrong] + 1) & self.mask
            found[wrong] = self.slots[at[wrong]]
            wrong = wrong[(self.keys[found[wrong]] != key[wrong]) & (found[wrong] != empty)]
        return self.ranks[found], self.products[found]

    def merge_all(self, ids: np.ndarray, owner: np.ndarray, words: int) -> tuple[np.ndarray, np.ndarray]:
        """Exact merging of many words: in each round every word makes its merge of least rank. Flat ids, and lengths."""
        out_ids, out_owner = [np.zeros(0, "int64")], [np.zeros(0, "int64")]
        rank, made = np.full(len(ids), NEVER), np.zeros(len(ids), "int64")

        def rate(at: np.ndarray) -> None:
            """Rank the pairs that begin at these places."""
            at = at[(at >= 0) & (at < len(ids) - 1)]
            rank[at], made[at] = self.look_up(ids[at], ids[at + 1])
            rank[at[owner[at] != owner[at + 1]]] = NEVER

        rate(np.arange(len(ids) - 1))
        while len(ids):
            rank[-1] = NEVER
            first = np.flatnonzero(np.concatenate([[True], owner[1:] != owner[:-1]]))
            least = np.repeat(np.minimum.reduceat(rank, first), np.diff(np.append(first, len(ids))))
            done = least == NEVER
            out_ids.append(ids[done])
            out_owner.append(owner[done])
            at = np.flatnonzero((rank == least) & ~done)
            if not len(at):
                break
            # Overlapping places of one pair (aaa): every other one from the left.
            begins = np.concatenate([[True], at[1:] != at[:-1] + 1])
            offset = np.arange(len(at)) - np.maximum.accumulate(np.where(begins, np.arange(len(at)), 0))
            at = at[offset % 2 == 0]
            ids[at] = made[at]
            keep = ~done
            keep[at + 1] = False
            place = np.cumsum(keep)[at] - 1
            ids, owner, rank, made = ids[keep], owner[keep], rank[keep], made[keep]
            rate(np.concatenate([place, place - 1]))
        ids, owner = np.concatenate(out_ids), np.concatenate(out_owner)
        return ids[np.argsort(owner, kind="stable")], np.bincount(owner, minlength=words)


class SpeculativeBpe:
    """Encoder and decoder of one vocabulary file."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        symbols = byte_symbols()
        back = {c: b for b, c in enumerate(symbols)}
        as_bytes = lambda token: bytes(back[c] for c in token)
        self.vocab = {as_bytes(t): i for t, i in spec["model"]["vocab"].items()}
        self.added = {t["content"]: t["id"] for t in spec["added_tokens"]}
        size = 1 + max([*self.vocab.values(), *self.added.values()])
        self.pieces: list[bytes] = [b""] * size
        for t, i in self.vocab.items():
            self.pieces[i] = t
        for t, i in self.added.items():
            self.pieces[i] = t.encode()
        self.left, self.right = np.arange(size), np.arange(size)
        self.born = np.full(size, -1, "int64")  # rank of the merge that makes a token; -1: a single byte
        self.merge: dict[tuple[int, int], tuple[int, int]] = {}
        pairs, products = [], []
        for rank, pair in enumerate(spec["model"]["merges"]):
            a, b = (self.vocab[as_bytes(t)] for t in (pair if isinstance(pair, list) else pair.split(" ")))
            made = self.vocab[self.pieces[a] + self.pieces[b]]
            self.merge[a, b] = (rank, made)
            pairs.append((a, b))
            products.append(made)
            if self.born[made] < 0:
                self.left[made], self.right[made], self.born[made] = a, b, rank
        self.table = MergeTable(pairs, products, size)
        self.single = np.array([self.vocab[bytes([b])] for b in range(256)])
        #: Tokens that merging their own bytes gives again; only these are proposed.
        self.whole = {t: i for t, i in self.vocab.items() if len(t) == 1 or self.exact(t) == [i]}
        self.reach: dict[bytes, int] = {}
        for t in self.whole:
            if len(t) > 1:
                self.reach[t[:2]] = max(len(t), self.reach.get(t[:2], 0))
        self.pattern = regex.compile(WORDS)
        self.cut = regex.compile("|".join(map(regex.escape, sorted(self.added, key=len, reverse=True)))) if self.added else None
        self.forget()

    def forget(self) -> None:
        self.known: dict[str, int] = {}
        self.flat, self.used = np.zeros(1 << 16, "uint32"), 0
        self.starts: list[int] = []
        self.lens: list[int] = []

    def exact(self, word: bytes) -> list[int]:
        """Merging the pair of least rank, leftmost first, until none is left."""
        ids = [self.vocab[word[i : i + 1]] for i in range(len(word))]
        merge = self.merge
        while len(ids) > 1:
            best = min((merge[p][0], i) if (p := (ids[i], ids[i + 1])) in merge else (NEVER, i) for i in range(len(ids) - 1))
            if best[0] == NEVER:
                break
            a, b = ids[best[1]], ids[best[1] + 1]
            made, i, out = merge[a, b][1], 0, []
            while i < len(ids):
                if i + 1 < len(ids) and ids[i] == a and ids[i + 1] == b:
                    out.append(made)
                    i += 2
                else:
                    out.append(ids[i])
                    i += 1
            ids = out
        return ids

    def propose(self, word: bytes) -> list[int]:
        """Greedy longest match; only lengths are tried that some token with these first two bytes has."""
        out, i, n, whole, reach = [], 0, len(word), self.whole, self.reach
        while i < n:
            for j in range(min(n, i + reach.get(word[i : i + 2], 1)), i, -1):
                t = whole.get(word[i:j])
                if t is not None:
                    out.append(t)
                    i = j
                    break
        return out

    def compatible(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """For each pair of tokens: merging the bytes of both gives the pair again.

        Walks back in time at the boundary. ``ends`` is the rank at which the boundary's present neighbours stop
        being apart from what they become; a merge across the boundary of lower rank would have come before.
        """
        good = np.ones(len(a), bool)
        live = np.arange(len(a))
        left, right, ends = a.copy(), b.copy(), np.full(len(a), NEVER, "int64")
        # A merge of equal rank runs from left to right: made at the left it comes first, so a tie counts against
        # the boundary only where the right side is undone.
        ties = np.zeros(len(a), bool)
        while len(live):
            r, _ = self.table.look_up(left[live], right[live])
            bad = (r < ends[live]) | ((r == ends[live]) & ties[live] & (r != NEVER))
            good[live[bad]] = False
            live = live[~bad]
            x, y = left[live], right[live]
            bx, by = self.born[x], self.born[y]
            undo_left = bx > by  # equal only if both are bytes, or one token beside itself: then the right one is younger
            over = (bx < 0) & (by < 0)
            ends[live] = np.where(undo_left, bx, by)
            ties[live] = ~undo_left
            left[live] = np.where(undo_left, self.right[x], x)
            right[live] = np.where(undo_left, y, self.left[y])
            live = live[~over]
        return good

    def learn(self, words: list[str]) -> None:
        """Tokens of words not met before."""
        raw = [w.encode() for w in words]
        tokens = [self.propose(w) for w in raw]
        lens = np.fromiter(map(len, tokens), "int64", len(tokens))
        flat = np.fromiter(itertools.chain.from_iterable(tokens), "int64", int(lens.sum()))
        owner = np.repeat(np.arange(len(tokens)), lens)
        inner = owner[:-1] == owner[1:]
        fine = self.compatible(flat[:-1][inner], flat[1:][inner])
        failing = np.zeros(len(words), bool)
        failing[owner[:-1][inner][~fine]] = True
        if failing.any():
            again = [w for w, f in zip(raw, failing.tolist(), strict=True) if f]
            sizes = np.fromiter(map(len, again), "int64", len(again))
            merged, merged_lens = self.table.merge_all(self.single[np.frombuffer(b"".join(again), "uint8")], np.repeat(np.arange(len(again)), sizes), len(again))
            owner = np.concatenate([owner[~failing[owner]], np.repeat(np.flatnonzero(failing), merged_lens)])
            flat = np.concatenate([flat[~failing[np.repeat(np.arange(len(words)), lens)]], merged])[np.argsort(owner, kind="stable")]
            lens[failing] = merged_lens
        while self.used + len(flat) > len(self.flat):
            self.flat = np.concatenate([self.flat, np.zeros_like(self.flat)])
        self.flat[self.used : self.used + len(flat)] = flat
        first = len(self.starts)
        self.starts += (self.used + np.cumsum(lens) - lens).tolist()
        self.lens += lens.tolist()
        self.used += len(flat)
        self.known.update(zip(words, range(first, first + len(words)), strict=True))

    def lookup(self, words: list[str]) -> np.ndarray:
        """Numbers of words in the memory; new ones are learnt."""
        at = np.fromiter(map(self.known.get, words, itertools.repeat(-1)), "int64", len(words))
        missing = np.flatnonzero(at < 0)
        if len(missing):
            new = [words[i] for i in missing.tolist()]
            self.learn(list(dict.fromkeys(new)))
            self._starts, self._lens = np.array(self.starts), np.array(self.lens)
            at[missing] = np.fromiter(map(self.known.__getitem__, new), "int64", len(new))
        return at

    def tokens(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Flat ids of remembered words, and where each word's ids end."""
        if not len(at):
            return np.zeros(0, "uint32"), np.zeros(0, "int64")
        lens = self._lens[at]
        ends = np.cumsum(lens)
        return self.flat[np.arange(ends[-1]) + np.repeat(self._starts[at] - (ends - lens), lens)], ends

    def encode_words(self, words: list[str]) -> np.ndarray:
        if len(self.known) > REMEMBERED:
            self.forget()
        return self.tokens(self.lookup(words))[0]

    def parts(self, text: str) -> Iterator[str | int]:
        """Pieces of the text, cut where no word goes on, and the ids of added tokens."""
        at = 0
        for m in self.cut.finditer(text) if self.cut else ():
            yield from self.slices(text[at : m.start()])
            yield self.added[m.group()]
            at = m.end()
        yield from self.slices(text[at:] if at else text)

    @staticmethod
    def slices(text: str) -> Iterator[str]:
        """A space between two characters that are none starts a word in any case."""
        at = 0
        while len(text) - at > PIECE:
            to = at + PIECE
            while 0 < (to := text.find(" ", to)) < len(text) - 1 and (text[to - 1].isspace() or text[to + 1].isspace()):
                to += 1
            if to < 0 or to >= len(text) - 1:
                break
            yield text[at:to]
            at = to
        if at < len(text):
            yield text[at:]

    def encode(self, text: str | None) -> np.ndarray:
        out = [np.array([p], "uint32") if isinstance(p, int) else self.encode_words(self.pattern.findall(p)) for p in self.parts(text or "")]
        return out[0] if len(out) == 1 else np.concatenate(out) if out else np.zeros(0, "uint32")

    def encode_batch(self, texts: list[str | None]) -> Iterator[np.ndarray]:
        """As ``encode`` for each; short texts share one lookup."""
        held: list[list[str]] = []
        n = 0

        def out() -> Iterator[np.ndarray]:
            if len(self.known) > REMEMBERED:
                self.forget()
            ids, ends = self.tokens(self.lookup(list(itertools.chain.from_iterable(held))))
            bounds = np.concatenate([[0], ends])[np.cumsum([0, *map(len, held)])]
            for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
                yield ids[a:b]

        for text in texts:
            text = text or ""
            if len(text) > PIECE or (self.cut and self.cut.search(text)):
                yield from list(out())
                held, n = [], 0
                yield self.encode(text)
            else:
                held.append(self.pattern.findall(text))
                n += len(held[-1])
                if n > PIECE // 4:
                    yield from out()
                    held, n = [], 0
        yield from out()

    def decode(self, ids: np.ndarray) -> str:
        return b"".join(map(self.pieces.__getitem__, ids.tolist())).decode("utf-8", errors="replace")


_LOADED: dict[str, SpeculativeBpe] = {}


def encoder(path: str) -> SpeculativeBpe:
    """One encoder a path and worker process."""
    if path not in _LOADED:
        _LOADED[path] = SpeculativeBpe(path)
    return _LOADED[path]


def encode_table(docs: DataFrame, path: str) -> DataFrame:
    """The documents' columns doc_id and ids (array of int), and the decoded text."""

    def work(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        bpe = encoder(path)
        for at in range(0, batch.num_rows, 256):
            part = batch.slice(at, 256)
            ids = list(bpe.encode_batch(part.column("text").to_pylist()))
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array([x.astype("int32") for x in ids], pa.list_(pa.int32())), pa.array([bpe.decode(x) for x in ids])], ["doc_id", "ids", "decoded"])

    return map_batches(docs.select("doc_id", "text"), work, "doc_id long, ids array<int>, decoded string")


def encode_digests(docs: DataFrame, path: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256: what ``encode_table`` gives, digested where it is made."""

    def work(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        bpe = encoder(path)
        for at in range(0, batch.num_rows, 256):
            part = batch.slice(at, 256)
            n, of_ids, of_text = [], [], []
            for ids in bpe.encode_batch(part.column("text").to_pylist()):
                n.append(len(ids))
                of_ids.append(hashlib.sha256(ids.astype("<u4").tobytes()).hexdigest())
                of_text.append(hashlib.sha256(bpe.decode(ids).encode()).hexdigest())
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(n, pa.int64()), pa.array(of_ids), pa.array(of_text)], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return map_batches(docs.select("doc_id", "text"), work, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
