"""Removal of repeated passages by suffix arrays over shards of repeated text.

A byte goes if a LENGTH-byte string that covers it also starts in a document with a smaller doc_id. One suffix array
over a whole corpus cannot be built, so the text is first brought together by content:

1. Documents are packed into blocks. In each block, every LENGTH-byte window is keyed by the least hash of its
   GRAM-byte substrings; neighbouring windows mostly share a key. Equal windows have equal keys. Each block sends its
   distinct keys, once each, to the key's bucket.
2. A bucket tells each block which of its keys other documents have too. Keys that very many blocks have, or with very much
   text, are marked heavy.
3. Blocks send the distinct stretches of windows with a shared key to the key's bucket. Under a heavy key each
   window is sent alone, to the bucket of its own hash, so that no bucket grows with one key.
4. A bucket groups equal windows: stretches with the same bytes are one; where a key has different stretches, a suffix
   array (grouping construction) of them puts equal windows side by side. Each window learns the smallest
   doc_id that it starts in, and the spans to remove go back to the block.
5. Blocks apply the spans.

Work is exact for any hash: keys only bring candidates together, and the suffix arrays compare bytes.

A null text counts as empty. Rows without a doc_id lose nothing and take nothing away, since no id is smaller. Rows with the
same doc_id never take from each other, repeated rows included. An empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathlore.llm.common import partitions_for, release, stage, stage_bucketed
from pathlore.llm.suffix_groups import suffix_array

LENGTH, GRAM = 50, 20
#: Text bytes of a block and of a bucket: they grow with the table between these bounds.
BLOCK_BYTES, BUCKET_BYTES = (2 << 20, 64 << 20), (4 << 20, 256 << 20)
#: Blocks that share a key, or bytes under it, before it counts as heavy; bytes of one suffix array's text.
HEAVY_BLOCKS, HEAVY_BYTES, ARRAY_BYTES = 4096, 32 << 20, 200_000
ODD_A, ODD_B = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)
KEY_BITS = 40
#: Bytes whose hashes are computed at once.
PIECE = 1 << 18
NO_ID = np.iinfo(np.int64).max


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * ODD_B
    x = (x ^ (x >> np.uint64(29))) * ODD_A
    return x ^ (x >> np.uint64(32))


def gram_hashes(text: np.ndarray) -> np.ndarray:
    """A hash of the GRAM bytes from each place on."""
    n = len(text) - GRAM + 1
    words = np.ascontiguousarray(np.lib.stride_tricks.sliding_window_view(text, 8)).view("<u8").ravel()
    h = mix(words[:n] * ODD_A + ODD_B)
    for at in (*range(8, GRAM - 8, 8), GRAM - 8):
        h = mix(h + words[at : at + n])
    return h


def stretches(text: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, ...]:
    """Of the runs of windows with the same key: key, document, first window and end. ``ends``: where each document ends."""
    if len(text) < LENGTH:
        none = np.zeros(0, "int64")
        return none.astype("uint64"), none, none, none
    h = gram_hashes(text)
    width = LENGTH - GRAM + 1
    least, span = h, 1
    while span * 2 <= width:
        least = np.minimum(least[:-span], least[span:])
        span *= 2
    n = len(h) - width + 1
    least = np.minimum(least[:n], least[width - span : width - span + n])
    edge = np.zeros(n + 1, "int8")  # 1 where windows begin to be whole, -1 where they run into the next document
    begins = np.concatenate([[0], ends[:-1]])
    whole = ends - begins >= LENGTH
    np.add.at(edge, begins[whole], 1)
    np.add.at(edge, ends[whole] - LENGTH + 1, -1)
    valid = np.cumsum(edge[:n], dtype="int8") > 0
    new = np.empty(n, bool)
    new[0] = True
    np.not_equal(least[1:], least[:-1], out=new[1:])
    new[begins[whole]] = True
    starts = np.flatnonzero(new & valid)
    doc = np.searchsorted(ends, starts, side="right")
    stop = np.minimum(np.append(starts[1:], n), ends[doc] - LENGTH + 1)
    return mix(least[starts]), doc, starts, stop


class Block:
    """The documents of a block, from its Arrow message, with all their columns."""

    def __init__(self, message: bytes):
        self.rows = pa.ipc.open_stream(message).read_all().combine_chunks()
        self.texts = [t.encode("utf-8", "replace") if t else b"" for t in self.rows.column("text").to_pylist()]
        ids = self.rows.column("doc_id").to_pylist()
        self.ids = np.array([NO_ID if i is None else i for i in ids], "int64")
        self.known = np.array([i is not None for i in ids], bool)
        self.starts = np.cumsum([0, *map(len, self.texts)])

    def runs(self) -> tuple[np.ndarray, ...]:
        """Of all stretches: key, document, first window and end (places in the block)."""
        out: list[list[np.ndarray]] = [[], [], [], []]
        data, first, n = self.data(), 0, len(self.texts)
        while first < n:  # documents of about PIECE bytes at once, so that the arrays stay in the cache
            last = max(first + 1, int(np.searchsorted(self.starts, self.starts[first] + PIECE, side="right")) - 1)
            at = int(self.starts[first])
            key, doc, a, b = stretches(data[at : int(self.starts[last])], self.starts[first + 1 : last + 1] - at)
            own = self.known[first + doc]
            for o, x in zip(out, (key, first + doc, a + at, b + at), strict=True):
                o.append(x[own])
            first = last
        kinds = ("uint64", "int64", "int64", "int64")
        return tuple(np.concatenate([np.zeros(0, k), *o]) for o, k in zip(out, kinds, strict=True))

    def data(self) -> np.ndarray:
        return np.frombuffer(b"".join(self.texts), "uint8")


def distinct_keys(key: np.ndarray, ids: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Distinct keys in order of (bucket, short key): bucket, short key, whether two ids have it, and for each key given its number."""
    bucket, short = (key % np.uint64(buckets)).astype("int64"), key >> np.uint64(64 - KEY_BITS)
    order = np.lexsort((ids, short, bucket))
    b, s, i = bucket[order], short[order], ids[order]
    new = np.concatenate([[True], (b[1:] != b[:-1]) | (s[1:] != s[:-1])]) if len(b) else np.zeros(0, bool)
    at = np.flatnonzero(new)
    several = np.minimum.reduceat(i, at) != np.maximum.reduceat(i, at) if len(at) else new
    number = np.empty(len(key), "int64")
    number[order] = np.cumsum(new) - 1
    return b[at], s[at], several, number


def to_planes(x: np.ndarray, width: int) -> bytes:
    """Sorted numbers as byte planes of their differences, which compress."""
    d = np.diff(x.astype("<u8"), prepend=np.uint64(0))
    return np.ascontiguousarray(d.view("uint8").reshape(-1, 8)[:, :width].T).tobytes()


def from_planes(raw: bytes, width: int) -> np.ndarray:
    planes = np.frombuffer(raw, "uint8").reshape(width, -1)
    d = np.zeros((planes.shape[1], 8), "uint8")
    d[:, :width] = planes.T
    return np.cumsum(d.view("<u8").ravel(), dtype="uint64")


def pack_blocks(docs: DataFrame, block_bytes: int) -> DataFrame:
    """block_id, message: the rows as Arrow messages of about ``block_bytes``."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        task, n = TaskContext.get().partitionId(), 0
        held: list[pa.RecordBatch] = []
        size = 0

        def out() -> pa.RecordBatch:
            sink = pa.BufferOutputStream()
            rows = pa.Table.from_batches(held).combine_chunks()
            with pa.ipc.new_stream(sink, rows.schema) as w:
                w.write_table(rows)
            return pa.RecordBatch.from_arrays([pa.array([(task << 32) + n], pa.int64()), pa.array([sink.getvalue().to_pybytes()], pa.binary())], ["block_id", "message"])

        for batch in batches:
            at = 0
            sizes = np.array([len(t.as_buffer()) if t.is_valid else 0 for t in batch.column("text")], "int64")
            while at < batch.num_rows:
                room = np.searchsorted(np.cumsum(sizes[at:]), block_bytes - size) + 1
                part = batch.slice(at, int(room))
                held.append(part)
                size += int(sizes[at : at + room].sum())
                at += int(room)
                if size >= block_bytes:
                    yield out()
                    held, size, n = [], 0, n + 1
        if held:
            yield out()

    return docs.mapInArrow(work, "block_id long, message binary")


def send_keys(buckets: int):
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block_id, message in zip(batch.column("block_id").to_pylist(), batch.column("message"), strict=True):
                block = Block(message.as_buffer())
                key, doc, first, last = block.runs()
                b, short, several, number = distinct_keys(key, block.ids[doc], buckets)
                size = np.bincount(number, last - first + LENGTH - 1, len(b))
                size = np.ceil(np.log2(np.maximum(size, 1))).astype("uint8")  # up to the next power of two
                names, at = np.unique(b, return_index=True)
                ends = np.append(at[1:], len(b))[: len(at)]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(names), pa.array(np.full(len(names), block_id)), pa.array([to_planes(short[x:y], KEY_BITS // 8) for x, y in zip(at, ends, strict=True)], pa.binary()), pa.array([np.packbits(several[x:y]).tobytes() for x, y in zip(at, ends, strict=True)], pa.binary()), pa.array([size[x:y].tobytes() for x, y in zip(at, ends, strict=True)], pa.binary())],
                    ["bucket", "block_id", "keys", "several", "sizes"],
                )

    return work


def mark_shared(heavy_blocks: int):
    """For each block of a bucket, a mark for each of its keys: 0 its own, 1 shared, 2 heavy."""

    def work(sent: pa.Table) -> pa.Table:
        keys = [from_planes(x.as_buffer(), KEY_BITS // 8) for x in sent.column("keys")]
        several = [np.unpackbits(np.frombuffer(x.as_buffer(), "uint8"), count=len(k)).astype(bool) for x, k in zip(sent.column("several"), keys, strict=True)]
        lens = np.array(list(map(len, keys)))
        all_keys, number, count = np.unique(np.concatenate(keys), return_inverse=True, return_counts=True)
        in_one = np.zeros(len(all_keys), bool)
        np.logical_or.at(in_one, number, np.concatenate(several))
        size = np.bincount(number, np.exp2(np.frombuffer(b"".join(x.as_py() for x in sent.column("sizes")), "uint8")), len(all_keys))
        shared = (count > 1) | in_one
        mark = np.where(shared & ((count > heavy_blocks) | (size > HEAVY_BYTES)), 2, shared).astype("uint8")[number]
        parts = np.split(mark, np.cumsum(lens)[:-1])
        keep = [i for i, p in enumerate(parts) if p.any()]
        return pa.table({"block_id": sent.column("block_id").take(pa.array(keep, pa.int64())), "bucket": sent.column("bucket").take(pa.array(keep, pa.int64())), "marks": pa.array([parts[i].tobytes() for i in keep], pa.binary())})

    return work


def send_stretches(buckets: int):
    """A block's distinct stretches with a shared key, by bucket, each with the places and doc_ids where it stands."""
    fields = ["bucket", "block_id", "keys", "lens", "data", "counts", "places", "ids"]

    def work(blocks: pa.Table, marked: pa.Table) -> pa.Table:
        rows: dict[str, list] = {f: [] for f in fields}
        for block_id, message in zip(blocks.column("block_id").to_pylist(), blocks.column("message"), strict=True):
            if not marked.num_rows:
                continue
            block = Block(message.as_buffer())
            key, doc, a, b = block.runs()
            bucket, _, _, number = distinct_keys(key, block.ids[doc], buckets)
            mark = np.zeros(len(bucket), "uint8")
            for name, m in zip(marked.column("bucket").to_pylist(), marked.column("marks"), strict=True):
                lo, hi = np.searchsorted(bucket, [name, name + 1])
                mark[lo:hi] = np.frombuffer(m.as_buffer(), "uint8")
            mark = mark[number]
            data = block.data()
            light, heavy = mark == 1, mark == 2
            key_, doc_, a_, b_ = key[light], doc[light], a[light], b[light]
            if heavy.any():  # each window alone, under its own hash
                n = b[heavy] - a[heavy]
                at = ranges(a[heavy], n)
                h = window_hashes(data, at)
                key_, doc_ = np.concatenate([key_, h]), np.concatenate([doc_, np.repeat(doc[heavy], n)])
                a_, b_ = np.concatenate([a_, at]), np.concatenate([b_, at + 1])
            raw = data.tobytes()
            seen: dict[tuple[int, bytes], list[int]] = {}
            for i, (k, x, y) in enumerate(zip(key_.tolist(), a_.tolist(), (b_ + LENGTH - 1).tolist(), strict=True)):
                seen.setdefault((k, raw[x:y]), []).append(i)
            parts: dict[int, list] = {}
            for (k, text), where in seen.items():
                parts.setdefault(k % buckets, []).append((k, text, where))
            ids = block.ids[doc_]
            for name, part in parts.items():
                where = np.array([i for _, _, w in part for i in w])
                for f, v in zip(
                    fields,
                    (name, block_id, np.array([k for k, _, _ in part], "uint64").tobytes(), np.array([len(t) for _, t, _ in part], "<u4").tobytes(), b"".join(t for _, t, _ in part), np.array([len(w) for _, _, w in part], "<u4").tobytes(), a_[where].astype("<i8").tobytes(), ids[where].tobytes()),
                    strict=True,
                ):
                    rows[f].append(v)
        kinds = [pa.int64(), pa.int64(), *[pa.binary()] * 6]
        return pa.table([pa.array(rows[f], k) for f, k in zip(fields, kinds, strict=True)], fields)

    return work


def least_ids(texts: list[bytes], ids: list[int]) -> list[np.ndarray]:
    """For each window of each text, the smallest id of the texts that it occurs in, by a suffix array of all of them."""
    lens = np.array(list(map(len, texts)))
    joined = np.frombuffer(b"\0".join(texts) + b"\0", "uint8")
    starts = np.cumsum(lens + 1) - lens - 1
    symbols = joined.astype("int16") + 2
    symbols[starts + lens] = 1
    order = np.array(suffix_array([*symbols.tolist(), 0])[1:])
    windows = np.zeros(len(joined) + 1, "int64")
    np.add.at(windows, starts, 1)
    np.add.at(windows, starts + lens - LENGTH + 1, -1)
    order = order[np.cumsum(windows)[order] > 0]
    view = np.lib.stride_tricks.sliding_window_view(joined, LENGTH)
    differs = np.ones(len(order), bool)
    step = 1 << 16
    for at in range(0, len(order) - 1, step):
        some = order[at : at + step + 1]
        differs[at + 1 : at + len(some)] = (view[some[1:]] != view[some[:-1]]).any(axis=1)
    first = np.flatnonzero(differs)
    own = np.array(ids, "int64")[np.searchsorted(starts, order, side="right") - 1]
    least = np.repeat(np.minimum.reduceat(own, first), np.diff(np.append(first, len(order))))
    of_place = np.zeros(len(joined), "int64")
    of_place[order] = least
    return [of_place[s : s + n - LENGTH + 1] for s, n in zip(starts.tolist(), lens.tolist(), strict=True)]


def window_hashes(data: np.ndarray, at: np.ndarray) -> np.ndarray:
    """A hash of the LENGTH bytes from each place on."""
    view = np.lib.stride_tricks.sliding_window_view(data, 8)
    h = np.zeros(len(at), "uint64")
    for o in (0, 8, 16, 24, 32, 40, LENGTH - 8):
        h = mix(h + ODD_B + np.ascontiguousarray(view[at + o]).view("<u8").ravel())
    return h


def ranges(first: np.ndarray, n: np.ndarray) -> np.ndarray:
    """The numbers first, first + 1, ... of each pair, ``n`` of them."""
    return np.arange(int(n.sum())) + np.repeat(first - (np.cumsum(n) - n), n)


def find_repeats(sent: pa.Table) -> pa.Table:
    """Spans to remove, by block: the work of a bucket."""
    texts: dict[bytes, int] = {}
    least: list[int] = []  # of a text: its smallest id
    by_key: dict[int, set[int]] = {}
    occurrences = []
    for i in range(sent.num_rows):  # one row at a time: a bucket is not held twice
        row = {name: sent.column(name)[i].as_py() for name in sent.column_names}
        keys, lens = np.frombuffer(row["keys"], "uint64").tolist(), np.frombuffer(row["lens"], "<u4").astype("int64")
        counts, places, ids = np.frombuffer(row["counts"], "<u4").astype("int64"), np.frombuffer(row["places"], "<i8"), np.frombuffer(row["ids"], "int64")
        ends, of = np.cumsum(lens).tolist(), np.cumsum(counts) - counts
        smallest = np.minimum.reduceat(ids, of).tolist()
        numbers, data = np.empty(len(keys), "int64"), row["data"]
        for at, (k, n, e, m) in enumerate(zip(keys, lens.tolist(), ends, smallest, strict=True)):
            t = data[e - n : e]
            x = texts.get(t)
            if x is None:
                x = texts[t] = len(least)
                least.append(m)
                by_key.setdefault(k, set()).add(x)
            else:
                if m < least[x]:
                    least[x] = m
                by_key[k].add(x)
            numbers[at] = x
        occurrences.append((row["block_id"], np.repeat(numbers, counts), places, ids))
    window_ids, first, n_windows = order_stretches(list(texts), np.array(least, "int64"), [sorted(x) for x in by_key.values() if len(x) > 1])
    blocks, starts, ends = [], [], []
    for block_id, number, places, ids in occurrences:
        n = n_windows[number]
        gone = window_ids[ranges(first[number], n)] < np.repeat(ids, n)
        at = np.unique(ranges(places, n)[gone])
        if len(at):
            new = np.concatenate([[True], at[1:] != at[:-1] + 1])
            blocks.append(block_id)
            starts.append(at[new].astype("<i8").tobytes())
            ends.append((at[np.append(new[1:], True)] + LENGTH).astype("<i8").tobytes())
    return pa.table([pa.array(blocks, pa.int64()), pa.array(starts, pa.binary()), pa.array(ends, pa.binary())], ["block_id", "starts", "ends"])


def order_stretches(texts: list[bytes], least: np.ndarray, rivals: list[list[int]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The smallest id of each window of each text, where each text's windows begin in that list, and their number.

    ``rivals`` are the sets of different texts under one key. A window whose hash no rival shares is in no other text,
    so only the parts of a text whose windows may be elsewhere go into the suffix arrays.
    """
    lens = np.array(list(map(len, texts)), "int64")
    n_windows = lens - LENGTH + 1
    first = np.cumsum(n_windows) - n_windows
    window_ids = np.repeat(least, n_windows)
    if not rivals:
        return window_ids, first, n_windows
    data = np.frombuffer(b"".join(texts), "uint8")
    begin = np.cumsum(lens) - lens
    members = np.array([x for r in rivals for x in r])
    group = np.repeat(np.arange(len(rivals)), [len(r) for r in rivals])
    n = n_windows[members]
    h = mix(window_hashes(data, ranges(begin[members], n)) + np.repeat(group, n).astype("uint64") * ODD_A)
    _, number, count = np.unique(h, return_inverse=True, return_counts=True)
    shared = count[number] > 1
    owner = np.repeat(np.arange(len(members)), n)
    inner = ranges(np.zeros(len(members), "int64"), n)
    new = shared & ~np.concatenate([[False], shared[:-1] & (owner[1:] == owner[:-1])])
    last = shared & ~np.concatenate([shared[1:] & (owner[1:] == owner[:-1]), [False]])
    raw = data.tobytes()
    job: dict[bytes, list] = {}
    size, key = 0, -1

    def settle() -> None:
        for parts, ids in zip(job.values(), least_ids(list(job), [min(m for _, m in p) for p in job.values()]), strict=True):
            for at, _ in parts:
                np.minimum(window_ids[at : at + len(ids)], ids, out=window_ids[at : at + len(ids)])

    for o, x, y in zip(owner[new].tolist(), inner[new].tolist(), inner[last].tolist(), strict=True):
        if group[o] != key:
            key = group[o]
            if size > ARRAY_BYTES:
                settle()
                job, size = {}, 0
        text = members[o]
        at = int(begin[text])
        part = raw[at + x : at + y + LENGTH]
        if part not in job:
            job[part] = []
            size += len(part)
        job[part].append((int(first[text]) + x, int(least[text])))
    if job:
        settle()
    return window_ids, first, n_windows


def removed_bytes(block: Block, spans: pa.Table) -> np.ndarray:
    edge = np.zeros(int(block.starts[-1]) + 1, "int64")
    for s, e in zip(spans.column("starts"), spans.column("ends"), strict=True):
        np.add.at(edge, np.frombuffer(s.as_buffer(), "<i8"), 1)
        np.add.at(edge, np.frombuffer(e.as_buffer(), "<i8"), -1)
    return np.cumsum(edge)[:-1] > 0


def report_block(blocks: pa.Table, spans: pa.Table) -> pa.Table:
    rows: list[tuple] = []
    for message in blocks.column("message"):
        block = Block(message.as_buffer())
        gone = removed_bytes(block, spans)
        for i, known, text, s in zip(block.ids.tolist(), block.known.tolist(), block.texts, block.starts.tolist(), strict=False):
            g = gone[s : s + len(text)]
            kept = np.frombuffer(text, "uint8")[~g].tobytes() if g.any() else text
            runs = int(g[:1].sum() + (g[1:] & ~g[:-1]).sum())
            rows.append((i if known else None, len(text), int(g.sum()), runs, hashlib.sha256(kept).hexdigest()))
    cols = [*zip(*rows, strict=True)] if rows else [[]] * 5
    kinds = [pa.int64()] * 4 + [pa.string()]
    return pa.table([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])


def whole_characters(text: bytes, gone: np.ndarray) -> str:
    """What is left; a character goes only if all its bytes do."""
    raw = np.frombuffer(text, "uint8")
    lead = (raw & 0xC0) != 0x80
    keep = ~gone
    of = np.cumsum(lead) - 1
    kept = np.zeros(int(lead.sum()), bool)
    np.logical_or.at(kept, of, keep)
    return raw[kept[of]].tobytes().decode("utf-8", "replace")


def cut_block(schema: pa.Schema):
    """The block's rows with the repeated passages cut out of their texts; n_chars, if there, follows."""

    def work(blocks: pa.Table, spans: pa.Table) -> pa.Table:
        out = []
        for message in blocks.column("message"):
            block = Block(message.as_buffer())
            gone = removed_bytes(block, spans)
            texts = []
            for old, text, s in zip(block.rows.column("text").to_pylist(), block.texts, block.starts.tolist(), strict=False):
                g = gone[s : s + len(text)]
                texts.append(whole_characters(text, g) if g.any() else old)
            rows = block.rows.set_column(block.rows.schema.get_field_index("text"), "text", pa.array(texts, pa.string()))
            if "n_chars" in rows.column_names:
                at = rows.schema.get_field_index("n_chars")
                rows = rows.set_column(at, "n_chars", pa.array([len(t or "") for t in texts], pa.int64()))
            out.append(rows.select(schema.names).cast(schema))
        return pa.concat_tables(out) if out else schema.empty_table()

    return work


def _between(x: float, bounds: tuple[int, int]) -> int:
    return int(min(bounds[1], max(bounds[0], x)))


def _spans(docs: DataFrame, heavy_blocks: int) -> tuple[DataFrame, DataFrame]:
    """The blocks, and the spans to remove from each."""
    spark = docs.sparkSession
    total = docs.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    parts = partitions_for(spark)
    buckets = int(max(parts, -(-total // _between(total / 2000, BUCKET_BYTES))))
    blocks = stage_bucketed(pack_blocks(docs, _between(total / 2000, BLOCK_BYTES)), "blocks", "block_id", parts)
    keys = blocks.mapInArrow(send_keys(buckets), "bucket long, block_id long, keys binary, several binary, sizes binary")
    marks = stage(keys.groupBy("bucket").applyInArrow(mark_shared(heavy_blocks), "block_id long, bucket long, marks binary"), "marks")
    sent = blocks.groupBy("block_id").cogroup(marks.groupBy("block_id")).applyInArrow(send_stretches(buckets), "bucket long, block_id long, keys binary, lens binary, data binary, counts binary, places binary, ids binary")
    spans = stage(sent.groupBy("bucket").applyInArrow(find_repeats, "block_id long, starts binary, ends binary"), "spans")
    release(marks)
    return blocks, spans


def report(docs: DataFrame, heavy_blocks: int = HEAVY_BLOCKS) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256: one row a document."""
    blocks, spans = _spans(docs.select("doc_id", "text"), heavy_blocks)
    return blocks.groupBy("block_id").cogroup(spans.groupBy("block_id")).applyInArrow(report_block, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def cut(docs: DataFrame, heavy_blocks: int = HEAVY_BLOCKS) -> DataFrame:
    """The documents with their repeated passages removed, all columns kept."""
    from pyspark.sql.pandas.types import to_arrow_schema

    blocks, spans = _spans(docs, heavy_blocks)
    return blocks.groupBy("block_id").cogroup(spans.groupBy("block_id")).applyInArrow(cut_block(to_arrow_schema(docs.schema)), docs.schema)
