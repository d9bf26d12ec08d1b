"""The packing tokenizer's memory: a chunk is parted once, forgetting changes nothing, batches are cut by bytes."""

import numpy as np
import public_tokenizers
import pyarrow as pa

from pathlore.llm import packing

WORD_BPE = public_tokenizers.path("word_bpe_49k.json")
TEXTS = ["It's a foo_bar, isn't it?  Été\n\ttwo two", "", "naïve 12ab34 x... end", "two, foo_bar 'quoted' ÀB", " \n"]


def test_chunks_are_parted_once(monkeypatch):
    tok = packing.ChunkTokenizer(WORD_BPE)
    seen: list[str] = []
    own = packing.ChunkTokenizer.encode_chunks
    monkeypatch.setattr(packing.ChunkTokenizer, "encode_chunks", lambda self, distinct, *a: (seen.extend(distinct.to_pylist()), own(self, distinct, *a))[1])
    for _ in range(2):
        got = [x.tolist() for x in tok.encode_batch(TEXTS)]
        assert got == [tok.model.encode(t, add_special_tokens=False).ids for t in TEXTS]
    assert len(seen) == len(set(seen))


def test_forgetting_changes_no_ids(monkeypatch):
    monkeypatch.setattr(packing, "REMEMBERED", 3)
    monkeypatch.setattr(packing, "CHUNKS", 2)
    tok = packing.ChunkTokenizer(WORD_BPE)
    for _ in range(2):
        for t in TEXTS:
            (got,) = tok.encode_batch([t])
            assert got.tolist() == tok.model.encode(t, add_special_tokens=False).ids


def test_batches_are_cut_by_bytes():
    batch = pa.RecordBatch.from_pydict({"doc_id": list(range(6)), "text": ["aa", None, "é" * 20, "", "b", "c" * 5]}, schema=pa.schema([("doc_id", pa.int64()), ("text", pa.string())]))
    parts = [p.column("doc_id").to_pylist() for p in packing.slices(batch, 6)]
    assert parts == [[0, 1], [2], [3, 4, 5]] and np.concatenate(parts).tolist() == list(range(6))
    assert [p.num_rows for p in packing.slices(batch.slice(1, 0), 6)] == []
