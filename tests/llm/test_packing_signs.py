"""Ids of the packing tokenizer over all code points, and spans that grow in number with the tokens."""

from test_operators import WORD_BPE, check_pieces

from pathlore.llm import packing, registry


def test_every_code_point_as_the_library():
    tok = packing.ChunkTokenizer(WORD_BPE)
    points = [chr(c) for c in range(0x110000) if not 0xD800 <= c < 0xE000]
    for at in range(0, len(points), 50_000):
        texts = [f"Ab {c}c A{c}" for c in points[at : at + 50_000]]
        wrong = [t for t, x, e in zip(texts, tok.encode_batch(texts), tok.model.encode_batch(texts, add_special_tokens=False), strict=True) if x.tolist() != e.ids]
        assert not wrong


def test_spans_grow_with_the_tokens(spark, monkeypatch):
    docs = registry.table(spark, "/root/testdata/sf0.001", "documents")
    monkeypatch.setattr(packing, "SPAN_TOKENS", 500)
    check_pieces(packing.pack(docs, WORD_BPE).collect(), [(r.doc_id, r.text) for r in docs.collect()])
