"""Spans and words that share a hash keep their own ids."""

import numpy as np
import pyarrow as pa
import pytest
from tokenizers import Tokenizer

from finegrain.llm import pieces, textkernel, token_files
from finegrain.llm.entries import piece_model, tokenizer_file
from finegrain.llm.textkernel import blocks, equal_spans, hash_spans


def binary_words(bits: int) -> list[str]:
    """Two words of ``2**bits`` letters whose hashes agree under every polynomial modulo 2**64 with an odd base, for enough bits."""
    signs = [bin(i).count("1") % 2 for i in range(1 << bits)]
    return ["".join("ab"[s] for s in signs), "".join("ba"[s] for s in signs)]


def encoded(encoder, texts):
    out = []
    for _, data, offsets in blocks(pa.array(texts)):
        ids, counts = encoder.encode(data, offsets)
        out += [x.tolist() for x in np.split(ids, np.cumsum(counts)[:-1])]
    return out


SAMPLE = ["one two three two one", "three  one\ntwo", "", None, "1234567 12345678 123456789", "x" * 5000 + " one", "y" * 5000 + " one", " ".join(binary_words(11))]


@pytest.mark.parametrize("weak", [None, 0, 3])
def test_words_of_equal_hash(monkeypatch, weak):
    model = open(tokenizer_file("word_bpe_49k.json"), encoding="utf-8").read()
    library = Tokenizer.from_str(model)
    if weak is not None:  # all spans have one of a few hashes
        monkeypatch.setattr(token_files, "hash_spans", lambda d, s, e: hash_spans(d, s, e) & np.uint64(weak))
    fast = token_files.FastWords(model)
    for _ in range(2):
        assert encoded(fast, SAMPLE) == [library.encode(t or "", add_special_tokens=False).ids for t in SAMPLE]


@pytest.mark.parametrize("weak", [None, 0, 3])
def test_pieces_of_equal_hash(monkeypatch, weak):
    if weak is not None:
        monkeypatch.setattr(pieces, "hash_spans", lambda d, s, e: hash_spans(d, s, e) & np.uint64(weak))
        monkeypatch.setattr(pieces, "mix", lambda z: z & np.uint64(0))
    encoder = pieces.BlockEncoder(piece_model())
    for _ in range(2):
        assert encoded(encoder, SAMPLE) == [encoder.model.encode(t or "") for t in SAMPLE]


def test_hashes_and_comparisons():
    rng = np.random.default_rng(3)
    words = sorted({bytes(rng.integers(97, 100, rng.integers(1, 40), dtype=np.uint8)) for _ in range(4000)} | {b"z" * n for n in range(1, 600)} | {w.encode() for w in binary_words(11)})
    data = np.frombuffer(b"".join(words), np.uint8)
    size = np.array([len(w) for w in words])
    ends = np.cumsum(size)
    h = hash_spans(data, ends - size, ends)
    assert len(np.unique(h)) == len(words)
    shifted = np.frombuffer(b"???" + data.tobytes(), np.uint8)
    assert (hash_spans(shifted, ends - size + 3, ends + 3) == h).all()
    assert equal_spans(data, ends - size, shifted, ends - size + 3, size).all()
    for at in (0, 1):
        edited = data.copy()
        edited[(ends - 1) if at else (ends - size)] ^= 1
        assert not equal_spans(data, ends - size, edited, ends - size, size).any()
    assert textkernel.hash_word("é") != textkernel.hash_word("e")


def test_lookup_does_not_copy_the_table():
    import tracemalloc

    table = textkernel.SpanTable(lambda spans: (np.arange(len(spans), dtype=np.uint32), np.ones(len(spans), np.int64)))
    table._flat, table._used = np.zeros(1 << 22, np.uint32), (1 << 22) - 8  # 16 MB of ids
    data = np.frombuffer(b"abcabc", np.uint8)
    starts, ends = np.array([0, 1, 3, 5]), np.array([1, 3, 4, 6])
    tracemalloc.start()
    try:
        ids, sizes = table.lookup(data, starts, ends, hash_spans(data, starts, ends), lambda i: i)
        peak = tracemalloc.get_traced_memory()[1]
    finally:
        tracemalloc.stop()
    assert sizes.tolist() == [1, 1, 1, 1] and ids[0] == ids[2] and len(set(ids.tolist())) == 3
    assert peak < 1 << 20


def test_partitions_give_memory_back(monkeypatch):
    from finegrain.llm import batches

    seen = []
    monkeypatch.setattr(batches, "release", lambda: seen.append(1))
    assert list(batches.releasing(lambda rows: (r + 1 for r in rows))(iter([1, 2]))) == [2, 3] and seen == [1]
