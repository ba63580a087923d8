"""Chunks of texts as arrays: what they hold, and words that share a hash."""

from __future__ import annotations

import random
import tracemalloc

import numpy as np

from exactsum.llm import superkmer as S


def test_a_chunk_holds_no_object_for_each_word():
    rng = random.Random(31)
    words = [f"w{k}" for k in range(50_000)]
    texts = [" ".join(rng.choices(words, k=2000)).encode() for _ in range(500)]  # 1,000,000 words
    tracemalloc.start()
    try:
        sent = list(S.chunk_rows(list(range(500)), texts, 20, 3, 8, np.zeros(0, np.uint64)))
        chunk = tracemalloc.get_traced_memory()[1]
        tracemalloc.reset_peak()
        S.bucket_spans([runs for _, _, runs in sent if runs], 20)
        bucket = tracemalloc.get_traced_memory()[1]
    finally:
        tracemalloc.stop()
    assert chunk < 72 * 1_000_000 and bucket < 130 * 1_000_000  # bytes a word


def test_words_of_one_hash_stay_apart(monkeypatch):
    texts = [b"", b" ab cd\tab  ef ", b"cd", b"gh\xc3\xa9 ab gh\xc3\xa8 abc\n"]
    plain = S.run_hash
    for bits in (64, 1, 0):
        monkeypatch.setattr(S, "run_hash", lambda v, b, e, bits=bits: plain(v, b, e) & np.uint64((1 << bits) - 1))
        read = S.Words(texts, 2)
        assert read.enough.tolist() == [False, True, False, True] and read.sizes.tolist() == [4, 4]
        want = [w for t in texts for w in t.split() if len(t.split()) > 1]
        assert [read.joined(np.array([k])) for k in read.flat] == want and len(set(read.flat.tolist())) == len(set(want))
        assert read.joined(read.flat) == b" ".join(want)
    assert len(S.Words([], 1).flat) == 0 == len(S.Words([b" \n"], 0).flat)
