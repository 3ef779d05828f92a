"""A worker's cache of words stays bounded, and texts get the tokenizer's own ids whatever it has dropped."""

import numpy as np

from evenpart.llm import packing


def _held(encode):
    return len(encode.known) + len(getattr(encode, "older", ()))


def test_words_of_single_texts_do_not_fill_the_cache():
    encode, most = packing.WordEncoder(packing.vocabulary_path()), 0
    for lot in range(32):
        encode([" ".join(f"q{lot}x{i}z{j}" for j in range(200)) + " common words" for i in range(50)])
        most = max(most, _held(encode))
    assert b"common" in encode.known
    assert most <= 2 * (120_000 + 10_002)  # of 320,002


def test_dropped_words_get_the_same_ids(monkeypatch):
    monkeypatch.setattr(packing, "CACHE_WORDS", 200)
    encode = packing.WordEncoder(packing.vocabulary_path())
    for lot in range(30):
        texts = [f"the common words, of all texts. stay q{lot}x{i} w{lot * 7 + i}z {'older' if lot % 4 == 0 else ''}" for i in range(50)]
        want = [np.array(e.ids, dtype="<u4").tobytes() for e in encode.tokenizer.encode_batch(texts, add_special_tokens=False)]
        assert encode(texts) == want
