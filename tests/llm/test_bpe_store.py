"""The store of encoded words when it is full, and the two ways to find the next merge."""

import random

import public_tokenizers
from polymetric.llm import bpe
from tokenizers import Tokenizer

PATH = public_tokenizers.path("byte_bpe_50k.json")


def test_words_that_recur_outlive_a_full_store(monkeypatch):
    monkeypatch.setattr(bpe, "MOST_KEPT", 4)
    pairs, merged = bpe.BytePairs(PATH), []
    monkeypatch.setattr(pairs, "merge", lambda word, merge=pairs.merge: merged.append(word) or merge(word))
    text = "".join(f" often w{chr(97 + i)}" for i in range(20))
    assert pairs.decode(pairs.encode(text)) == text
    assert merged.count(" often") == 1 and len(merged) == 21
    assert len(pairs.ids) + len(pairs.ids.older) <= 8


def test_short_and_long_words_merge_as_the_library_does(monkeypatch):
    pairs, library, rnd = bpe.BytePairs(PATH), Tokenizer.from_file(PATH), random.Random(5)
    words = ["".join(rnd.choice(["the", "ing", "un", "a", "e", "\u00e9", "\u4e2d", "0", "zz"]) for _ in range(n)) for n in range(1, 60) for _ in range(5)]
    want = [library.encode(x, add_special_tokens=False).ids for x in words]
    assert [pairs.encode(x).tolist() for x in words] == want
    monkeypatch.setattr(bpe, "SHORT", 1)
    pairs.ids.clear()
    assert [pairs.encode(x).tolist() for x in words] == want
    assert [pairs.decode(pairs.encode(x)) for x in ["", *words]] == ["", *words]
