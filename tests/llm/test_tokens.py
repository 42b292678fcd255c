"""Words that the cache has not seen: ids of the library, and no call of it for what known parts make up."""

from __future__ import annotations

import random

import numpy as np
import pyarrow as pa
import pytest
from tokenizers import Tokenizer

from subpopgrid.llm import tokens

PARTS = ["a", "The", "é", "ÿ", "œ", "ß", "Σ", "'", "'s", "'ll", "###", ".", "...", "!?", "\n", "\n\n", "\t", " ", "  ", "\u00a0", "\u3000", "\r", "23", "½", "ª", "_", "<|endoftext|>", "<|", "日本", "🙂", "\x0b", "\x85", "İ"]


@pytest.mark.parametrize(("name", "spaced"), [("byte_bpe_50k.json", True), ("word_bpe_49k.json", False)])
def test_ids_of_odd_texts(name, spaced):
    r = random.Random(5)
    texts = ["".join(r.choice(PARTS) if r.random() < 0.7 else r.choice("\n ") for _ in range(r.randrange(40))) for _ in range(3000)]
    path = tokens.vocabulary(name)
    library, rows = Tokenizer.from_file(path), []
    for _, _, flat, counts in tokens.Encoder(path, spaced).slices(pa.array(texts), 2):
        rows += [x.tolist() for x in np.split(flat, np.cumsum(counts)[:-1])]
    assert rows == [[*library.encode(t, add_special_tokens=False).ids, 2] for t in texts]


def test_new_words_of_known_parts_need_no_library(monkeypatch):
    e = tokens.Encoder(tokens.vocabulary("byte_bpe_50k.json"), True)
    list(e.slices(pa.array(["one two\nthree ### one### four###", "three four ###"]), 2))
    calls = []
    monkeypatch.setattr(e, "whole", lambda t, whole=e.whole: calls.append(t) or whole(t))
    list(e.slices(pa.array(["one two### four\nthree one\nthree"]), 2))
    assert {*calls} <= {".", ","}
