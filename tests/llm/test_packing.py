"""The tokenizer against the library, and the share of pieces that the least squares solution places."""

from __future__ import annotations

import json
import random
from collections import Counter

import public_tokenizers
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from tracegraph.llm import packing_nnls as pk

PATH = public_tokenizers.path("byte_bpe_50k.json")
SLOW = Tokenizer.from_file(PATH)


def _slow(text: str) -> list[int]:
    return SLOW.encode(text, add_special_tokens=False).ids


def test_encoder_equals_the_library_on_the_whole_vocabulary():
    with open(PATH, encoding="utf-8") as f:
        words = [pk._bytes(t).decode("utf-8", "ignore") if t != "<|endoftext|>" else t for t in json.load(f)["model"]["vocab"]]
    rnd = random.Random(1)
    rnd.shuffle(words)
    encode = pk.encoder(PATH)
    for k in range(0, len(words), 50):
        for glue in ("", " "):
            text = glue.join(words[k : k + 50])
            assert encode(text).tolist() == _slow(text)


@settings(max_examples=400, deadline=None)
@given(st.lists(st.one_of(st.text(max_size=30), st.sampled_from(["<|endoftext|>", " ", "\n\n", "'ll", " ", "̀e", "1234", "\U0001f600", "<|end"])), max_size=12))
def test_encoder_equals_the_library_on_random_texts(parts):
    text = "".join(parts)
    assert pk.encoder(PATH)(text).tolist() == _slow(text)


@pytest.mark.parametrize("text", ["\n " * 60_000, " " * 150_000 + "a", "ab" * 100_000])
def test_encoder_equals_the_library_on_long_runs(text):
    assert pk.encoder(PATH)(text).tolist() == _slow(text)


@pytest.mark.parametrize("seed,pieces,lengths", [(1, 1_000, 2047), (2, 20_000, 2047), (3, 5_000, 700)])
def test_the_solution_places_most_pieces(seed, pieces, lengths):
    rnd = random.Random(seed)
    histogram = Counter(rnd.randint(1, lengths) if rnd.random() < 0.7 else rnd.randint(1, 60) for _ in range(pieces))
    p = pk.make_plan(dict(histogram), 2048)
    used = Counter()
    for times, combo in p.chosen:
        for n in combo:
            used[n] += times
    assert used == histogram and sum(p.placed.values()) == pieces
    assert p.placed["solved"] > 0.5 * pieces


def test_counts_of_a_small_problem():
    """Lengths 6, 4 and 3 fill a window of 10 as (6, 4) and (4, 3, 3): the solution is known."""
    p = pk.make_plan({6: 50, 4: 70, 3: 40}, 10)
    counts = Counter()
    for times, combo in p.chosen:
        counts[tuple(sorted(combo, reverse=True))] += times
    assert counts == Counter({(6, 4): 50, (4, 3, 3): 20})
