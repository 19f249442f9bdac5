"""Parts of items that the benchmark holds many times, and parts without plain words enough."""

import random

import numpy as np

from semjoin.llm import decontaminate as D


def found(text, items):
    index = D.Index(items, D.WINDOW)
    return {x[0]: x[2] for x in D.leaks_in(text, index, D.Lexicon(index.words), D.MIN_COVER)}


def word(i):
    return "".join(chr(97 + int(c)) for c in f"{i:05d}")


def test_part_that_many_items_share():
    lead = " ".join(map(word, range(20)))
    items = [(k, f"{lead} " + " ".join(word(1000 + 100 * k + j) for j in range(10))) for k in range(60)]
    assert found(f"well then {lead} the end", items) == dict.fromkeys(range(60), 20)
    assert found("well then " + " ".join(map(word, range(14))), items) == {}


def test_words_that_repeat_without_end():
    items = [(1, "la " * 400), (2, "1 km 2 kg " + "la " * 16)]
    got = found("so " + "la " * 3000, items)
    assert got == {1: 400, 2: 16}


def test_part_between_the_slots():
    assert found("then " + "la " * 9 + "7 s", [(2, "1 km 2 kg " + "la " * 12)]) == {2: 9}
    assert found("9 km 8 kg " + "7 m 6 g " * 4, [(3, "1 km 2 kg 3 m 4 g " * 2)]) == {}


def test_cover_is_an_upper_bound():
    """What is reported is what is reported without the test of covered tokens."""
    rng = random.Random(4)
    words = ["ab", "cd", "ef", "gh", "5", "km", "7", "Bob", "ij"]
    items = [(k, " ".join(rng.choice(words) for _ in range(rng.randint(3, 30)))) for k in range(80)]
    index = D.Index(items, D.WINDOW)
    every = D.covered_enough
    hits = 0
    for _ in range(150):
        parts = [(lambda t: " ".join(t[(a := rng.randrange(len(t))) : a + rng.randint(4, 30)]))(rng.choice(items)[1].split()) for _ in range(3)]
        text = " zz ".join(parts)
        got = sorted(D.leaks_in(text, index, D.Lexicon(index.words), D.MIN_COVER))
        D.covered_enough = lambda i, e, c: np.ones(len(i.ids), bool)
        try:
            assert sorted(D.leaks_in(text, index, D.Lexicon(index.words), D.MIN_COVER)) == got
        finally:
            D.covered_enough = every
        hits += len(got)
    assert hits > 50
