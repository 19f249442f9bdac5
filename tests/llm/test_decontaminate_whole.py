import random
import re
import time

import numpy as np
import pytest

from semjoin.llm import decontaminate

ITEM = "the old mill by the river grinds corn for all farms of that wide valley and sells flour in small sacks to bakers who come each week from far away"


def leaks(docs, items, **params):
    index = decontaminate.Index(list(enumerate(items)), decontaminate.WINDOW)
    lexicon = decontaminate.Lexicon(index.words)
    return [{x[0]: x[1:] for x in decontaminate.leaks_in(d, index, lexicon, params.get("min_cover", 0.5))} for d in docs]


def test_tokens_put_in_or_left_out():
    words = ITEM.split()
    put_in = " ".join([*words[:10], "very", *words[10:20], "really", *words[20:]])
    left_out = " ".join(words[:10] + words[11:20] + words[21:])
    got = leaks([f"before {put_in} after", f"before {left_out} after", " ".join(reversed(words)), " ".join(words[:12])], [ITEM])
    assert [sorted(x) for x in got] == [[0], [0], [], []]
    assert got[0][0][1] == len(words) and got[1][0][1] == len(words) - 2


@pytest.mark.parametrize("old, new", [("Tom", "Mary Ann"), ("25", "twenty five"), ("25", "twenty-five"), ("25 kg", "31kg"), ("Tom", "Anna")])
def test_slots_of_another_length(old, new):
    item = "On the market Tom buys 25 kg of apples and then gives one half of them to his own sister at home"
    assert 0 in leaks([f"once more: {item.replace(old, new)} and so on"], [item])[0]


def test_short_items_inside_a_sentence():
    for item in ("Which river flows past the tower?", "Bolt and nut sit tight", "How many legs has a spider"):
        for before in ("She asked him ", "", "Then Paul said: ", "We met Anna Maria "):
            assert 0 in leaks([f"{before}{item} And they left."], [item])[0], (item, before)
    assert leaks(["How many wings has a fly, said the spider"], ["How many legs has a spider"]) == [{}]


def test_slots_must_agree():
    item = "A train leaves Paris at 9 and a bus leaves Paris at 10 so when do both of them meet on the road"
    again = item.replace("Paris", "Rome").replace("10", "12")
    mixed = again.replace("bus leaves Rome", "bus leaves Oslo")
    got = leaks([again, mixed, item.replace("9", "10")], [item])
    assert [sorted(x) for x in got] == [[0], [], []] and got[0][0][3] > 0


def canon(text):
    """Lower-case words and numbers only: (code, filler) with up to four numbers in a row folded."""
    out = []
    text = re.sub(r"(?<!\S)(?:[0-9]+(?:\s|$)){5,}", lambda m: re.sub(r"([0-9]+)", r"_\1", m[0]), text)
    for t in text.split():
        if re.fullmatch("[0-9]+", t):
            if out and out[-1][0] == "#":
                out[-1] = ("#", f"{out[-1][1]} {t}")
            else:
                out.append(("#", t))
        else:
            out.append((t, t))
    return out


def slow_cover(doc, item, window=8):
    """Most tokens of the item that one shift covers by runs of equal codes whose slots map one to one."""
    best, size = 0, min(window, len(item))
    for shift in range(-len(item), len(doc)):
        there, back, run, cover, ok = {}, {}, [], 0, True
        for at in range(len(item) + 1):
            if at < len(item) and 0 <= at + shift < len(doc) and doc[at + shift][0] == item[at][0]:
                run.append(at)
                continue
            if len(run) >= size:
                cover += len(run)
                for i in run:
                    if item[i][0] == "#":
                        ok &= there.setdefault(item[i][1], doc[i + shift][1]) == doc[i + shift][1] and back.setdefault(doc[i + shift][1], item[i][1]) == item[i][1]
            run = []
        best = max(best, cover if ok else 0)
    return best


def common(doc, item):
    """Length of the longest common subsequence of codes."""
    table = np.zeros((len(doc) + 1, len(item) + 1), int)
    for i, (x, _) in enumerate(doc):
        for j, (y, _) in enumerate(item):
            table[i + 1, j + 1] = max(table[i, j] + (x == y), table[i, j + 1], table[i + 1, j])
    return table[-1, -1]


def test_leaks_equal_brute_force():
    rng = random.Random(11)
    vocabulary = [f"w{chr(97 + i)}" for i in range(20)]
    line = lambda n: " ".join(rng.choice(vocabulary) if rng.random() < 0.85 else str(rng.randrange(100)) for _ in range(n))
    items = [line(rng.randint(5, 30)) for _ in range(25)]
    docs = []
    for _ in range(60):
        words = rng.choice(items).split()
        kind = rng.randrange(5)
        if kind == 1:
            swap = {x: str(rng.randrange(1000, 2000) * 2 + i % 2) for i, x in enumerate(sorted({w for w in words if w.isdigit()}))}
            words = [swap.get(w, w) for w in words]
        elif kind == 2:
            words[len(words) // 2] = "other"
        elif kind == 3:
            words = words[: rng.randint(1, len(words))]
        elif kind == 4:
            words.insert(len(words) // 2, "other")
        docs.append(f"{line(rng.randint(0, 9))} xx {' '.join(words)} yy {line(rng.randint(0, 9))}")
    for doc, got in zip(docs, leaks(docs, items), strict=True):
        d = canon(doc)
        want = {i for i, x in enumerate(items) if slow_cover(d, canon(x)) >= 0.5 * len(canon(x))}
        assert want <= set(got), doc
        assert all(common(d, canon(items[i])) >= 0.5 * len(canon(items[i])) for i in got)


@pytest.mark.parametrize("unit", ["", " km", " km 3 h", " ha"])
def test_hot_windows_take_little_time(unit):
    rng, began = random.Random(2), time.time()
    row = lambda n: " ".join(f"{rng.randrange(10**6)}{unit}" for _ in range(n))
    items = [row(200) for _ in range(200)]
    got = leaks([row(20_000), f"see {row(50)} {items[7]} {row(50)}", "ha " * 20_000], [*items, "ha " * 300])
    assert time.time() - began < 30
    assert got[1][7][3] == 0 and 200 in got[2]
    assert not any(set(x) - {7, 200} for x in got)


def test_rows_of_one_id_are_told_apart(spark):
    rows = [(1, f"see {ITEM}", "x"), (1, "clean words of its own", "y"), (2, None, "z"), (None, ITEM, "n"), (3, "long " * 50_000 + ITEM, "l")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, __h1 string")
    bench = spark.createDataFrame([(7, ITEM, 1), (8, None, 1), (None, "tiny words of no document at all", 1)], "item_id long, text string, doc_id int")
    kept = decontaminate.without_leaks(docs, bench)
    assert kept.columns == docs.columns and sorted(r["__h1"] for r in kept.collect()) == ["n", "y", "z"]
    assert sorted((str(r["doc_id"]), r["item_id"]) for r in decontaminate.leaks(docs, bench).collect()) == [("1", 7), ("3", 7), ("None", 7)]


def test_one_disagreeing_run_does_not_hide_a_chain():
    """The longest run, of three sentences, has another number than the six single ones, which are half of the item."""
    say = lambda k, n: f"s{chr(97 + k)} wa wb wc {n} wd we wf t{chr(97 + k)}"
    doc = [" ".join(say(k, 7) for k in range(3)), *[f"x{chr(97 + k)} {say(k, 9)}" for k in range(3, 9)]]
    assert leaks([" ".join(doc)], [" ".join(say(k, 5) for k in range(12))])[0][0][1:3] == (54, 108)


def test_a_longer_run_far_away_does_not_hide_a_chain():
    item = ITEM.split()
    doc = [*item[:11], *["x"] * 200, *item[:10], "y", *item[11:20]]
    assert leaks([" ".join(doc)], [ITEM])[0][0][:2] == (211, 19)


def test_fillers_that_disagree_leave_nothing_behind():
    doc, tokens = [(np.array(x), np.array(x), None) for x in ([5, 6, 6], [1, 2, 3])]
    tokens = (*tokens[:2], np.ones(3, bool))
    there, back = {1: 5}, {5: 1}
    assert decontaminate.fillers(doc, tokens, 0, 3, 0, there, back) is None and (there, back) == ({1: 5}, {5: 1})
    assert decontaminate.fillers(doc, tokens, 0, 2, 0, there, back) == 2 and there == {1: 5, 2: 6}


def slow_chain(doc, tokens, runs, span):
    """All chains, one after the other."""
    best = (0, 0)

    def value(pieces, starts):
        there, back, changed, cover = {}, {}, 0, 0
        for a, b, shift in pieces:
            cover += b - a
            for i in range(a, b):
                if tokens[2][i]:
                    x, y = tokens[0][i], doc[0][i + shift]
                    if there.setdefault(x, y) != y or back.setdefault(y, x) != x:
                        return (0, 0)
                    changed += x != y
        plain = {tokens[1][i] for a, b, _ in pieces for i in range(a, b) if not tokens[2][i]}
        near = any(all(abs(x - c) <= span for x in starts) for c in starts)
        return (cover, -changed) if near and (not changed or len(plain) >= decontaminate.PLAIN) else (0, 0)

    def walk(pieces, last, starts):
        nonlocal best
        best = max(best, value(pieces, starts))
        a, b, s = pieces[-1]
        for c, d, t in runs:
            if c > last[0] and c + t > last[0] + last[2]:
                for stop, go in {(b, max(c, b, b + s - t)), (min(b, c, c + t - s), c)}:
                    if a < stop and go < d:
                        walk([*pieces[:-1], (a, stop, s), (go, d, t)], (c, d, t), [*starts, c + t])

    for r in runs:
        walk([r], r, [r[0] + r[2]])
    return best[0], -best[1]


def test_no_chain_is_missed():
    rng, missed = np.random.default_rng(3), 0
    for _ in range(400):
        slots = rng.random(24) < 0.4
        own = np.where(slots, 100 + rng.integers(0, 6, 24), rng.integers(0, 9, 24))
        tokens = (own, np.where(slots, 99, own), slots)
        doc = (100 + rng.integers(0, 6, 60), None, None)
        runs = []
        for _ in range(rng.integers(2, 8)):
            a = int(rng.integers(0, 20))
            runs.append((a, int(rng.integers(a + 1, 25)), int(rng.integers(0, 36))))
        runs = list(dict.fromkeys(runs))
        span = int(rng.integers(8, 40))
        want = slow_chain(doc, tokens, runs, span)
        cover, changed, _ = decontaminate.chain(doc, tokens, runs, span)
        assert (cover, -changed) >= (want[0], -want[1])
        assert all(decontaminate.chain(doc, tokens, runs, span, need)[0] >= need for need in range(want[0] + 1))
        missed += decontaminate.near_chain(doc, tokens, runs, span)[0] < want[0]
    assert missed > 20
