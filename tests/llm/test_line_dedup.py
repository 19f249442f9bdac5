import random

from semjoin.llm import linededup


def brute(rows, min_words=5):
    lines = [((i, k), x.strip(" \t\n\x0b\f\r")) for i, t in rows if i is not None for k, x in enumerate((t or "").split("\n"))]
    lines = [(at, x) for at, x in lines if len(x.split()) >= min_words]
    first = {}
    for at, x in lines:
        first[x] = min(first.get(x, at), at)
    out = set()
    for at, x in lines:
        near = [first[y] for y in first if y != x and linededup.within_one_edit(x, y)]
        if near and min(near) < first[x]:
            out.add((*at, *min(near), 1))
        elif first[x] < at:
            out.add((*at, *first[x], 0))
    return out


def documents():
    rng, words = random.Random(3), "alpha beta gamma delta épsilon zeta eta theta".split()
    base = [" ".join(rng.choice(words) for _ in range(rng.randint(3, 12))) for _ in range(25)]
    rows = []
    for i in range(60):
        text = []
        for _ in range(rng.randint(0, 5)):
            x = rng.choice(base)
            if rng.random() < 0.5:
                p = rng.randrange(len(x))
                x = x[:p] + rng.choice(["", x[p] + "q", "z", "ü"]) + x[p + 1 :]
            text.append(rng.choice(["", "  "]) + x)
        rows.append((i, "\n".join(text)))
    return [*rows, (None, base[0]), (200, None), (201, ""), (202, "aaaa aaaa aaaa aaaa aaab"), (203, "aaaa aaaa aaaa aaaa aaba"), (204, "aaaa aaaa aaaa aaaa aaa")]


def test_equals_brute_force(spark):
    rows = documents()
    docs = spark.createDataFrame([(i, t, "x") for i, t in rows], "doc_id long, text string, h string")
    got = {tuple(r) for r in linededup.duplicate_lines(docs).collect()}
    assert got == brute(rows) and any(r[4] for r in got)
    cleaned = {r["doc_id"]: r["text"] for r in linededup.without_lines(docs, linededup.duplicate_lines(docs)).collect()}
    gone = {}
    for d, k, *_ in got:
        gone.setdefault(d, set()).add(k)
    for i, t in rows:
        left = t if i not in gone else "\n".join(x for k, x in enumerate(t.split("\n")) if k not in gone[i])
        assert (i not in cleaned and not left.strip()) if i in gone and not left.strip() else cleaned[i] == left


def test_beyond_the_broadcast_bound(spark, monkeypatch):
    """Frequent classes by broadcast and rare ones by shuffle give the same rows as all by broadcast."""
    rows = documents()
    monkeypatch.setattr(linededup, "BROADCAST_ROWS", 0)
    monkeypatch.setattr(linededup, "HOT_SHARE", 25)
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert {tuple(r) for r in linededup.duplicate_lines(docs).collect()} == brute(rows)
    seen = spark.createDataFrame([(i, 1, 1) for i in range(90)] + [(i, 2, 2) for i in range(10)] + [(0, 3, 3)], "doc_id long, h long, h2 long")
    classes = spark.createDataFrame([(1, 1, 90), (2, 2, 10)], "h long, h2 long, n long")
    assert linededup._with_classes(seen, classes).groupBy("h", "n").count().orderBy("h").collect() == [(1, 90, 90), (2, 10, 10)]


def test_empty_table(spark):
    docs = spark.createDataFrame([], "doc_id long, text string")
    assert linededup.duplicate_lines(docs).collect() == []


def test_deletion_hashes():
    whole, cut = linededup.deletion_hashes("abcbé")
    for p in range(5):
        assert int(cut[p]) == linededup.deletion_hashes("abcbé"[:p] + "abcbé"[p + 1 :])[0]
