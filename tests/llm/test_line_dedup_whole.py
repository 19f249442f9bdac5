"""Short lines and lines without spaces: equal ones go, near ones from NEAR_CHARS code points on."""

import random

from semjoin.llm import linededup, queries


def brute(rows, near_chars, min_words=5):
    lines = [((i, k), x.strip(" \t\n\x0b\f\r")) for i, t in rows if i is not None for k, x in enumerate((t or "").split("\n"))]
    lines = [(at, x) for at, x in lines if x]
    near_line = lambda x: len(x.split()) >= min_words or len(x) >= near_chars
    first = {}
    for at, x in lines:
        first[x] = min(first.get(x, at), at)
    out = set()
    for at, x in lines:
        near = [first[y] for y in first if y != x and near_line(x) and near_line(y) and linededup.within_one_edit(x, y)]
        if near and min(near) < first[x]:
            out.add((*at, *min(near), 1))
        elif first[x] < at:
            out.add((*at, *first[x], 0))
    return out


def test_equals_brute_force(spark, tmp_path):
    rng = random.Random(5)
    han = "".join(chr(0x4E00 + rng.randrange(500)) for _ in range(30))
    base = ["Read more here", "x", "All rights reserved", "  ", "one two three four five", "one two three four fivE", "averylongtokenwithoutanyspaces1", "averylongtokenwithoutanyspaces2", "Page 12", "Page 13", han, han[:7] + "Z" + han[8:], han[:12], han[:11] + "Z"]
    rows = [(i, "\n".join(rng.choice(["", " "]) + rng.choice(base) for _ in range(rng.randint(0, 4)))) for i in range(40)] + [(None, "x"), (99, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    docs.write.parquet(str(tmp_path / "documents.parquet"))
    got = {tuple(r) for r in queries.op9_line_dedup(spark, str(tmp_path)).collect()}
    assert got == brute(rows, linededup.NEAR_CHARS)
    texts = dict(rows)
    gone = {(texts[d].split("\n")[k].strip(), e) for d, k, _, _, e in got}
    assert {("Read more here", 0), ("x", 0), (han[:12], 0)} <= gone and any(len(x.split()) == 1 and e for x, e in gone)
