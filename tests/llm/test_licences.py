import math
import re
from collections import Counter

import pytest
from pyspark.sql import functions as F

from semjoin.llm import licences

SF = "/root/testdata/sf0.01"


def terms(text):
    return [x for x in re.split("[^a-z0-9]+", (text or "").lower()) if x]


def passages(text):
    return set(re.split("\n", re.sub(r"([.!?;])[ \t]+", r"\1\n", text))) | set(re.split(r"\r?\n(?:[^\w\n]*\n)+", text)) | {text}


def slow_best(texts, min_cosine=0.8):
    """Best cosine of each text: every passage against every template."""
    every = [*licences.TEMPLATES, *licences.FULL_TEXTS]
    df = Counter(t for x in texts for t in set(terms(x)))
    vocabulary = {t for _, x in every for t in terms(x)}
    weights = lambda ts: {t: (1 + math.log(n)) * (math.log((len(texts) + 1) / ((df[t] if t in vocabulary else 0) + 1)) + 1) for t, n in Counter(ts).items()}
    norm = lambda w: math.sqrt(sum(x * x for x in w.values()))
    templates = [(name, weights(terms(x))) for name, x in every]
    out = []
    for x in texts:
        best = None
        for p in passages(x or ""):
            w = weights(terms(p))
            for i, (name, t) in enumerate(templates):
                cosine = round(sum(v * t.get(k, 0) for k, v in w.items()) / (norm(t) * norm(w)), 6) if w else 0
                if cosine >= min_cosine and (best is None or (cosine, -i) > best[:2]):
                    best = (cosine, -i, name)
        out.append(best and (best[2], best[0]))
    return out


def wrapped(text, width=60, mark="# "):
    lines, now = [], ""
    for w in text.split():
        if len(now) + len(w) > width:
            lines, now = [*lines, now], ""
        now += w + " "
    return "\n".join(mark + x.rstrip() for x in [*lines, now])


def test_cosines_equal_brute_force(spark):
    texts = [r["text"] for r in spark.read.parquet(f"{SF}/documents.parquet").where("text rlike '(?i)licen|permission|software' or doc_id % 25 = 0").orderBy("doc_id").collect()]
    texts += [None, "", "x", wrapped(licences.FULL_TEXTS[0][1]), wrapped(licences.TEMPLATES[5][1]) + "\n#\nimport os\nprint(1)\n", licences.FULL_TEXTS[2][1] + "\nmore", "Released under the MIT License."]
    texts += ["Licensed under the Apache License, Version 2.0 (the License); you may not use other files in compliance with anything"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: (r["licence"], r["cosine"]) for r in licences.licences(docs, F.lit(None).cast("string")).collect()}
    for i, want in enumerate(slow_best(texts)):
        assert got[i][0] == (want and want[0]) and (want is None or got[i][1] == pytest.approx(want[1], abs=2e-6)), texts[i]
    assert sum(x is not None for x in slow_best(texts)) > 8


def test_wrapped_notices_and_inheritance(spark):
    mit, gpl = licences.FULL_TEXTS[0][1], licences.TEMPLATES[5][1]
    rows = [
        (1, "r/LEGAL", mit), (2, "r/a/b.py", "plain code"), (3, "r/a/c.c", wrapped(gpl, 40, " * ") + "\n */\nint main() {}"), (4, "r/a/d.c", "no notice"),
        (5, None, mit), (6, None, "no notice"), (7, "s/x.py", wrapped(mit) + "\n\n" + "value = compute(other)\n" * 400), (8, "s/y.py", "no notice"), (1, "r/LEGAL", mit), (9, "t/COPYING.txt", gpl), (10, "t/u/v", None),
    ]
    docs = spark.createDataFrame([(*r, "clash") for r in rows], "doc_id long, path string, text string, k1 string")
    got = {r["doc_id"]: (r["licence"], r["how"]) for r in licences.licences(docs, F.col("path")).collect()}
    assert got == {
        1: ("MIT", "own"), 2: ("MIT", "inherited"), 3: ("GPL-3.0", "own"), 4: ("MIT", "inherited"), 5: ("MIT", "own"), 6: (None, "none"), 7: ("MIT", "own"), 8: (None, "none"),
        9: ("GPL-3.0", "own"), 10: ("GPL-3.0", "inherited"),
    }
    assert licences.licences(docs, F.col("path")).count() == len(rows)


def test_query_inherits_along_paths(spark, tmp_path):
    from semjoin.llm.queries import op3_license_scan

    rows = [(1, "r/LICENSE", licences.FULL_TEXTS[0][1]), (2, "r/a/b.py", "plain code"), (3, "s/c.py", "plain code")]
    spark.createDataFrame(rows, "doc_id long, path string, text string").write.parquet(f"{tmp_path}/documents.parquet")
    assert {r["doc_id"]: (r["licence"], r["how"]) for r in op3_license_scan(spark, str(tmp_path)).collect()} == {1: ("MIT", "own"), 2: ("MIT", "inherited"), 3: (None, "none")}
