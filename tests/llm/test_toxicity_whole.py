import random

import pytest

from semjoin.llm import toxicity

SF = "/root/testdata/sf0.1"


def figures(docs, labels, fairness, **params):
    model = toxicity.fit(docs, labels, fairness=fairness, **params)
    got = toxicity.score(docs, model).where("held_out").join(labels, "doc_id").collect()
    rows = toxicity.mention_changes(docs, labels, model).collect()
    hits, toxic = sum(r["predicted"] for r in got if r["toxic"]), sum(r["toxic"] for r in got)
    return hits / toxic, sum(r["false_mention"] for r in rows), sum(r["n"] for r in rows), max(abs(r["change"]) for r in rows)


def test_penalty_lowers_false_positives_on_neutral_mentions(spark):
    """Labels that lean against texts which name a group: without the penalty the name alone makes a text toxic."""
    rng, terms, rows, labels = random.Random(4), sorted(toxicity._next_terms()), [], []
    for i in range(3000):
        toxic = rng.random() < 0.4
        words = [f"w{rng.randrange(300)}" for _ in range(12)]
        if rng.random() < (0.8 if toxic else 0.02):
            words.append(rng.choice(terms))
        if toxic and rng.random() < 0.85:
            words.append(rng.choice(["idiot", "scum", "moron"]))
        rng.shuffle(words)
        rows.append((i, " ".join(words)))
        labels.append((i, int(toxic)))
    docs, marks = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, toxic int")
    plain, fair = figures(docs, marks, 0.0), figures(docs, marks, 20.0)
    assert plain[1] > 0.5 * plain[2] and fair[1] < 0.1 * fair[2] and fair[3] < 0.3 * plain[3]
    assert fair[0] > 0.75


def test_penalty_acts_on_the_tables(spark):
    docs, labels = (spark.read.parquet(f"{SF}/{t}.parquet") for t in ("documents", "labels"))
    plain, fair = figures(docs, labels, 0.0, max_train=2000), figures(docs, labels, 1.0, max_train=2000)
    print("held-out hits, false positives on neutral mentions, rows, largest change of a score:", plain, fair)
    assert fair[1] <= plain[1] and fair[3] <= plain[3] + 1e-9 and fair[0] >= plain[0] - 0.02


def test_tables(spark):
    none = spark.createDataFrame([], "doc_id long, text string")
    labels = spark.createDataFrame([], "doc_id long, toxic int")
    model = toxicity.fit(none, labels)
    assert toxicity.score(none, model).collect() == []
    odd = spark.createDataFrame([(1, None, 9.0), (1, "x " * 300_000, 9.0), (None, "", 9.0), (1, None, 9.0)], "doc_id long, text string, score double")
    got = [r["score"] for r in toxicity.score(odd, model).collect()]
    assert len(got) == 4 and len(set(got)) == 1 and 0 <= got[0] <= 1
    assert toxicity.fit(odd, spark.createDataFrame([(1, 1), (1, 0), (None, 1), (2, None)], labels.schema))[0] == pytest.approx(6.9, abs=0.1)
