"""Containment, similarity and encoders against plain Python; noise against its coins."""

import random

from pyspark.sql import functions as F

from semjoin.functions import text as T
from semjoin.models import NoisyModel, Prompt, RulebookModel, contradicts, parse_pairs
from semjoin.operators import baselines


def test_containment_join_is_exact(spark):
    rng = random.Random(3)
    word = lambda: rng.choice(["a", "b", "cc", "", "d\n", "é"])
    texts = [" ".join(word() for _ in range(rng.randrange(40))) for _ in range(60)] + [None, ""]
    items = [t[i : i + rng.randrange(1, 25)] for t in texts if t for i in (0, len(t) // 3)] + [None, "a", "none of these words is here"]
    docs = spark.createDataFrame(list(enumerate(texts)), "a_id long, text string")
    passages = spark.createDataFrame(list(enumerate(items)), "b_id long, passage string")
    want = sorted((i, j) for i, t in enumerate(texts) for j, p in enumerate(items) if t is not None and p is not None and p in t)
    assert any(len(p.split(" ")) >= 5 for p in items if p)
    for bound in (1 << 20, 0):
        assert sorted(map(tuple, baselines.containment_join(docs, passages, bound).collect())) == want


def test_similar_pairs_lose_none(spark):
    rng = random.Random(5)
    rows = [(i, " ".join(rng.choice("red blue bolt gear ring rod plate x y z".split()) for _ in range(rng.randrange(6)))) for i in range(80)]
    df = spark.createDataFrame(rows, "id long, text string")
    vectors = {r["id"]: r["v"] for r in df.select("id", T.ENCODERS["hash-word-64"](F.col("text")).alias("v")).collect()}
    dot = lambda x, y: sum(p * q for p, q in zip(x, y, strict=True))
    for num, den in ((1, 2), (9, 10), (1, 1)):
        want = sorted((a, b) for a, x in vectors.items() for b, y in vectors.items() if dot(x, y) > 0 and dot(x, y) ** 2 * den * den >= num * num * dot(x, x) * dot(y, y))
        assert sorted(map(tuple, baselines.similar_pairs(df, df, "hash-word-64", num, den).collect())) == want


def test_similar_pairs_of_nothing(spark):
    df = spark.createDataFrame([(1, ""), (2, None)], "id long, text string")
    assert baselines.similar_pairs(df, df, "hash-word-64", 1, 2).count() == 0


def test_fields_are_cut_not_rows(spark):
    df = spark.createDataFrame([(1, "x" * 500 + "|bolt"), (2, "x" * 400 + "|bolt"), (3, None)], "id long, text string")
    one, two, none = (r["v"] for r in df.orderBy("id").select(T.embed_words(F.col("text")).alias("v")).collect())
    assert one == two and sum(one) == 2 and sum(none) == 0


def test_own_encoder(spark):
    T.register_encoder("length-2", lambda: lambda texts: [[len(x), 0.5] for x in texts])
    try:
        from semjoin.plans.advisor import resolve

        assert resolve("embedding", "use length-2").value == "length-2"
        df = spark.createDataFrame([(1, "abc"), (2, None)], "id long, text string")
        got = df.orderBy("id").select(T.ENCODERS["length-2"](F.col("text")).alias("v")).collect()
        assert [r["v"] for r in got] == [[3_000_000, 500_000], [0, 500_000]]
    finally:
        del T.ENCODERS["length-2"]


def test_noise_adds_and_leaves_out(spark):
    a, b = tuple(f"x {i}" for i in range(30)), tuple(f"y {i}" for i in range(30))
    noisy = NoisyModel(RulebookModel("equal"), 7, spurious=0.1)
    pairs, _ = parse_pairs(noisy.complete(Prompt("match", "same", a, b)).text, 30, 30)
    assert 50 < len(pairs) < 130
    labels = NoisyModel(RulebookModel("equal"), 7, unsure=1.0).complete(Prompt("classify", "which", a, (), a)).text
    assert labels.count("unknown") == 30


def test_time_frames_contradict():
    note = "person 4 says first notice was on 2024-01-12"
    told = "person {} was told in the {} part of the month"
    assert [contradicts(note, told.format(p, t)) for p, t in ((4, "early"), (4, "middle"), (4, "late"), (5, "early"))] == [True, True, False, False]
