"""The feature baseline: proposed and extracted features, equality as a hash join, drawn pairs, a precision target."""

import random

import duckdb
import pytest

from semjoin import catalogue
from semjoin.models import RulebookModel, ScriptedModel
from semjoin.operators import baselines
from semjoin.operators.baselines import Literal


def sides(spark, n=60):
    rows = lambda kind: spark.createDataFrame([(i, f"the {('le' if i % 4 == 1 else 'der' if i % 4 == 2 else 'el' if i % 4 == 3 else 'of')} {kind}{i}") for i in range(n)], "id long, text string")
    return rows("a"), rows("b")


def test_features_are_proposed_extracted_and_joined_by_hash(spark):
    a = spark.createDataFrame([(i, f"person {i % 5} says first notice was on 2024-01-{10 + i % 9}") for i in range(80)], "id long, text string")
    b = spark.createDataFrame([(i, f"person {i % 5} was told on 2024-01-{8 + i % 4:02d}") for i in range(80)], "id long, text string")
    got = baselines.model_feature_cnf_join(a, b, "the two notes cannot both be true", RulebookModel("contradiction"), sample_size=3000)
    assert got["features"] == ["class"] and any(len(c) == 1 and c[0].distance == "equal" for c in got["clauses"]) and got["bound"] >= 0.9
    assert "Cartesian" not in got["survivors"]._jdf.queryExecution().toString() and "NestedLoop" not in got["survivors"]._jdf.queryExecution().toString()
    day = lambda t: t[-10:]
    person = lambda t: t.split()[1]
    want = {(x["id"], y["id"]) for x in a.collect() for y in b.collect() if person(x["text"]) == person(y["text"]) and day(y["text"]) < day(x["text"])}
    assert {(r["a_id"], r["b_id"]) for r in got["matches"].collect()} == want
    stages = {r["stage"]: r["n"] for r in got["calls"].groupBy("stage").count().withColumnRenamed("count", "n").collect()}
    assert stages["propose"] == 1 and stages["extract"] == 8 and stages["feature"] == 3000 and stages["verify"] == got["survivors"].count() == 80 * 16


def test_a_precision_target_saves_verification(spark):
    a, b = (x.withColumn("f", (x["id"] % 4).cast("string")) for x in sides(spark))
    literal = [Literal("f", "equal", 0.0)]

    class Same(RulebookModel):
        def complete(self, prompt):
            import json

            number = lambda t: int("".join(c for c in t if c.isdigit())) % 4
            return self.reply(prompt, json.dumps([[i, j] for i, x in enumerate(prompt.a) for j, y in enumerate(prompt.b) if number(x) == number(y)]))

    got = baselines.feature_cnf_join(a, b, literal, "x", Same("equal"), sample_size=3000, precision_target=0.9)
    assert got["precision_bound"] >= 0.9 and got["calls"].where("stage = 'verify'").count() == 0 and got["matches"].count() == 60 * 15


def test_drawn_pairs(spark):
    a, b = sides(spark, 40)
    fa, fb = a.selectExpr("id as a_id", "text as a_text"), b.limit(3).selectExpr("id as b_id", "text as b_text")
    assert baselines.drawn_pairs(fa, fb, 60).distinct().count() == 60 and baselines.drawn_pairs(fa, fb, 600).count() == 120
    assert baselines.drawn_pairs(fa, fb.where("false"), 60).count() == 0


def test_no_proposal_means_all_pairs(spark):
    a, b = sides(spark, 3)
    assert baselines.propose_features(a, b, "x", ScriptedModel(["nothing to say"]))[0] == []


@pytest.mark.parametrize("lit", [Literal("f", "missing_word", 0.0), Literal("f", "missing_word", 1.0), Literal("f", "jaccard", 0.0), Literal("f", "jaccard", 0.4), Literal("f", "jaccard", 0.75)])
def test_word_candidates_lose_no_pair(spark, lit):
    """Pairs that meet on rare words are those of the nested loop, with empty, null, repeated and hot words."""
    rng = random.Random(4)
    text = lambda: rng.choice([None, "", "!!"]) if rng.random() < 0.1 else " ".join(rng.choice("the the the Ring rod bolt gear anvil über b#7".split()) for _ in range(rng.randint(1, 6)))
    fa = spark.createDataFrame([(i, text()) for i in range(60)], "a_id long, a_f string")
    fb = spark.createDataFrame([(i, text()) for i in range(50)], "b_id long, b_f string")
    pairs = lambda x: sorted(tuple(r) for r in x.select("a_id", "b_id").collect())
    want = pairs(fa.crossJoin(fb).where(baselines.cnf_holds([[lit]])))
    assert pairs(baselines.cnf_candidates(fa, fb, [[lit]])) == want and want


def test_candidates_over_whole_tables(spark):
    con = duckdb.connect()
    for t in ("part", "conversations", "embeddings"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '/root/testdata/sf0.01/{t}.parquet'")
    for name in ("cnf_candidates_w3", "cnf_candidates_w7", "label_groups_equal_all"):
        got = catalogue.QUERIES[name](spark, "/root/testdata/sf0.01")
        want = con.execute(catalogue.ORACLES[name]).df()[got.columns]
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.itertuples(index=False))) and len(want)
