import dataclasses

import numpy as np
import pytest
from pyspark.sql import functions as F

from semjoin import catalogue
from semjoin.functions import measures as M
from semjoin.functions.text import serialize
from semjoin.models import UNKNOWN, LanguageModel, NoisyModel, Prompt, ReplayModel, RulebookModel, ScriptedModel, parse_choice, parse_labels, parse_list, parse_pairs
from semjoin.operators import baselines, classifier, clustering
from semjoin.operators import cluster_join as cj
from semjoin.plans import tuning
from semjoin.plans.advisor import JoinOptions, resolve
from semjoin.plans.api import BudgetError, semantic_join
from semjoin.plans.invoke import block_prompts, calls_of, pairs_of, run_prompts
from semjoin.workloads import workload

SF = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def w1(spark):
    return workload(spark, SF, "w1")


@pytest.fixture(scope="module")
def w2(spark):
    return workload(spark, SF, "w2")


@pytest.fixture(scope="module")
def w3(spark):
    return workload(spark, SF, "w3")


def pairs(df):
    return {(r["a_id"], r["b_id"]) for r in df.collect()}


def profile_rows(spark, rows):
    return spark.createDataFrame(rows, "ca int, cb int, na long, nb long, bypassed boolean, n_match long, n_cmp long")


def test_workload_sizes(w1, w2, w3):
    got = [(w.a.count(), w.b.count(), w.truth.count()) for w in (w1, w2, w3)]
    assert got == [(50, 50, 1220), (100, 100, 579), (250, 10, 264)]


def test_threshold_is_strict(spark):
    rows = profile_rows(spark, [(0, 0, 9, 9, False, 0, 25), (1, 0, 9, 9, False, 1, 25), (2, 0, 9, 9, False, 5, 100), (3, 0, 9, 9, False, 25, 25), (4, 0, 2, 9, True, 0, 0)])
    kept = lambda t: {r["ca"] for r in cj.filter_pairs(rows, t).collect()}
    assert kept(0) == {0, 1, 2, 3, 4} and kept(4) == {1, 2, 3, 4} and kept(5) == {2, 3, 4} and kept(100) == {3, 4}


def test_bypass(spark):
    pairs_ = spark.createDataFrame([(0, 5, 0, 30), (1, 6, 0, 30), (-1, 40, 0, 30)], "ca int, na long, cb int, nb long")
    assert {r["ca"]: r["bypassed"] for r in cj.profile_plan(pairs_, 6).collect()} == {0: True, 1: False, -1: True}


def test_unknown_never_joins(spark):
    rows = spark.createDataFrame([(1, UNKNOWN), (2, "x"), (3, "x")], "id long, label string")
    assert pairs(classifier.label_equi_join(rows, rows)) == {(2, 2), (2, 3), (3, 2), (3, 3)} == pairs(classifier.label_equi_join(rows, rows, 4))


def test_parsers():
    assert parse_labels('[[0, "A"], [1, "zzz"], [3, "b"], [3, "a"]]', 4, ["a", "b", UNKNOWN]) == (["a", UNKNOWN, UNKNOWN, UNKNOWN], "ok")
    assert parse_labels("no", 2, ["a"])[1] == "malformed" and parse_pairs("[[0, 1], [9, 9]]", 1, 2) == ([(0, 1)], "dropped")
    assert parse_list('[" A ", "a", "unknown", "b"]')[-1] == UNKNOWN and len(parse_list('[" A ", "a", "b"]')) == 3 and parse_list("x") == [UNKNOWN]
    assert parse_choice("Use all-MiniLM-L6-v2.", ("all-mpnet-base-v2", "all-MiniLM-L6-v2")) == "all-MiniLM-L6-v2" and parse_choice("label or cluster", ("label", "cluster")) is None


@pytest.mark.parametrize("raw", ["", "label, or else cluster", "nothing", "[broken"])
def test_unclear_replies_fall_back(raw):
    assert (resolve("strategy", raw).value, resolve("strategy", raw).source) == ("cluster", "fallback")


def test_override_costs_no_call(spark, w3):
    class Forbidden(LanguageModel):
        name = "forbidden"

        def complete(self, prompt):
            assert prompt.kind == "classify", "an override must not be asked for"
            return RulebookModel("tag").complete(prompt)

    r = semantic_join(w3.a, w3.b, w3.predicate, Forbidden(), JoinOptions(force_strategy="label", label_table=True))
    assert r.calls.where("stage = 'advisor'").count() == 0 and r.decisions[0].source == "override" and r.pairs.count() == 250


def test_serialize(spark):
    df = spark.createDataFrame([("x" * n, None, "a|b", [1]) for n in (399, 400, 401)], "s string, n string, p string, l array<int>")
    got = [r[0] for r in df.select(serialize(df)).collect()]
    assert [g.split("|")[0] for g in got] == ["x" * 399, "x" * 400, "x" * 400] and got[0].endswith("||a|b|[1]")


def test_cluster_count():
    assert [clustering.cluster_count(50, r) for r in tuning.RATIOS] == [2, 2, 3, 5] and clustering.cluster_count(10, 0.025) == 2 and clustering.cluster_count(250, 0.1) == 25


def test_perfect_model_agrees_everywhere(w2):
    model, truth = RulebookModel(w2.rule), pairs(w2.truth)
    assert pairs(cj.cluster_join(w2.a, w2.b, w2.predicate, model, JoinOptions(filter_threshold=0))["matches"]) == truth
    for size, n in ((10, 100), (15, 49), (20, 25)):
        matches, calls = baselines.block_join(w2.a, w2.b, w2.predicate, model, (size, size))
        assert pairs(matches) == truth and calls.count() == n
    assert pairs(baselines.block_join(w2.a, w2.b, w2.predicate, model, (15, 15), buckets=4)[0]) == truth


def test_higher_thresholds_never_add(w2):
    last, tokens = None, None
    for t in (0, 5, 20):
        got = cj.cluster_join(w2.a, w2.b, w2.predicate, RulebookModel(w2.rule), JoinOptions(filter_threshold=t))
        now, cost = pairs(got["matches"]), M.token_cost(got["calls"].where("stage = 'match'")).first()["tokens"]
        assert last is None or (now <= last and cost <= tokens)
        last, tokens = now, cost


def test_overflow_splits(spark, w3):
    a, b = w3.a.limit(40), w3.b
    answers = run_prompts(block_prompts(a, b, None, (20, 10), "match"), "match", w3.predicate, RulebookModel("tag", 12), "match")
    ids = {r["id"] for r in a.collect()}
    assert pairs(pairs_of(answers)) == {p for p in pairs(w3.truth) if p[0] in ids} and calls_of(answers).where("status = 'overflow'").count() > 0


def test_adaptive_blocks(w2):
    s = baselines.Stats(250, 10, 130, 111, 3, 8)
    assert baselines.choose_blocks(s, 2600, 0.11) == (20, 10) and baselines.choose_blocks(s, 2700, 0.11) == (21, 10)
    matches, calls, rounds = baselines.adaptive_block_join(w2.a, w2.b, w2.predicate, lambda m: RulebookModel(w2.rule, m), 1000)
    assert pairs(matches) == pairs(w2.truth) and rounds[0][5] > 0 and rounds[-1][5] == 0


def test_cnf(w2, w3):
    rows = [{baselines.Literal("f", "equal", 0.0): i % 3 == 0, "match": i % 3 == 0} for i in range(1200)]
    lit = next(iter(rows[0]))
    clauses, bound = baselines.fit_cnf(rows, [lit])
    assert clauses == [[lit]] and 0.9 <= bound <= 1.0
    useless = [{lit: True, "match": i % 3 == 0} for i in range(1200)]
    assert baselines.fit_cnf(useless, [lit])[0] == []
    assert baselines.recall_bound(90, 100, 0.05) == pytest.approx(0.9 - (np.log(20) / 200) ** 0.5)


def test_projection_is_for_embedding_only(w3):
    seen = []

    class Spy(RulebookModel):
        def complete(self, prompt: Prompt):
            assert prompt.kind != "match" or all("Brand#" in t for t in prompt.a)
            return super().complete(prompt)

    options = JoinOptions(filter_threshold=0)
    got = cj.cluster_join(w3.a.limit(60), w3.b, w3.predicate, Spy("tag"), options, projected=True)
    assert got["calls"].where("stage = 'project'").count() == 3 and not seen
    plain = cj.cluster_join(w3.a, w3.b, w3.predicate, RulebookModel("tag"), JoinOptions())["matches"].count()
    assert cj.cluster_join(w3.a, w3.b, w3.predicate, RulebookModel("tag"), JoinOptions(), projected=True)["matches"].count() > plain


def test_vacuous_label_join(w2):
    labels = tuple(f"person {i}" for i in range(9))
    r = semantic_join(w2.a, w2.b, w2.predicate, RulebookModel(w2.rule), JoinOptions(force_strategy="label", labels=labels))
    s = M.score(r.pairs, w2.truth).first()
    assert r.pairs.count() == 1102 and s["recall"] == 100 and round(s["precision"], 1) == 52.5


def test_grid_equals_single_runs(w2):
    options, model = JoinOptions(), RulebookModel(w2.rule)
    grid = {r["threshold"]: r for r in tuning.cluster_grid(w2.a, w2.b, w2.truth, w2.predicate, model, options, "w2", (0.05,), (0, 5, 20)).collect()}
    for t, r in grid.items():
        got = cj.cluster_join(w2.a, w2.b, w2.predicate, model, dataclasses.replace(options, filter_threshold=t))
        s = M.score(got["matches"], w2.truth).first()
        assert (s["tp"], s["fp"], s["fn"]) == (r["tp"], r["fp"], r["fn"]) and M.token_cost(got["calls"]).first()["tokens"] == r["tokens"]


def test_noise_lowers_recall_with_block_area(w2):
    recalls = [M.score(baselines.block_join(w2.a, w2.b, w2.predicate, NoisyModel(RulebookModel(w2.rule), 7, 0.05, 0.0006), (b, b))[0], w2.truth).first()["recall"] for b in (5, 15, 25)]
    assert recalls == sorted(recalls, reverse=True) and recalls[0] > recalls[2]


def test_no_double_billing(spark, w2):
    r = semantic_join(w2.a, w2.b, w2.predicate, RulebookModel(w2.rule), JoinOptions())
    n = r.calls.count()
    r.pairs.count()
    assert r.calls.count() == n and r.calls.agg(F.countDistinct("call_id")).first()[0] == n


def test_replay_and_scripts():
    base = ScriptedModel(["[]"])
    model = ReplayModel(base)
    p = Prompt("match", "x", ("a",), ("b",))
    assert model.complete(p) == model.complete(p)
    with pytest.raises(AssertionError):
        base.complete(p)


def test_budget(w2):
    with pytest.raises(BudgetError):
        semantic_join(w2.a, w2.b, w2.predicate, RulebookModel(w2.rule), JoinOptions(max_tokens=10))
    with pytest.raises(ValueError):
        baselines.pairwise_join(w2.a, w2.b, w2.predicate, RulebookModel(w2.rule), max_calls=100)


def test_edges(spark, w2):
    none = w2.a.where("false")
    model = RulebookModel(w2.rule)
    assert cj.cluster_join(none, w2.b, w2.predicate, model, JoinOptions())["matches"].count() == 0
    assert baselines.block_join(w2.a, none, w2.predicate, model)[0].count() == 0
    same = spark.createDataFrame([(i, "person 1 says first notice was on 2024-01-02") for i in range(20)], "id long, text string")
    late = spark.createDataFrame([(1, "person 1 was told on 2024-01-01")], "id long, text string")
    assert cj.cluster_join(same, late, w2.predicate, model, JoinOptions())["matches"].count() == 20


def test_partitions_do_not_matter(spark, w2):
    want = None
    for n in (1, 5):
        spark.conf.set("spark.sql.shuffle.partitions", n)
        got = pairs(cj.cluster_join(w2.a.repartition(n), w2.b, w2.predicate, RulebookModel(w2.rule), JoinOptions())["matches"])
        assert want is None or got == want
        want = got
    spark.conf.set("spark.sql.shuffle.partitions", 4)


def test_density_clusters():
    rng = np.random.default_rng(1)
    x = np.concatenate([rng.normal(c, 0.3, (20, 2)) for c in ((0, 0), (10, 0), (0, 10))] + [np.array([[50.0, 50.0], [-40.0, 30.0]])])
    got = clustering.hdbscan_labels(x, 5, 3)
    groups = [set(got[i : i + 20]) - {-1} for i in (0, 20, 40)]
    assert all(len(g) == 1 for g in groups) and len(set.union(*groups)) == 3 and set(got[60:]) == {-1}
    assert set(clustering.hdbscan_labels(x[:3], 5, 3)) == {-1}


def test_measures(spark):
    p = spark.createDataFrame([], "a_id long, b_id long")
    t = spark.createDataFrame([(1, 1)], "a_id long, b_id long")
    s = M.score(p, t).first()
    assert s["precision"] is None and s["f1"] == 0 and M.score(t, p).first()["recall"] is None


def test_plans(spark):
    c = spark.read.parquet(f"{SF}/customer.parquet").select(F.col("c_custkey").alias("id"), F.col("c_mktsegment").alias("label"))
    plan = classifier.label_equi_join(c, c)._jdf.queryExecution().toString()
    assert "Cartesian" not in plan and "BroadcastNestedLoop" not in plan and "IsNotNull(c_mktsegment)" in plan


@pytest.mark.parametrize("name", ["agg_cube", "join_asof", "stream_label_join", "stream_session", "kmeans_embeddings_k4", "cluster_join_w2", "label_join_language", "adaptive_blocks_w3", "fn_html", "filter_pairs_t005"])
def test_query_equals_sql(spark, name):
    import duckdb

    con = duckdb.connect()
    for t in catalogue.load.__globals__["TABLES"]:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    got = catalogue.QUERIES[name](spark, SF)
    cur = con.execute(catalogue.ORACLES[name])
    names = [x[0] for x in cur.description]
    assert sorted(names) == sorted(got.columns)
    assert sorted(str(tuple(r[c] for c in names)) for r in got.collect()) == sorted(map(str, cur.fetchall()))
