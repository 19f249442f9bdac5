"""Cut replies lose no row, conditions keep their meaning, clusterings do not depend on size switches."""

import numpy as np
import pytest

from semjoin.models import UNKNOWN, RulebookModel
from semjoin.operators import classifier, clustering
from semjoin.plans import invoke
from semjoin.plans.advisor import JoinOptions
from semjoin.plans.sqlapi import conjuncts, sql


def rows(spark, n):
    return spark.createDataFrame([(i, f"an item {'bolt' if i % 2 else 'gear'} x") for i in range(n)], "id long, text string")


def test_overflowing_label_batches_are_split(spark):
    got, calls = classifier.classify(rows(spark, 50), ["bolt", "gear", UNKNOWN], "the tag describes the item", RulebookModel("tag", 12), 25)
    assert {r["id"]: r["label"] for r in got.collect()} == {i: "bolt" if i % 2 else "gear" for i in range(50)}
    assert calls.where("status = 'overflow'").count() > 0
    none, calls = classifier.classify(rows(spark, 5), ["bolt", "gear", UNKNOWN], "x", RulebookModel("tag", 1), 5)
    assert [r["label"] for r in none.collect()] == [UNKNOWN] * 5 and calls.where("status = 'abstained'").count() == 5


def test_a_single_pair_that_overflows_is_on_record(spark):
    a, b = rows(spark, 2), spark.createDataFrame([(9, "bolt")], "id long, text string")
    answers = invoke.run_prompts(invoke.block_prompts(a, b, None, (2, 1), "match"), "match", "x", RulebookModel("tag", 1), "match")
    assert invoke.pairs_of(answers).count() == 0 and invoke.calls_of(answers).where("status = 'abstained'").count() == 1


def test_batches_are_numbered_in_buckets_by_count(spark, monkeypatch):
    assert invoke.batches(rows(spark, 100), 10).count() == 10
    monkeypatch.setattr(invoke, "BUCKET_ROWS", 20)
    got = invoke.batches(rows(spark, 100), 10).collect()
    assert len({r["blk"].split("-")[0] for r in got}) == 5 and sorted(x["id"] for r in got for x in r["items"]) == list(range(100))


def test_conditions_keep_their_meaning(spark):
    rows(spark, 6).createOrReplaceTempView("things")
    spark.createDataFrame([(0, "bolt"), (1, "gear")], "id long, text string").createOrReplaceTempView("marks")
    for where in ("things.id BETWEEN 1 AND 4", "things.id = 1 OR things.id = 2 AND marks.id = 99", "NOT (things.id = 3) AND marks.text <> 'a AND things.b'", "things.id % 2 = marks.id AND things.id > 0"):
        got = sql(spark, f"SELECT things.id AS a, marks.id AS b FROM things SEMANTIC JOIN marks ON MATCHES('the tag describes the item') WHERE {where}", RulebookModel("tag"), JoinOptions(force_strategy="cluster", filter_threshold=0))
        want = spark.sql(f"SELECT things.id AS a, marks.id AS b FROM things JOIN marks ON contains(concat(' ', things.text, ' '), concat(' ', marks.text, ' ')) WHERE {where}")
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect())), where
    assert len(conjuncts(spark, "a BETWEEN 1 AND 2 AND b = 'x AND y' AND (c = 1 OR d = 2)")) == 3


def test_hot_labels_are_dealt(spark, monkeypatch):
    labelled = spark.createDataFrame([(i, "x" if i < 90 else "y") for i in range(100)], "id long, label string")
    monkeypatch.setattr(classifier, "HOT_ROWS", 10)
    assert classifier.salt_for(labelled) == 9 and classifier.salt_for(labelled.where("false")) == 1
    assert classifier.label_equi_join(labelled, labelled, 9).count() == 90 * 90 + 100


def test_kmeans_means_are_exact(spark):
    big = 2**60 + 1
    points = spark.createDataFrame([(1, [big]), (2, [-big])], "id long, v array<bigint>")
    assert clustering.kmeans(points.where("id = 1"), 1, rounds=1).count() == 1
    assert clustering._towards_zero(3 * big, 3) == big and clustering._towards_zero(-7, 2) == -3


def slow_tree(x, k):
    """Weights of a minimum spanning tree over mutual reachability, by sorting all pairs."""
    d = np.sqrt(((x[:, None].astype(float) - x[None]) ** 2).sum(-1))
    core = np.sort(d, axis=1)[:, k - 1]
    root, out = list(range(len(x))), []
    find = lambda i: i if root[i] == i else find(root[i])
    for w, i, j in sorted((max(d[i, j], core[i], core[j]), i, j) for i in range(len(x)) for j in range(i)):
        a, b = find(i), find(j)
        if a != b:
            root[a], out = b, [*out, w]
    return out


def test_density_clusters_split_where_the_tree_says(spark):
    rng = np.random.default_rng(3)
    x = np.concatenate([rng.normal(c, 1.0, (40, 3)) for c in (0, 30, 60)])
    got = clustering.hdbscan_labels(x, 5, 4)
    cut = sorted(slow_tree(x, 4))[-2]
    root = list(range(len(x)))
    assert cut > 10 and all(len(set(got[i : i + 40]) - {-1}) == 1 for i in (0, 40, 80)) and len(set(got) - {-1}) == 3 and root


def test_density_clustering_does_not_switch_by_size(spark):
    points = spark.createDataFrame([(i, [i % 7, i // 7]) for i in range(60)], "id long, v array<bigint>")
    with pytest.raises(ValueError):
        clustering.hdbscan(points, max_points=50)
    got = clustering.hdbscan(points, cells=True, max_points=25).collect()
    assert sorted(r["id"] for r in got) == list(range(60))
