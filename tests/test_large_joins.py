"""Joins whose work must not grow with their pairs."""

import time
import tracemalloc

import numpy as np
from pyspark.sql import functions as F

from semjoin import catalogue
from semjoin.operators import classifier, clustering, relational


def test_label_totals_equal_the_pairs(spark):
    rows = [(i, [None, "x", "y", "unknown"][i % 4]) for i in range(40)] + [(None, "x"), (5, "z")]
    t = spark.createDataFrame(rows, "id long, label string")
    a, b = t.where("id is null or id % 3 <> 0"), t.where("id is null or id % 5 <> 1")
    pairs = classifier.label_equi_join(a, b).groupBy("label").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("a_id") % 97 + F.col("b_id") % 89).alias("s"))
    want = sorted(map(tuple, pairs.collect()))
    for salt in (1, 8):
        assert sorted(map(tuple, classifier.label_join_totals(a, b, F.col("id") % 97, F.col("id") % 89, salt).collect())) == want
    assert len(want) > 2


def test_segments_of_many_customers(spark, tmp_path):
    """200,000 customers of one segment: 10,000,000,000 pairs, of which none is formed."""
    spark.range(200_000).select(F.col("id").alias("c_custkey"), F.lit("s").alias("c_mktsegment")).write.parquet(f"{tmp_path}/customer.parquet")
    began = time.time()
    for name in ("label_join_segment", "label_join_segment_salted"):
        (row,) = catalogue.QUERIES[name](spark, str(tmp_path)).collect()
        evens, odds = range(0, 200_000, 2), range(1, 200_000, 2)
        assert row["n"] == 10**10 and row["s"] == 10**5 * (sum(x % 97 for x in evens) + sum(x % 89 for x in odds))
    assert time.time() - began < 60


def test_broadcast_is_the_smaller_side(spark, tmp_path):
    spark.range(50).select(F.col("id").alias("c_custkey")).write.parquet(f"{tmp_path}/customer.parquet")
    spark.range(3_000).select(F.col("id").alias("o_orderkey"), (F.col("id") % 40).alias("o_custkey")).write.parquet(f"{tmp_path}/orders.parquet")
    got = catalogue.QUERIES["join_hint_broadcast"](spark, str(tmp_path))
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert got.count() == 3_000 and "leftHint=(strategy=broadcast)" in plan and "rightHint" not in plan
    a, b = relational.broadcast_smaller(spark.range(5).withColumnRenamed("id", "x"), spark.range(4), most=3)
    assert "Hint" not in a.join(b, F.col("x") == F.col("id"))._jdf.queryExecution().optimizedPlan().toString()


def test_stream_join_compares_what_is_near(spark, tmp_path):
    """20,000 rows a side with one label, an hour apart: 400,000,000 pairs have the label, 100,000 are near in time."""
    rows = spark.range(40_000).select(F.col("id").alias("event_id"), F.lit(1).cast("long").alias("user_id"), F.when(F.col("id") % 2 == 0, "error").otherwise("signup").alias("event_type"), F.timestamp_micros((F.col("id") / 2).cast("long") * 3_600_000_000 + 1_800_000_000).cast("timestamp_ntz").alias("ts"), F.lit(1.0).alias("value"))
    rows.write.parquet(f"{tmp_path}/events.parquet")
    began = time.time()
    got = catalogue.QUERIES["stream_label_join"](spark, str(tmp_path))
    assert time.time() - began < 90
    near = lambda i: [j for j in range(i - 2, i + 3) if 0 <= j < 20_000]
    assert {tuple(r) for r in got.select("a_id", "b_id").collect()} == {(2 * i, 2 * j + 1) for i in range(20_000) for j in near(i)} and got.count() == 99_994


def test_density_blocks_give_the_one_tree(spark):
    rng = np.random.default_rng(5)
    x = np.concatenate([rng.integers(-40, 40, (150, 3)) + c for c in (0, 300, 900)] + [rng.integers(-2000, 2000, (30, 3))])
    points = spark.createDataFrame([(1000 - i, v.tolist()) for i, v in enumerate(x)], "id long, v array<bigint>")
    want = clustering.hdbscan_labels(x[::-1], 5, 3)
    got = {r["id"]: r["cluster"] for r in clustering.hdbscan(points, 5, 3, block=70).collect()}
    assert [got[k] for k in sorted(got)] == want.tolist() and len(set(want) - {-1}) >= 3


def test_density_clustering_of_many_points(spark):
    """Over 20,000 points, in two far groups of equal points and one that falls off the nearer of them."""
    points = spark.range(20_003).selectExpr("id", "array(IF(id = 20002, -900000, (id % 2) * 1000000), id % 2) AS v")
    got = clustering.hdbscan(points, 5, 3, block=6_000).collect()
    assert len(got) == 20_003 and {(r["id"] % 2, r["cluster"]) for r in got if r["id"] < 20_002} == {(0, 0), (1, 1)} and [r["cluster"] for r in got if r["id"] == 20_002] == [0]


def test_trees_of_blocks_and_between_blocks_hold_the_one_tree():
    rng = np.random.default_rng(1)
    for most in (3, 50, 10**6):
        x = rng.integers(-most, most + 1, (110, 2))
        core = clustering.core_squares(x, 0, len(x), 3)
        assert (core == np.sort(clustering.squares(x, x), 1)[:, 2]).all()
        edges, cuts = [], [(a, min(a + 27, 110)) for a in range(0, 110, 27)]
        for k, (a, b) in enumerate(cuts):
            w, i, j = clustering.tree_of(x[a:b], core[a:b])
            edges.append((w, i + a, j + a))
            for c, d in cuts[k + 1 :]:
                w, i, j = clustering.tree_between(x[a:b], x[c:d], core[a:b], core[c:d])
                assert len(w) == b - a + d - c - 1
                edges.append((w, i + a, j + c))
        want, got = clustering.least_tree(110, *clustering.tree_of(x, core)), clustering.least_tree(110, *[np.concatenate(e) for e in zip(*edges, strict=True)])
        assert all((a == b).all() for a, b in zip(want, got, strict=True))


def test_vectors_are_gathered_without_rows_of_python(spark):
    """A list of Python's numbers takes many times the bytes of its vector."""
    points = spark.range(0, 30_000, 1, 3).selectExpr("29999 - id AS id", "transform(sequence(1, 32), d -> id * 32 + d) AS v")
    tracemalloc.start()
    ids, x = clustering._gathered(points)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert x.dtype == np.int32 and (ids == np.arange(30_000)).all() and (x[:, 0] == (29_999 - ids) * 32 + 1).all() and x.shape == (30_000, 32)
    assert most < 6 * x.nbytes, most / x.nbytes


def test_nearest_center_is_exact():
    rng = np.random.default_rng(2)
    for most in (3, 2**40):
        x, centers = rng.integers(-most, most, (300, 4)), rng.integers(-most, most, (20, 4))
        centers[7] = centers[3]
        slow = [min(range(20), key=lambda i, v=v: (sum((int(p) - int(q)) ** 2 for p, q in zip(v, centers[i], strict=True)), i)) for v in x]
        if most == 3:
            assert clustering.nearest(x, centers).tolist() == slow
        else:
            assert clustering.nearest(x // 2**12, centers // 2**12).tolist() == [min(range(20), key=lambda i, v=v: (sum((int(p) - int(q)) ** 2 for p, q in zip(v // 2**12, centers[i] // 2**12, strict=True)), i)) for v in x]


def test_tag_clusters_of_many_parts(spark, tmp_path):
    """40,000 parts and 200 clusters, of which equal texts are dealt once a round."""
    words = F.array(*[F.lit(x) for x in ("large bolt", "red gear", "hot ring", "blue rod")])
    spark.range(40_000).select(F.col("id").alias("p_partkey"), words[(F.col("id") % 4).cast("int")].alias("p_name"), F.concat(F.lit("Brand#"), F.col("id") % 25).alias("p_brand")).write.parquet(f"{tmp_path}/part.parquet")
    began = time.time()
    got = catalogue.QUERIES["cluster_join_w3_all"](spark, str(tmp_path))
    assert got.count() == got.distinct().count() == 40_000 + 2 * 1_600 and time.time() - began < 60
