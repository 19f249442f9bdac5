"""Cluster join: clusters of each side, cluster pairs, sampled match rates, blocks of the pairs that stay."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from semjoin.functions.text import ENCODERS, order_key
from semjoin.models import LanguageModel
from semjoin.operators import clustering
from semjoin.plans.advisor import JoinOptions
from semjoin.plans.invoke import block_prompts, calls_of, pairs_of, row_prompts, run_prompts
from semjoin.sources.tables import keep


def project(a: DataFrame, b: DataFrame, predicate: str, model: LanguageModel, options: JoinOptions) -> tuple[DataFrame, DataFrame]:
    """a with embed_text: what the model expects the partner in B to look like. Matching still sees text."""
    from semjoin.functions.text import bottom_n

    sample = [(r["id"], r["text"]) for r in bottom_n(b, options.advisor_sample, options.seed).collect()]
    answers = run_prompts(row_prompts(a, options.project_batch, "project", sample, options.buckets), "project", predicate, model, "project")
    out = a.join(answers.where("row = 'answer'").select(F.col("a_id").alias("id"), F.col("answer").alias("embed_text")), "id", "left")
    return out.withColumn("embed_text", F.coalesce("embed_text", "text")), calls_of(answers)


def embed(rows: DataFrame, encoder: str = "hash-word-64") -> DataFrame:
    text = F.col("embed_text") if "embed_text" in rows.columns else F.col("text")
    return rows.select("id", ENCODERS[encoder](text).alias("v"))


def cluster_side(rows: DataFrame, options: JoinOptions, encoder: str = "hash-word-64", method: str = "kmeans") -> DataFrame:
    """rows (id, text) with their cluster. Each side is clustered by itself."""
    points = keep(embed(rows, encoder), "embedded")
    if method == "hdbscan":
        got = clustering.hdbscan(points)
    else:
        k = clustering.cluster_count(points.count(), options.cluster_ratio, most=options.max_clusters)
        got = clustering.kmeans(points, k, options.seed, options.kmeans_rounds)
    return keep(rows.select("id", "text").join(got, "id"), "clustered")


def cluster_pairs(a: DataFrame, b: DataFrame) -> DataFrame:
    """(ca, na, cb, nb): all pairs of clusters; both sides have a row for each cluster only."""
    sizes = lambda x, c, n: x.groupBy(F.col("cluster").alias(c)).agg(F.count(F.lit(1)).alias(n))
    return sizes(a, "ca", "na").crossJoin(sizes(b, "cb", "nb"))


def profile_plan(pairs: DataFrame, min_profile_size: int = 6) -> DataFrame:
    """Pairs with a cluster that is smaller than min_profile_size, or with noise, bypass the filter."""
    return pairs.withColumn("bypassed", (F.least("na", "nb") < min_profile_size) | (F.col("ca") < 0) | (F.col("cb") < 0))


def pair_samples(side: DataFrame, pairs: DataFrame, own: str, s: int, seed: int = 7, pool_factor: int | None = 4) -> DataFrame:
    """(ca, cb, items): s rows of the side's cluster for each pair, lowest by md5 of seed, pair and id,
    out of a pool of pool_factor * s rows of the cluster (None: out of the whole cluster)."""
    pool = side
    if pool_factor is not None:
        w = Window.partitionBy("cluster").orderBy(order_key(seed, "id"), "id")
        pool = side.withColumn("rn", F.row_number().over(w)).where(F.col("rn") <= pool_factor * s)
    drawn = pairs.select("ca", "cb", F.col(own).alias("cluster")).join(pool.select("cluster", "id", "text"), "cluster")
    w = Window.partitionBy("ca", "cb").orderBy(order_key(seed, "ca", "cb", "id"), "id")
    return drawn.withColumn("rn", F.row_number().over(w)).where(F.col("rn") <= s).groupBy("ca", "cb").agg(F.sort_array(F.collect_list(F.struct("id", "text"))).alias("items"))


def profile_pairs(plan: DataFrame, a: DataFrame, b: DataFrame, predicate: str, model: LanguageModel, s: int = 5, seed: int = 7, pool_factor: int | None = 4) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(pairs with sa, sb, n_match, n_cmp; sampled matches; calls): one small join for each pair not bypassed."""
    asked = plan.where(~F.col("bypassed"))
    left = pair_samples(a, asked, "ca", s, seed, pool_factor).withColumnRenamed("items", "a")
    right = pair_samples(b, asked, "cb", s, seed, pool_factor).withColumnRenamed("items", "b")
    prompts = keep(left.join(right, ["ca", "cb"]).select(F.concat_ws(":", F.lit("profile"), "ca", "cb").alias("call_id"), "ca", "cb", "a", "b"), "profile-prompts")
    answers = run_prompts(prompts, "match", predicate, model, "profile")
    found = answers.where("row = 'pair'").groupBy("ca", "cb").agg(F.count(F.lit(1)).alias("n_match"))
    sizes = prompts.select("ca", "cb", F.size("a").alias("sa"), F.size("b").alias("sb"))
    out = plan.join(sizes, ["ca", "cb"], "left").join(found, ["ca", "cb"], "left")
    zero = F.lit(0).cast("long")
    out = out.select("ca", "cb", "na", "nb", "bypassed", F.coalesce("sa", F.lit(0)).alias("sa"), F.coalesce("sb", F.lit(0)).alias("sb"), F.coalesce("n_match", zero).alias("n_match"), F.coalesce(F.col("sa").cast("long") * F.col("sb"), zero).alias("n_cmp"))
    return out, pairs_of(answers), calls_of(answers)


def match_rate(n_match: Column, sa: Column, sb: Column) -> Column:
    return F.try_divide(n_match.cast("double"), (sa * sb).cast("double"))


def passes(threshold: int | Column) -> Column:
    """Kept unless the match rate is lower than the threshold (hundredths), in integers."""
    return F.col("bypassed") | ~(100 * F.col("n_match") < threshold * F.col("n_cmp"))


def filter_pairs(pairs: DataFrame, threshold: int) -> DataFrame:
    return pairs.where(passes(threshold))


def centroid_top(a: DataFrame, b: DataFrame, pairs: DataFrame, m: int, encoder: str = "hash-word-64") -> DataFrame:
    """Only the m nearest clusters of B for each cluster of A, by squared distance of integer centroids."""
    def centers(x: DataFrame, c: str, v: str) -> DataFrame:
        e = x.select("cluster", F.posexplode(ENCODERS[encoder](F.col("text"))).alias("d", "x"))
        mean = e.groupBy("cluster", "d").agg(F.sum("x").alias("s"), F.count(F.lit(1)).alias("n")).withColumn("x", F.expr("1000 * s div n"))
        return mean.groupBy(F.col("cluster").alias(c)).agg(F.transform(F.sort_array(F.collect_list(F.struct("d", "x"))), lambda y: y["x"]).alias(v))

    near = pairs.join(centers(a, "ca", "va"), "ca").join(centers(b, "cb", "vb"), "cb")
    near = near.withColumn("dist", F.aggregate(F.zip_with("va", "vb", lambda x, y: (x - y) * (x - y)), F.lit(0).cast("long"), lambda s, x: s + x))
    w = Window.partitionBy("ca").orderBy("dist", "cb")
    return near.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= m).drop("va", "vb", "dist", "rank")


def match_pairs(kept: DataFrame, a: DataFrame, b: DataFrame, predicate: str, model: LanguageModel, block: tuple[int, int] = (15, 15), buckets: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(matches, calls): every row of A against every row of B inside the kept cluster pairs, block by block."""
    answers = run_prompts(block_prompts(a, b, kept, block, "match", buckets), "match", predicate, model, "match")
    return pairs_of(answers), calls_of(answers)


def cluster_join(a: DataFrame, b: DataFrame, predicate: str, model: LanguageModel, options: JoinOptions, encoder: str = "hash-word-64", method: str = "kmeans", projected: bool = False) -> dict[str, DataFrame]:
    """matches, calls, pairs (profiled), a and b (clustered)."""
    calls = None
    rows_a = a
    if projected:
        rows_a, calls = project(a, b, predicate, model, options)
    points_a = cluster_side(rows_a if projected else a, options, encoder, method)
    points_b = cluster_side(b, options, encoder, method)
    plan = profile_plan(cluster_pairs(points_a, points_b), options.min_profile_size)
    if options.centroid_top_m:
        plan = centroid_top(points_a, points_b, plan, options.centroid_top_m, encoder)
    pairs, sampled, profile_calls = profile_pairs(plan, points_a, points_b, predicate, model, options.profile_sample, options.seed, options.pool_factor)
    matches, match_calls = match_pairs(filter_pairs(pairs, options.filter_threshold), points_a, points_b, predicate, model, options.block, options.buckets)
    if options.reuse_profile:
        matches = matches.unionByName(sampled).dropDuplicates(["a_id", "b_id"])
    every = profile_calls.unionByName(match_calls)
    return {"matches": matches, "calls": every.unionByName(calls) if calls is not None else every, "pairs": pairs, "a": points_a, "b": points_b}
