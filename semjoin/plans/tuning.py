"""Sweeps: cluster ratio x threshold in one pass, block sizes, projection on and off."""

from __future__ import annotations

import dataclasses
import functools
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semjoin.functions.measures import percent, score, token_cost
from semjoin.models import LanguageModel
from semjoin.operators import cluster_join as cj
from semjoin.operators.baselines import block_join
from semjoin.plans.advisor import JoinOptions
from semjoin.plans.invoke import block_prompts, calls_of, pairs_of, run_prompts
from semjoin.sources.tables import keep

RATIOS = (0.025, 0.05, 0.075, 0.1)


def side_by_side(runs: list[Callable[[], DataFrame]], at_once: int = 8) -> DataFrame:
    """The union of the results of independent runs, each written as it ends. Their many small jobs are submitted
    from several threads, so one run fills the cores that another leaves idle."""
    with ThreadPoolExecutor(at_once) as pool:
        rows = list(pool.map(lambda run: keep(run(), "run"), runs))
    return functools.reduce(DataFrame.unionByName, rows)


def cluster_grid(a: DataFrame, b: DataFrame, truth: DataFrame, predicate: str, model: LanguageModel, options: JoinOptions, workload: str, ratios: tuple[float, ...] = RATIOS, thresholds: tuple[int, ...] = tuple(range(101))) -> DataFrame:
    """(workload, ratio, threshold, tp, fp, fn, f1, tokens) for all ratios and thresholds (hundredths).

    Thresholds decide only which cluster pairs stay. So for each ratio all pairs are profiled and matched
    once, summed up by cluster pair, and each threshold adds up the pairs it keeps.
    """
    spark = a.sparkSession
    n_true = truth.agg(F.count(F.lit(1)).alias("n_true"))
    steps = spark.range(1).select(F.explode(F.array(*[F.lit(t) for t in thresholds])).alias("threshold"))

    def one(ratio: float) -> DataFrame:
        o = dataclasses.replace(options, cluster_ratio=ratio)
        ca, cb = cj.cluster_side(a, o), cj.cluster_side(b, o)
        pairs, _, profile_calls = cj.profile_pairs(cj.profile_plan(cj.cluster_pairs(ca, cb), o.min_profile_size), ca, cb, predicate, model, o.profile_sample, o.seed, o.pool_factor)
        prompts = keep(block_prompts(ca, cb, pairs, o.block, "match"), "grid-prompts")
        answers = run_prompts(prompts, "match", predicate, model, "match")
        hits = pairs_of(answers).join(truth.withColumn("t", F.lit(1)), ["a_id", "b_id"], "left").groupBy("ca", "cb").agg(F.count("t").alias("tp"), F.count_if(F.col("t").isNull()).alias("fp"))
        cost = calls_of(answers).join(prompts.select("call_id", "ca", "cb"), "call_id").groupBy("ca", "cb").agg(F.sum(F.col("in_tok") + F.col("out_tok")).alias("tokens"))
        by_pair = keep(pairs.join(hits, ["ca", "cb"], "left").join(cost, ["ca", "cb"], "left").fillna(0, ["tp", "fp", "tokens"]), "grid-pairs")
        fixed = token_cost(profile_calls).select(F.col("tokens").alias("fixed"))
        sums = steps.join(by_pair, cj.passes(F.col("threshold")), "left").groupBy("threshold").agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in ("tp", "fp", "tokens")])
        row = sums.crossJoin(n_true).crossJoin(fixed).withColumn("fn", F.col("n_true") - F.col("tp"))
        return row.select(F.lit(workload).alias("workload"), F.lit(ratio).alias("ratio"), "threshold", "tp", "fp", "fn", F.coalesce(percent(F.col("tp") * 2, F.col("tp") * 2 + F.col("fp") + F.col("fn")), F.lit(0.0)).alias("f1"), (F.col("tokens") + F.col("fixed")).alias("tokens"))

    return side_by_side([functools.partial(one, r) for r in ratios])


def block_sweep(a: DataFrame, b: DataFrame, truth: DataFrame, predicate: str, model: LanguageModel, workload: str, sizes: tuple[int, ...] = (5, 10, 15, 20, 25)) -> DataFrame:
    """(workload, block, recall, precision, f1, tokens, calls) of fixed blocks over the full tables."""
    n_a, n_b = a.count(), b.count()

    def one(size: int) -> DataFrame:
        ba, bb = min(size, n_a), min(size, n_b)
        matches, calls = block_join(a, b, predicate, model, (ba, bb))
        return score(matches, truth).crossJoin(token_cost(calls)).select(F.lit(workload).alias("workload"), F.lit(f"{ba}x{bb}").alias("block"), "recall", "precision", "f1", "tokens", "calls")

    return side_by_side([functools.partial(one, s) for s in sizes])
