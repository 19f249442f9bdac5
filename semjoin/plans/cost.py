"""Calls and tokens of a plan before it runs, by closed formulas."""

from __future__ import annotations

import dataclasses
import math

from pyspark.sql import DataFrame

from semjoin.operators.baselines import Stats, measure
from semjoin.operators.clustering import cluster_count


@dataclasses.dataclass(frozen=True)
class Estimate:
    strategy: str
    calls: int
    tokens: int


def block_cost(s: Stats, ba: int, bb: int) -> tuple[int, float]:
    ra, rb = math.ceil(s.m / ba), math.ceil(s.n / bb)
    return ra * rb, ra * rb * s.p + s.m * s.ta * rb + s.n * s.tb * ra


def estimate(a: DataFrame, b: DataFrame, predicate: str, strategy: str, options, n_labels: int = 1) -> Estimate:
    """With multi_label every row is asked once for each of n_labels; a label table is not asked."""
    s = measure(a, b, predicate)
    if strategy == "label":
        times, asked = n_labels if options.multi_label else 1, 0 if options.label_table else s.n
        batches = math.ceil(s.m / options.classify_batch) + math.ceil(asked / options.classify_batch)
        calls = 1 + times * batches
        return Estimate(strategy, calls, round(calls * (s.p + 20) + times * (s.m * s.ta + asked * s.tb)))
    if strategy == "pairwise":
        return Estimate(strategy, s.m * s.n, round(s.m * s.n * (s.p + s.ta + s.tb + 1)))
    if strategy == "block":
        calls, tokens = block_cost(s, *options.block)
        return Estimate(strategy, calls, round(tokens))
    ka, kb = (cluster_count(n, options.cluster_ratio, most=options.max_clusters) for n in (s.m, s.n))
    one = Stats(math.ceil(s.m / ka), math.ceil(s.n / kb), s.p, s.ta, s.tb, s.to)
    calls, tokens = block_cost(one, *options.block)
    profile = ka * kb * (s.p + options.profile_sample * (s.ta + s.tb))
    return Estimate(strategy, ka * kb * (calls + 1), round(ka * kb * tokens + profile))
