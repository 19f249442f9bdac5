"""Accuracy and cost measures over pairs, truths and call logs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

PAIR = ["a_id", "b_id"]


def score(pairs: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: tp, fp, fn, recall, precision, f1 (percent). No output: precision null, f1 0; no truth: recall null."""
    out, want = pairs.select(*PAIR).distinct().withColumn("o", F.lit(1)), truth.select(*PAIR).distinct().withColumn("t", F.lit(1))
    both = out.join(want, PAIR, "full")
    n = both.agg(F.count_if(F.col("o").isNotNull() & F.col("t").isNotNull()).alias("tp"), F.count_if(F.col("t").isNull()).alias("fp"), F.count_if(F.col("o").isNull()).alias("fn"))
    return n.select("*", percent("tp", F.col("tp") + F.col("fn")).alias("recall"), percent("tp", F.col("tp") + F.col("fp")).alias("precision"), F.coalesce(percent(F.col("tp") * 2, F.col("tp") * 2 + F.col("fp") + F.col("fn")), F.lit(0.0)).alias("f1"))


def percent(part: Column | str, whole: Column) -> Column:
    part = F.col(part) if isinstance(part, str) else part
    return F.round(100.0 * F.try_divide(part.cast("double"), whole.cast("double")), 4)


def average_trials(scores: DataFrame, *by: str) -> DataFrame:
    """Means over trials of recall, precision, f1 and tokens; f1 is averaged, not computed from averages."""
    return scores.groupBy(*by).agg(*[F.round(F.avg(c), 2).alias(c) for c in ("recall", "precision", "f1", "tokens")])


def token_cost(calls: DataFrame, *by: str) -> DataFrame:
    return calls.groupBy(*by).agg(F.coalesce(F.sum(F.col("in_tok") + F.col("out_tok")), F.lit(0)).alias("tokens"), F.count(F.lit(1)).alias("calls"), F.count_if(F.col("attempt") > 1).alias("retries"))


def advisor_cost(calls: DataFrame) -> DataFrame:
    return token_cost(calls.where("stage in ('advisor', 'labels')"))


def selectivity(a: DataFrame, b: DataFrame, truth: DataFrame) -> DataFrame:
    n = lambda x, c: x.agg(F.count(F.lit(1)).alias(c))
    return n(a, "n_a").crossJoin(n(b, "n_b")).crossJoin(n(truth, "n_true")).withColumn("selectivity", percent("n_true", F.col("n_a") * F.col("n_b")))


def label_ceiling(truth: DataFrame) -> DataFrame:
    """Best recall of any output with one partner for each row of A."""
    return truth.agg(F.countDistinct("a_id").alias("reachable"), F.count(F.lit(1)).alias("n_true")).withColumn("ceiling", percent("reachable", F.col("n_true")))


def pruning_report(pairs: DataFrame, kept: DataFrame, a: DataFrame, b: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: tuple pairs, those not sent on, their share, and the share of true pairs that the filter left."""
    total = pairs.agg(F.sum(F.col("na") * F.col("nb")).alias("n_pairs"))
    sent = kept.agg(F.coalesce(F.sum(F.col("na") * F.col("nb")), F.lit(0)).alias("n_sent"))
    where = truth.join(a.select(F.col("id").alias("a_id"), F.col("cluster").alias("ca")), "a_id").join(b.select(F.col("id").alias("b_id"), F.col("cluster").alias("cb")), "b_id")
    left = where.join(kept.select("ca", "cb", F.lit(1).alias("k")), ["ca", "cb"], "left").agg(F.count(F.lit(1)).alias("n_true"), F.count("k").alias("true_kept"))
    return total.crossJoin(sent).crossJoin(left).select("n_pairs", "n_sent", percent(F.col("n_pairs") - F.col("n_sent"), F.col("n_pairs")).alias("pruned"), "n_true", "true_kept", percent("true_kept", F.col("n_true")).alias("filter_recall"))


def compare(scores: DataFrame, base: str) -> DataFrame:
    """Token saving in percent and F1 points of each strategy against `base`, by workload."""
    b = scores.where(F.col("strategy") == base).select("workload", F.col("f1").alias("f0"), F.col("tokens").alias("t0"))
    return scores.where(F.col("strategy") != base).join(b, "workload").select("workload", "strategy", F.round(F.col("f1") - F.col("f0"), 2).alias("points"), F.round(100.0 * (F.col("t0") - F.col("tokens")) / F.col("t0"), 1).alias("saving"))


def routing_accuracy(scores: DataFrame, routes: DataFrame) -> DataFrame:
    best = scores.groupBy("workload").agg(F.max_by("strategy", F.struct("f1", "strategy")).alias("best"))
    return best.join(routes, "workload").select("workload", "best", "route", (F.col("best") == F.col("route")).alias("right"))


def pick_config(grid: DataFrame, f1_slack: float = 2.5, min_saving: float = 0.1) -> DataFrame:
    """The tuned row of a grid (workload, ratio, threshold, f1, tokens): the best F1, or, inside f1_slack points of it,
    the row with the fewest tokens if it saves min_saving of the best row's tokens."""
    w = Window.partitionBy("workload").orderBy(F.desc("f1"), "tokens", "ratio", "threshold")
    ranked = grid.withColumn("r", F.row_number().over(w))
    best = ranked.where("r = 1").select("workload", F.col("f1").alias("best_f1"), F.col("tokens").alias("best_tokens"))
    pool = ranked.join(best, "workload").where((F.col("f1") >= F.col("best_f1") - f1_slack) & ((F.col("r") == 1) | (F.col("tokens") <= (1 - min_saving) * F.col("best_tokens"))))
    w2 = Window.partitionBy("workload").orderBy((F.col("r") == 1).cast("int"), "tokens", F.desc("f1"), "ratio", "threshold")
    return pool.withColumn("p", F.row_number().over(w2)).where("p = 1").select("workload", "ratio", "threshold", "f1", "tokens")
