"""Quality rules with risk-controlled cutoffs, in DataFrame functions alone."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from semjoin.llm.common import SPACE, materialize, packed, small, words_of

SYMBOLS = "#*$%&|<>"

#: Each rule is a rate of a document that grows with its faults. Names and cutoff grids.
RULES = {
    "symbols": (0.02, 0.05, 0.1, 0.2, 0.35, 0.5, 0.75, 1.0),
    "marks": (0.05, 0.1, 0.2, 0.35, 0.5, 0.75, 1.0, 1.5),
    "dup_lines": (0.1, 0.15, 0.2, 0.3, 0.4, 0.5, 0.6, 0.75),
    "repeats": (0.05, 0.1, 0.15, 0.2, 0.25, 0.3, 0.4, 0.45),
}


def with_features(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """docs with __n_words, __word_chars, __n_symbols, __n_dup_lines, __n_repeat_words, __n_lines, __n_marks.

    docs must not have columns of such names; packed() rows never do. Words are runs of anything but white space; windows of three words are compared by XXH64.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    n = F.size("__words")
    d = docs.withColumn("__words", words_of(F.col(text_col))).withColumn("__lines", F.filter(F.split(text, "\n"), lambda x: F.trim(x, F.lit(SPACE)) != ""))
    d = d.withColumn("__win", F.transform(F.slice("__words", 1, F.greatest(n - 2, F.lit(0))), lambda w, i: F.xxhash64(w, F.get("__words", i + 1), F.get("__words", i + 2))))
    d = d.select(
        *docs.columns, "__win",
        n.cast("long").alias("__n_words"),
        F.length(F.translate(text, SPACE, "")).cast("long").alias("__word_chars"),
        (F.length(text) - F.length(F.translate(text, SYMBOLS, ""))).cast("long").alias("__n_symbols"),
        (F.size("__lines") - F.size(F.array_distinct("__lines"))).cast("long").alias("__n_dup_lines"),
        F.size("__lines").cast("long").alias("__n_lines"),
        (F.length(text) - F.length(F.translate(text, "!", ""))).cast("long").alias("__n_marks"),
    )
    # Only texts in which a window comes twice sort their windows with positions.
    twice = F.size(F.array_distinct("__win")) < F.size("__win")
    d = d.withColumn("__sorted", F.when(twice, F.sort_array(F.transform("__win", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))))
    near = lambda i, by: F.coalesce(F.get("__sorted", i + by)["h"] == F.get("__sorted", i)["h"], F.lit(False))
    found = F.filter("__sorted", lambda _, i: near(i, 1) | F.when(i > 0, near(i, -1)).otherwise(False))
    d = d.withColumn("__at", F.sort_array(F.transform(found, lambda x: x["i"])))
    covered = F.aggregate(F.transform("__at", lambda x, i: F.least(F.lit(3), F.coalesce(F.get("__at", i + 1) - x, F.lit(3)))), F.lit(0).cast("long"), lambda a, x: a + x)
    d = d.withColumn("__n_repeat_words", F.coalesce(covered, F.lit(0).cast("long")))
    # A generator of one row keeps later filters from being pushed below, which would compute all this again.
    names = ("__n_words", "__word_chars", "__n_symbols", "__n_dup_lines", "__n_lines", "__n_marks", "__n_repeat_words")
    return d.select(*docs.columns, F.inline(F.array(F.struct(*names))))


def base_failed() -> Column:
    return (F.col("__n_words") < 50) | (100 * F.col("__n_repeat_words") > 50 * F.col("__n_words"))


def rule_value(rule: str) -> Column:
    words = F.greatest(F.col("__n_words"), F.lit(1)).cast("double")
    return {"symbols": F.col("__n_symbols") / words, "marks": F.col("__n_marks") / words, "dup_lines": F.col("__n_dup_lines") / F.greatest(F.col("__n_lines"), F.lit(1)).cast("double"), "repeats": F.col("__n_repeat_words") / words}[rule]


def binomial_tail(n: Column, k: Column, p: float) -> Column:
    """P(Bin(n, p) <= k), summed exactly term by term in log space."""
    start = F.struct((n * F.lit(math.log1p(-p))).alias("lp"), F.exp(n * F.lit(math.log1p(-p))).alias("sum"))

    def step(acc: Column, i: Column) -> Column:
        lp = acc["lp"] + F.log((n - i + 1).cast("double") / i) + F.lit(math.log(p / (1 - p)))
        return F.struct(lp.alias("lp"), (acc["sum"] + F.exp(lp)).alias("sum"))

    return F.aggregate(F.sequence(F.lit(0).cast("long"), k), start, lambda acc, i: F.when(i == 0, acc).otherwise(step(acc, F.greatest(i, F.lit(1)))))["sum"]


def calibrate(features: DataFrame, labels: DataFrame, stratum: str = "lang", max_false_reject: float = 0.10, delta: float = 0.05, rules: dict[str, tuple] = RULES) -> DataFrame:
    """Cutoffs (stratum, rule, cutoff, n_good, n_rejected): for each stratum and rule the lowest cutoff
    whose false rejections are proven to be rare.

    Over the labelled good documents that pass the base rules, a cutoff is accepted if the exact binomial
    test rejects "a share of max_false_reject / rules or more of good documents exceeds it" at level
    delta / (strata * rules * cutoffs), a Bonferroni correction over everything tried. So with
    probability 1 - delta no stratum loses over max_false_reject of its good documents to the rules.
    Strata with too few labels get no cutoff and lose nothing. A document with several labels counts as
    good only if all of them are; rows with null labels or ids are left out.
    """
    marks = labels.where("doc_id is not null and quality is not null").groupBy("doc_id").agg(F.min("quality").alias("quality")).where("quality = 1").select(F.col("doc_id").alias("__good"))
    good = features.where(~base_failed()).join(small(marks, 1_000_000), features["doc_id"] == F.col("__good"), "left_semi")
    grid = [(r, c) for r in rules for c in rules[r]]
    counts = good.groupBy(F.coalesce(F.col(stratum), F.lit("?")).alias("stratum")).agg(F.count(F.lit(1)).alias("n_good"), *[F.count_if(rule_value(r) > c).alias(f"k{i}") for i, (r, c) in enumerate(grid)])
    tried = counts.withColumn("m", F.count(F.lit(1)).over(Window.partitionBy()) * len(grid))
    each = tried.select("stratum", "n_good", "m", F.explode(F.array(*[F.struct(F.lit(r).alias("rule"), F.lit(c).alias("cutoff"), F.col(f"k{i}").alias("n_rejected")) for i, (r, c) in enumerate(grid)])).alias("x")).select("stratum", "n_good", "m", "x.*")
    share = max_false_reject / len(rules)
    safe = (F.col("n_rejected") <= F.col("n_good") * share) & (binomial_tail(F.col("n_good"), F.col("n_rejected"), share) <= F.lit(delta) / F.col("m"))
    return each.where(safe).groupBy("stratum", "rule").agg(F.min_by(F.struct("cutoff", "n_good", "n_rejected"), "cutoff").alias("x")).select("stratum", "rule", "x.*")


def judge(features: DataFrame, cutoffs: DataFrame, stratum: str = "lang", rules: dict[str, tuple] = RULES) -> DataFrame:
    """features with __base_failed and __kept. The table of cutoffs has a row for each stratum."""
    wide = cutoffs.groupBy(F.col("stratum").alias("__stratum")).agg(*[F.min(F.when(F.col("rule") == r, F.col("cutoff"))).alias(f"__cut_{r}") for r in rules])
    joined = features.join(small(wide, 10_000), F.coalesce(F.col(stratum), F.lit("?")) == F.col("__stratum"), "left")
    bad = F.lit(False)
    for r in rules:
        bad = bad | F.coalesce(rule_value(r) > F.col(f"__cut_{r}"), F.lit(False))
    return joined.withColumn("__base_failed", base_failed()).withColumn("__kept", ~base_failed() & ~bad).drop("__stratum", *[f"__cut_{r}" for r in rules])


def quality(docs: DataFrame, labels: DataFrame, **params) -> DataFrame:
    """One row per row of docs: doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
    base_failed, kept.

    Null and empty texts have no words and fail the base rules. Null strata share the stratum "?".
    Rows with null ids are judged too and take no part in calibration; repeated rows are each judged.
    Without labels, only the base rules reject. Extra columns are not read.
    """
    feats = materialize(with_features(docs.select("doc_id", "text", "lang")).drop("text"), "features")
    cutoffs = materialize(calibrate(feats, labels, **params), "cutoffs")
    named = [F.col(f"__{c}").alias(c) for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")]
    return judge(feats, cutoffs).select("doc_id", *named)


def keep_good(docs: DataFrame, labels: DataFrame, **params) -> DataFrame:
    """The rows of docs that quality() keeps, with their columns as they are, whatever their names.

    Calibration reads labelled texts alone; judging then is one pass that neither shuffles nor writes texts. Rows
    are judged each by itself: repeated ids and null ids change nothing.
    """
    ids = materialize(labels.where("doc_id is not null and quality is not null").select(F.col("doc_id").alias("__id")).distinct(), "labelled")
    labelled = docs.select("doc_id", "text", "lang").join(small(ids, 1_000_000), F.col("doc_id") == F.col("__id"), "left_semi")
    cutoffs = materialize(calibrate(materialize(with_features(labelled).drop("text"), "features"), labels, **params), "cutoffs")
    return judge(with_features(packed(docs, "text", "lang")), cutoffs).where("__kept").select("__row.*")
