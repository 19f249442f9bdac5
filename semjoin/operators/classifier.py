"""Label join: one label a row, then an equi-join."""

from __future__ import annotations

import functools

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from semjoin.models import UNKNOWN, LanguageModel
from semjoin.plans.invoke import calls_of, row_prompts, run_prompts


def classify(rows: DataFrame, labels: list[str], predicate: str, model: LanguageModel, batch: int = 25, side: str = "a", dedupe: bool = False, buckets: int | None = None) -> tuple[DataFrame, DataFrame]:
    """((id, label), calls): exactly one label of the list for each row (id, text).

    With dedupe, equal texts are asked once, as their smallest id.
    """
    asked = rows
    if dedupe:
        first = rows.groupBy("text").agg(F.min("id").alias("first"))
        asked = first.select(F.col("first").alias("id"), "text")
    answers = run_prompts(row_prompts(asked, batch, f"classify-{side}", buckets=buckets), "classify", predicate, model, "classify", tuple(labels))
    out = answers.where("row = 'answer'").select(F.col("a_id").alias("id"), F.col("answer").alias("label"))
    if dedupe:
        out = rows.join(first, "text").join(out.withColumnRenamed("id", "first"), "first").select("id", "label")
    return out, calls_of(answers)


def classify_multi(rows: DataFrame, labels: list[str], predicate: str, model: LanguageModel, batch: int = 25, side: str = "a", dedupe: bool = False, buckets: int | None = None) -> tuple[DataFrame, DataFrame]:
    """((id, label), calls): a line for each label that a row has, each label asked by itself."""
    asked = [classify(rows, [x, UNKNOWN], predicate, model, batch, f"{side}{i}", dedupe, buckets) for i, x in enumerate(x for x in labels if x != UNKNOWN)]
    out, calls = (functools.reduce(DataFrame.unionByName, x) for x in zip(*asked, strict=True))
    return out.where(F.col("label") != UNKNOWN), calls


def keep_listed(label: Column, labels: list[str]) -> Column:
    """A label outside the list counts as unknown."""
    return F.when(label.isin([x for x in labels if x != UNKNOWN]), label).otherwise(F.lit(UNKNOWN))


def label_equi_join(a: DataFrame, b: DataFrame, salt: int = 1) -> DataFrame:
    """(a_id, b_id, label) of rows (id, label) with the same known label. With salt, each label is dealt over
    `salt` keys: rows of A keep one, rows of B are copied to all, so a hot label is not one task."""
    left = a.where(F.col("label") != UNKNOWN).select(F.col("id").alias("a_id"), "label")
    right = b.where(F.col("label") != UNKNOWN).select(F.col("id").alias("b_id"), "label")
    if salt == 1:
        return left.join(right, "label").select("a_id", "b_id", "label")
    left = left.withColumn("salt", F.pmod(F.xxhash64("a_id"), F.lit(salt)))
    right = right.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salt - 1).cast("long"))))
    return left.join(right, ["label", "salt"]).select("a_id", "b_id", "label")


def label_join_totals(a: DataFrame, b: DataFrame, of_a: Column, of_b: Column, salt: int = 1) -> DataFrame:
    """(label, n, s): how many pairs label_equi_join() has for each label, and the sum of of_a + of_b over them, in whole
    numbers, without their expansion. of_a and of_b are columns of `id`; as in SQL, a pair with a null term adds nothing.
    With salt, each side is first summed over `salt` keys of a label, so a hot label is not one task."""

    def summed(rows: DataFrame, of: Column, n: str, some: str, s: str) -> DataFrame:
        known = rows.where(F.col("label") != UNKNOWN).select("label", of.cast("long").alias("x"), F.pmod(F.xxhash64("id"), F.lit(salt)).alias("salt"))
        parts = known.groupBy("label", "salt").agg(F.count(F.lit(1)).alias(n), F.count("x").alias(some), F.coalesce(F.sum("x"), F.lit(0).cast("long")).alias(s))
        return parts.groupBy("label").agg(*[F.sum(x).alias(x) for x in (n, some, s)])

    both = summed(a, of_a, "na", "xa", "sa").join(summed(b, of_b, "nb", "xb", "sb"), "label")
    total = F.col("sa") * F.col("xb") + F.col("sb") * F.col("xa")
    return both.select("label", (F.col("na") * F.col("nb")).alias("n"), F.when(F.col("xa") * F.col("xb") > 0, total).alias("s"))


#: Rows of one label that one task joins.
HOT_ROWS = 100_000


def salt_for(b: DataFrame) -> int:
    """Keys that the largest label is dealt over, by its measured size."""
    top = b.where(F.col("label") != UNKNOWN).groupBy("label").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] or 0
    return min(256, -(-top // HOT_ROWS)) or 1


def multi_label_join(a: DataFrame, b: DataFrame) -> DataFrame:
    """(a_id, b_id) of rows (id, labels array) that share a label."""
    left = a.select(F.col("id").alias("a_id"), F.explode("labels").alias("label")).where(F.col("label") != UNKNOWN)
    right = b.select(F.col("id").alias("b_id"), F.explode("labels").alias("label")).where(F.col("label") != UNKNOWN)
    return left.join(right, "label").select("a_id", "b_id").distinct()


def label_groups(a: DataFrame, b: DataFrame) -> DataFrame:
    """(label, n_a, n_b, n_pairs): the join without its expansion."""
    count = lambda df, name: df.where(F.col("label") != UNKNOWN).groupBy("label").agg(F.count(F.lit(1)).alias(name))
    return count(a, "n_a").join(count(b, "n_b"), "label").withColumn("n_pairs", F.col("n_a") * F.col("n_b"))
