"""SQL surface: SELECT ... FROM a SEMANTIC JOIN b ON MATCHES('sentence') [WHERE ...], and functions for SQL."""

from __future__ import annotations

import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from semjoin.models import UNKNOWN, LanguageModel, Prompt, parse_labels, parse_pairs
from semjoin.plans.advisor import JoinOptions
from semjoin.plans.api import semantic_join

_FORM = re.compile(r"^\s*SELECT\s+(?P<cols>.+?)\s+FROM\s+(?P<a>\w+)\s+SEMANTIC\s+JOIN\s+(?P<b>\w+)\s+ON\s+MATCHES\s*\(\s*'(?P<on>(?:[^']|'')*)'\s*\)(?:\s+WHERE\s+(?P<where>.+?))?\s*;?\s*$", re.I | re.S)


def sql(spark: SparkSession, query: str, model: LanguageModel, options: JoinOptions = JoinOptions()) -> DataFrame:
    """Run a query of the form above over views with columns id, text and others; the sentence is never put
    into SQL. The engine's parser takes WHERE apart: conditions joined by AND that name one view alone are applied below the
    join, so that rows they exclude cost no tokens; the others stay above it."""
    m = _FORM.match(query)
    if m is None:
        raise ValueError("expected SELECT ... FROM a SEMANTIC JOIN b ON MATCHES('...') [WHERE ...]")
    names, above = (m["a"], m["b"]), []
    below: dict[str, list[str]] = {n: [] for n in names}
    for part in conjuncts(spark, m["where"]) if m["where"] else ():
        used = [n for n in names if re.search(rf"\b{n}\.", re.sub(r"'[^']*'", "''", part))]
        if len(used) == 1:
            below[used[0]].append(part)
        else:
            above.append(part)
    sides = {}
    for n in names:
        side = spark.table(n).alias(n)
        for condition in below[n]:
            side = side.where(condition)
        sides[n] = side
    a, b = (sides[n].select(F.col(f"{n}.id").alias("id"), F.col(f"{n}.text").alias("text")) for n in names)
    pairs = semantic_join(a, b, m["on"].replace("''", "'"), model, options).pairs
    out = pairs.join(sides[names[0]], F.col("a_id") == F.col(f"{names[0]}.id")).join(sides[names[1]], F.col("b_id") == F.col(f"{names[1]}.id"))
    for condition in above:
        out = out.where(condition)
    return out.selectExpr(*[c.strip() for c in re.split(r",(?![^(]*\))", m["cols"])])


def conjuncts(spark: SparkSession, condition: str) -> list[str]:
    """The conditions that AND joins at the top of a condition, as the engine reads it."""
    todo, out = [spark._jsparkSession.sessionState().sqlParser().parseExpression(condition)], []
    while todo:
        x = todo.pop()
        if x.getClass().getSimpleName() == "And":
            todo += [x.right(), x.left()]
        else:
            out.append(x.sql())
    return out


def register_classify(spark: SparkSession, name: str, question: str, labels: tuple[str, ...], model: LanguageModel, batch: int = 25) -> None:
    """name(text) in SQL: the label of each row, asked in batches of an Arrow batch."""

    @F.pandas_udf("string")
    def classify(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for texts in batches:
            out: list[str] = []
            for i in range(0, len(texts), batch):
                part = tuple(t or "" for t in texts.iloc[i : i + batch])
                reply = model.complete(Prompt("classify", question, part, (), (*labels, UNKNOWN)))
                out += parse_labels(reply.text, len(part), [*labels, UNKNOWN])[0]
            yield pd.Series(out)

    spark.udf.register(name, classify)


def register_partners(spark: SparkSession, name: str, predicate: str, partners: tuple[str, ...], model: LanguageModel) -> None:
    """name(text) as a table function in SQL: the texts among a short fixed list that match."""

    class Partners:
        def eval(self, text: str):
            reply = model.complete(Prompt("match", predicate, (text or "",), partners))
            for _, j in parse_pairs(reply.text, 1, len(partners))[0]:
                yield (partners[j],)

    spark.udtf.register(name, F.udtf(Partners, returnType="partner string"))
