"""Running prompts inside Spark: one row a prompt, answers and call log written once."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semjoin.models import UNKNOWN, LanguageModel, Prompt, parse_labels, parse_pairs, parse_texts
from semjoin.sources.tables import keep

SCHEMA = "row string, stage string, call_id string, attempt int, model string, n_a int, n_b int, in_tok long, out_tok long, status string, ca int, cb int, a_id long, b_id long, answer string"
_COLUMNS = [x.split()[0] for x in SCHEMA.split(", ")]


#: Rows that one task numbers.
BUCKET_ROWS = 50_000


def run_prompts(prompts: DataFrame, kind: str, predicate: str, model: LanguageModel, stage: str, options: tuple[str, ...] = (), split: bool = True, concurrency: int | None = None) -> DataFrame:
    """Ask the model each prompt (call_id, ca, cb, a, b: arrays of struct id, text); rows of SCHEMA, written.

    row is call for one line of the log, or pair, label or text for an answer. A malformed reply is asked
    once more, then counts as no answer. A prompt whose reply is cut by length is asked again in parts, four of a match
    and two of rows, down to one pair or row; what overflows even then is logged as abstained and has the answer of no
    information: no pair, the label unknown, the text itself. With split=False overflows are reported alone, for a caller
    that asks again. The result is read from storage, so later actions cost no calls.
    """

    def blank(a) -> list:
        return [] if kind == "match" else [UNKNOWN] * len(a) if kind == "classify" else [x["text"] for x in a]

    def ask(row, a, b, attempt: int) -> Iterator[tuple]:
        prompt = Prompt(kind, predicate, tuple(x["text"] for x in a), tuple(x["text"] for x in b), options)
        while True:
            reply = model.complete(prompt)
            if kind == "match":
                got, status = parse_pairs(reply.text, len(a), len(b))
            elif kind == "classify":
                got, status = parse_labels(reply.text, len(a), list(options))
            else:
                got, status = parse_texts(reply.text, [x["text"] for x in a])
            if reply.finish == "length":
                last = split and len(a) * (len(b) if kind == "match" else 1) == 1
                got, status = blank(a), "abstained" if last else "overflow"
            yield ("call", stage, row.call_id, attempt, model.name, len(a), len(b), reply.in_tok, reply.out_tok, status, row.ca, row.cb, None, None, None)
            if status != "malformed" or attempt >= 2:
                break
            attempt += 1
        if status == "overflow" and split and kind == "match" and len(a) * len(b) > 1:
            h, k = (len(a) + 1) // 2, (len(b) + 1) // 2
            for part_a in filter(len, (a[:h], a[h:])):
                for part_b in filter(len, (b[:k], b[k:])):
                    yield from ask(row, part_a, part_b, attempt + 1)
        elif status == "overflow" and split and kind != "match":
            h = (len(a) + 1) // 2
            for part in (a[:h], a[h:]):
                yield from ask(row, part, b, attempt + 1)
        elif kind == "match":
            for i, j in got:
                yield ("pair", stage, row.call_id, attempt, model.name, None, None, None, None, None, row.ca, row.cb, a[i]["id"], b[j]["id"], None)
        elif status != "overflow":
            for x, answer in zip(a, got, strict=True):
                yield ("answer", stage, row.call_id, attempt, model.name, None, None, None, None, None, row.ca, row.cb, x["id"], None, answer)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            rows = [r for row in pdf.itertuples(index=False) for r in ask(row, list(row.a), list(row.b), 1)]
            out = pd.DataFrame(rows, columns=_COLUMNS)
            yield out.astype({c: "Int64" for c in ("attempt", "n_a", "n_b", "in_tok", "out_tok", "ca", "cb", "a_id", "b_id")})

    if concurrency:
        prompts = prompts.repartition(concurrency, "call_id")
    return keep(prompts.select("call_id", "ca", "cb", "a", "b").mapInPandas(run, SCHEMA), f"answers-{stage}")


def calls_of(answers: DataFrame) -> DataFrame:
    return answers.where("row = 'call'").select("call_id", "attempt", "model", "n_a", "n_b", "in_tok", "out_tok", "status", "stage")


def pairs_of(answers: DataFrame) -> DataFrame:
    return answers.where("row = 'pair'").select("a_id", "b_id", "ca", "cb", "stage")


def batches(rows: DataFrame, size: int, buckets: int | None = None, by: tuple[str, ...] = ()) -> DataFrame:
    """rows (id, text, *by) in lists of at most `size`: (*by, blk, items). Numbering is exact inside each
    hash bucket of ids; one bucket gives the least number of batches, more buckets scale. Without a number there is a
    bucket for each BUCKET_ROWS rows, counted."""
    from pyspark.sql import Window

    if buckets is None:
        buckets = -(-rows.count() // BUCKET_ROWS)
    dealt = rows.withColumn("bucket", F.pmod(F.xxhash64("id"), F.lit(max(1, buckets))).cast("int"))
    numbered = dealt.withColumn("blk", ((F.row_number().over(Window.partitionBy(*by, "bucket").orderBy("id")) - 1) / F.lit(size)).cast("int"))
    grouped = numbered.groupBy(*by, "bucket", "blk").agg(F.sort_array(F.collect_list(F.struct("id", "text"))).alias("items"))
    return grouped.withColumn("blk", F.concat_ws("-", "bucket", "blk")).drop("bucket")


_NO_ROWS = "array<struct<id:bigint,text:string>>"


def row_prompts(rows: DataFrame, size: int, stage: str, b_sample: list[tuple[int, str]] | None = None, buckets: int | None = None) -> DataFrame:
    b = F.array(*[F.struct(F.lit(i).cast("long").alias("id"), F.lit(t).alias("text")) for i, t in b_sample]) if b_sample else F.array()
    return batches(rows, size, buckets).select(F.concat_ws(":", F.lit(stage), "blk").alias("call_id"), F.lit(None).cast("int").alias("ca"), F.lit(None).cast("int").alias("cb"), F.col("items").alias("a"), b.cast(_NO_ROWS).alias("b"))


def block_prompts(a: DataFrame, b: DataFrame, pairs: DataFrame | None, size: tuple[int, int], stage: str, buckets: int | None = None) -> DataFrame:
    """Prompts of blocks x blocks: inside the cluster pairs given (ca, cb), or over the whole tables."""
    if pairs is None:
        left, right = batches(a, size[0], buckets), batches(b, size[1], buckets)
        joined = left.select(F.col("blk").alias("ba"), F.col("items").alias("a")).crossJoin(right.select(F.col("blk").alias("bb"), F.col("items").alias("b")))
        joined = joined.select(F.lit(None).cast("int").alias("ca"), F.lit(None).cast("int").alias("cb"), "*")
    else:
        left = batches(a, size[0], buckets, ("cluster",)).select(F.col("cluster").alias("ca"), F.col("blk").alias("ba"), F.col("items").alias("a"))
        right = batches(b, size[1], buckets, ("cluster",)).select(F.col("cluster").alias("cb"), F.col("blk").alias("bb"), F.col("items").alias("b"))
        joined = pairs.select("ca", "cb").join(left, "ca").join(right, "cb")
    return joined.select(F.concat_ws(":", F.lit(stage), "ca", "ba", "cb", "bb").alias("call_id"), "ca", "cb", "a", "b")
