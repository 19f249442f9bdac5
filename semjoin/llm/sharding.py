"""Sharding by a keyed permutation of global row numbers: reproducible shuffle, computable shard and slot."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from semjoin.llm.common import materialize, with_rank

ROUNDS = 6


def feistel_step(x: Column, side: int, key: int, rounds: int = ROUNDS) -> Column:
    """A keyed permutation of 0 .. side * side - 1: a balanced Feistel network on (x div side, x mod side),
    whose round function is XXH64 and whose mixing is addition modulo side."""
    left, right = F.floor(x / F.lit(side)).cast("long"), x % F.lit(side)
    for r in range(rounds):
        left, right = right, (left + F.pmod(F.xxhash64(right, F.lit(r), F.lit(key)), F.lit(side))) % F.lit(side)
    return left * F.lit(side) + right


def permuted(x: Column, n: int, key: int, rounds: int = ROUNDS) -> Column:
    """A keyed permutation of 0 .. n - 1. The square of the side is the first at or over n, so few values
    fall outside; those walk on along their cycle until they are inside. A walk passes each outside value
    once at most; for large n the longest walk is far below the bound kept here, and running into
    it is an error, never a wrong slot."""
    side = max(1, math.isqrt(max(n, 1) - 1) + 1)
    steps = min(side * side - n, 201)
    first = feistel_step(x, side, key, rounds)
    if steps <= 0:
        return first
    walked = F.aggregate(F.sequence(F.lit(1), F.lit(steps)), first, lambda at, _: F.when(at < n, at).otherwise(feistel_step(at, side, key, rounds)))
    walked = F.when(walked < n, walked).otherwise(F.raise_error(F.lit("cycle walk too long")).cast("long"))
    return F.when(first < n, first).otherwise(walked)


def shard(docs: DataFrame, n_shards: int = 8, key: int = 42, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of docs: doc_id, size, text_crc32, row_number, law, shard, slot, grown_shard.

    Rows are numbered 0 .. n - 1 in an order that depends on ids and texts alone; the number is permuted,
    and shard = permuted mod n_shards, slot = permuted div n_shards. So shard counts differ by one at most
    (law `rows`), slots are gapless, and both can be computed from a row number without the other rows.
    size is the text's UTF-8 bytes plus 1; null texts count as empty; null ids are numbered like others;
    equal rows get different slots; an empty table gives no rows. Extra columns are not read.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = materialize(docs.select(F.col(id_col).alias("doc_id"), (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32")), "sizes")
    n = rows.count()
    ranked = with_rank(rows, [], ["doc_id", "text_crc32", "size"], ["doc_id", "text_crc32", "size"], "row_number", n)
    at = F.col("__at")
    return ranked.withColumn("__at", permuted(F.col("row_number"), n, key)).select(
        "doc_id", "size", "text_crc32", "row_number", F.lit("rows").alias("law"),
        (at % F.lit(n_shards)).cast("int").alias("shard"), F.floor(at / F.lit(n_shards)).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
