"""Packing: length buckets of least padding by dynamic programming, token-budget batches inside each."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from semjoin.llm.common import materialize, n_words_of, with_rank


def best_boundaries(lengths: list[int], counts: list[int], max_buckets: int) -> tuple[list[int], int]:
    """Bucket boundaries (padded lengths, increasing, the last one the longest length) and their total
    padding, the least that max_buckets buckets allow; of equal solutions, the one with fewer buckets.

    Exact dynamic program over the distinct lengths: best[j] with k buckets is the least, over the
    previous boundary i, of best[i] with k - 1 buckets plus the padding of lengths i+1 .. j up to length j.
    The best i never falls as j grows, so a level is found by halving in O(n log n) time and O(n) memory.
    """
    if not lengths:
        return [], 0
    order = np.argsort(lengths)
    size, count = np.asarray(lengths, np.float64)[order], np.asarray(counts, np.float64)[order]
    n = len(size)
    c, s = np.concatenate([[0], np.cumsum(count)]), np.concatenate([[0], np.cumsum(count * size)])
    best, back = size * c[1:] - s[1:], [np.zeros(n, np.int64)]
    totals = [best[-1]]
    for _ in range(1, min(max_buckets, n)):
        before = np.concatenate([[np.inf], best[:-1]])
        best, first = np.empty(n), np.empty(n, np.int64)
        spans = [(0, n, 0, n - 1)]
        while spans:
            lo, hi, i_lo, i_hi = spans.pop()
            j = (lo + hi) // 2
            i = slice(i_lo, min(i_hi, j) + 1)
            through = before[i] + size[j] * (c[j + 1] - c[i]) - (s[j + 1] - s[i])
            at = int(through.argmin())
            best[j], first[j] = through[at], i_lo + at
            if lo < j:
                spans.append((lo, j, i_lo, int(first[j])))
            if j + 1 < hi:
                spans.append((j + 1, hi, int(first[j]), i_hi))
        back.append(first)
        totals.append(best[-1])
    k = int(np.argmin(totals))
    out, j = [], n - 1
    for level in range(k, -1, -1):
        out.append(int(size[j]))
        j = int(back[level][j]) - 1
    return out[::-1], int(totals[k])


def tokenizer_length(text: Column, path: str) -> Column:
    """Tokens of a text under the public tokenizer file at `path` (a tokenizer.json on every executor)."""

    @F.pandas_udf("long")
    def count(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        from tokenizers import Tokenizer

        tok = Tokenizer.from_file(path)
        for texts in batches:
            yield pd.Series([len(tok.encode(t or "", add_special_tokens=False).ids) for t in texts])

    return count(text)


def pack(docs: DataFrame, max_len: int = 2048, max_buckets: int = 8, token_budget: int = 16_384, id_col: str = "doc_id", text_col: str = "text", tokenizer_path: str | None = None) -> DataFrame:
    """Rows (doc_id, piece, start_token, n_tokens, bucket, padded_len, batch, slot), one for each piece.

    Tokens are words unless a tokenizer file is named. A text over max_len tokens is cut into pieces of
    max_len and a rest; nothing is dropped. The histogram of piece lengths covers all rows and has
    max_len + 1 entries at most, so it may go to the driver. Bucket b holds the pieces whose length is
    over the boundary before it and at most padded_len; a batch is token_budget div padded_len pieces
    (one at least) of a bucket, filled in an order given by a hash of the id, so that only the last batch
    of a bucket is short. Texts without words (null, empty) give one piece of no tokens. Rows that are
    equal are all packed. An empty table gives no rows. Extra columns are not read.
    """
    length = tokenizer_length(F.col(text_col), tokenizer_path) if tokenizer_path else n_words_of(F.col(text_col))
    sized = docs.select(F.col(id_col).alias("doc_id"), length.alias("__n"))
    last = F.greatest(F.floor((F.col("__n") - 1) / F.lit(max_len)), F.lit(0)).cast("long")
    pieces = sized.select("doc_id", "__n", F.explode(F.sequence(F.lit(0).cast("long"), last)).alias("piece"))
    start = F.col("piece") * F.lit(max_len)
    pieces = materialize(pieces.select("doc_id", "piece", start.alias("start_token"), F.least(F.lit(max_len).cast("long"), F.col("__n") - start).alias("n_tokens")), "pieces")
    histogram = sorted((r["n_tokens"], r["n"]) for r in pieces.groupBy("n_tokens").agg(F.count(F.lit(1)).alias("n")).collect())
    bounds, _ = best_boundaries([x for x, _ in histogram], [n for _, n in histogram], max_buckets)
    bucket, padded, room = F.lit(None).cast("int"), F.lit(None).cast("long"), F.lit(None).cast("long")
    for b in reversed(range(len(bounds))):
        inside = F.col("n_tokens") <= bounds[b]
        bucket = F.when(inside, F.lit(b)).otherwise(bucket)
        padded = F.when(inside, F.lit(bounds[b]).cast("long")).otherwise(padded)
        room = F.when(inside, F.lit(max(1, token_budget // max(1, bounds[b]))).cast("long")).otherwise(room)
    mixed = pieces.select("*", bucket.alias("bucket"), padded.alias("padded_len"), room.alias("__room"), F.xxhash64("doc_id", "piece", "n_tokens").alias("__mix"))
    ranked = with_rank(mixed, ["bucket"], ["__mix", "doc_id", "piece", "n_tokens"], ["doc_id", "piece", "n_tokens"], "__rank", sum(n for _, n in histogram))
    return ranked.select("doc_id", "piece", "start_token", "n_tokens", "bucket", "padded_len", F.floor(F.col("__rank") / F.col("__room")).cast("long").alias("batch"), (F.col("__rank") % F.col("__room")).alias("slot"))
