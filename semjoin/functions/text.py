"""Serialization, tokens, hash order, samples and hash embeddings: column expressions without Python."""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

DELIMITER, MAX_CHARS, DIMS = "|", 400, 64
NOT_WORD = r"[^\p{L}\p{N}]+"


def serialize(df: DataFrame, cols: list[str] | None = None, delim: str = DELIMITER, max_chars: int = MAX_CHARS) -> Column:
    """The named columns as one string; each field is cut to max_chars, nulls are empty fields, nested values JSON."""
    kinds = dict(df.dtypes)

    def field(c: str) -> Column:
        text = F.to_json(c) if kinds[c].startswith(("array", "map", "struct")) else F.col(c).cast("string")
        return F.substring(F.coalesce(text, F.lit("")), 1, max_chars)

    return F.concat_ws(delim, *[field(c) for c in cols or df.columns])


def tag_ids(df: DataFrame, side: str, key: str, text: Column) -> DataFrame:
    return df.select(F.lit(side).alias("side"), F.col(key).cast("long").alias("id"), text.alias("text"))


def tokens(text: Column) -> Column:
    """Stand-in token count: a quarter of the characters, rounded up."""
    return F.ceil(F.length(text) / F.lit(4.0)).cast("long")


def md5_int(text: Column) -> Column:
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")


def order_key(seed: int, *ids: str) -> Column:
    """What "random" order means here: md5 of the seed and the ids, the same in every engine and partitioning."""
    return F.md5(F.concat_ws(":", F.lit(str(seed)), *[F.col(i).cast("string") for i in ids]))


def bottom_n(df: DataFrame, n: int, seed: int = 7, key: str = "id") -> DataFrame:
    return df.orderBy(order_key(seed, key), key).limit(n)


def cut_fields(text: Column, delim: str = DELIMITER, max_chars: int = MAX_CHARS) -> Column:
    """A serialized row with each field cut, not the row: a long first field hides no later one. Null is empty."""
    return F.concat_ws(delim, F.transform(F.split(text, re.escape(delim)), lambda f: F.substring(f, 1, max_chars)))


def embed_words(text: Column, dims: int = DIMS) -> Column:
    """Counts of hashed words, at most MAX_CHARS characters of a field: a stand-in encoder with exact integers."""
    words = F.filter(F.split(F.lower(cut_fields(text)), NOT_WORD), lambda w: w != "")
    return _counts(F.transform(words, lambda w: F.pmod(md5_int(w), F.lit(dims))), dims)


def embed_trigrams(text: Column, dims: int = DIMS) -> Column:
    low = F.lower(cut_fields(text))
    grams = F.when(F.length(low) < 3, F.array(low)).otherwise(F.transform(F.sequence(F.lit(1), F.greatest(F.length(low) - 2, F.lit(1))), lambda i: F.substring(low, i, F.lit(3))))
    return _counts(F.transform(grams, lambda w: F.pmod(md5_int(w), F.lit(dims))), dims)


def _counts(buckets: Column, dims: int) -> Column:
    # The outer array binds the buckets to a variable, so they are computed once a row, not once a dimension.
    return F.transform(F.array(buckets), lambda k: F.transform(F.sequence(F.lit(0), F.lit(dims - 1)), lambda i: F.size(F.filter(k, lambda b: b == i)).cast("long")))[0]


def quantize(vector: Column) -> Column:
    """Fixed-point longs of a float vector, in millionths."""
    return F.transform(vector, lambda x: F.round(x.cast("double") * 1e6).cast("long"))


#: Encoders by name. The first one is what an unknown name falls back to; encoders that are not
#: installed run as the local stand-in given here, and reports say so.
ENCODERS = {"all-mpnet-base-v2": embed_words, "all-MiniLM-L6-v2": embed_trigrams, "hash-word-64": embed_words, "hash-char3-64": embed_trigrams}
STAND_INS = {"all-mpnet-base-v2": "hash-word-64", "all-MiniLM-L6-v2": "hash-char3-64"}


def register_encoder(name: str, load: Callable[[], Callable[[list[str]], list]], replaces: str | None = None) -> None:
    """Make an encoder known by name. load runs once in each Python worker and returns a function from a list
    of texts to float vectors, which is called in Arrow batches; vectors are kept in millionths, as integers.
    replaces: a name whose stand-in gives way to this encoder. Register before the advisor is asked."""

    @F.pandas_udf("array<bigint>")
    def encode(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        run = load()
        for texts in batches:
            yield pd.Series([[round(float(x) * 1e6) for x in v] for v in run(texts.fillna("").tolist())], dtype=object)

    for known in filter(None, (name, replaces)):
        ENCODERS[known] = lambda text: encode(cut_fields(text))
        STAND_INS.pop(known, None)
