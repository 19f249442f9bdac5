"""Near copies by similarity: sketch blocks propose pairs, the whole sets of word shingles decide.

A 64-bit SimHash cannot do this: copies at a Jaccard similarity of 0.8 over five words differ in up to 11 bits and
more, and blocks for that many bits would be five bits wide.
"""

from __future__ import annotations

import functools

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from semjoin.llm.common import KEY, components, forget, keyed, materialize, same_key, small, words_of

#: Blocks of a sketch and minima in a block. A pair at 0.8 shares a block with probability 1 - (1 - 0.8^6)^24 = 0.9993.
BLOCKS, ROWS = 24, 6
#: Parts of a large block; each has representatives of its own, so that no text is compared by everybody.
CELLS = 64
#: Shingles that one task compares at a time; a block with more is compared part by part.
MASS = 1_000_000

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


@functools.lru_cache
def _odd(n: int, seed: int) -> np.ndarray:
    return np.random.default_rng(seed).integers(0, 2**63, n, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def shingle_hashes(text: bytes, ngram: int = 5) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the text's word shingles, A-Z lower-cased; fewer words than `ngram`
    make one shingle, no words none."""
    words = text.lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    each = np.fromiter((xxhash.xxh64_intdigest(w) for w in words), np.uint64, len(words))
    n = min(ngram, len(each))
    mixed = np.zeros(len(each) - n + 1, np.uint64)
    for i in range(n):
        mixed = mixed * np.uint64(0x9E3779B97F4A7C15) + each[i : i + len(mixed)]
        mixed ^= mixed >> np.uint64(29)
    return np.unique(mixed)


def block_keys(hashes: np.ndarray, blocks: int = BLOCKS, rows: int = ROWS) -> list[int]:
    """One signed key for each block: equal if the sketches agree in all minima of the block."""
    if not len(hashes):
        return []
    by, plus = _odd(blocks * rows, 1)[:, None], _odd(blocks * rows, 2)[:, None]
    least = np.full(blocks * rows, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(hashes), 4096):
        np.minimum(least, (hashes[None, at : at + 4096] * by + plus).min(1), out=least)
    parts = least.reshape(blocks, rows)
    return np.array([xxhash.xxh64_intdigest(parts[b].tobytes(), b) for b in range(blocks)], np.uint64).view(np.int64).tolist()


def sketch(text: bytes, ngram: int = 5) -> tuple[int, list[int]]:
    """A hash of the whole shingle set of a text, and its block keys."""
    hashes = shingle_hashes(text, ngram)
    return int(np.uint64(xxhash.xxh64_intdigest(hashes.tobytes())).view(np.int64)), block_keys(hashes)


def shingle_set(words: str, ngram: int = 5) -> Column:
    """Distinct XXH64 hashes of the shingles of an array of words, in built-in functions."""
    starts = F.sequence(F.lit(0), F.greatest(F.size(words) - ngram, F.lit(0)))
    hashes = F.transform(starts, lambda i: F.xxhash64(*[F.get(words, i + k) for k in range(ngram)]))
    return F.when(F.size(words) > 0, F.array_distinct(hashes)).otherwise(F.array().cast("array<long>"))


def shared_blocks(firsts: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The pairs (a < b) of ids of the blocks that have two rows, and the members (key, id, top) of the larger
    blocks, top being a block's smallest id."""
    keys = firsts.select("id", F.explode("keys").alias("key"))
    blocks = materialize(keys.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.min("id").alias("a"), F.max("id").alias("b")).where("n > 1 and a < b"), "blocks")
    large = keys.join(blocks.where("n > 2").select("key", F.col("a").alias("top")), "key")
    return blocks.where("n = 2").select("a", "b"), materialize(large, "members")


def candidates(two: DataFrame, large: DataFrame) -> DataFrame:
    """Distinct pairs (a < b) to compare first, without listing a block's pairs.

    A block of two is one pair. In a larger one each member meets the smallest and the largest id of its
    part (one of CELLS, by a hash of the id alone, so that blocks with the same members give the same
    pairs), and each part's smallest id meets the smallest one of the block.
    """
    large = large.withColumn("cell", F.pmod(F.xxhash64("id"), F.lit(CELLS)))
    ends = large.groupBy("key", "cell").agg(F.min("id").alias("low"), F.max("id").alias("high"), F.min("top").alias("top"))
    met = large.select("key", "cell", "id").join(ends, ["key", "cell"]).select(F.explode(F.array(F.struct(F.col("id").alias("x"), F.col("low").alias("y")), F.struct(F.col("id").alias("x"), F.col("high").alias("y")))).alias("p")).select("p.x", "p.y")
    pairs = met.union(ends.select(F.col("low").alias("x"), F.col("top").alias("y"))).where("x <> y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"))
    return two.union(pairs).distinct()


def joining_links(ids: np.ndarray, roots: np.ndarray, sets: list[np.ndarray], threshold: float) -> list[tuple[int, int]]:
    """Links between sets of different groups (roots) that connect what all links of `threshold` or more connect.

    Members of the largest group need no turn: every pair across groups has a member of another group.
    """
    names, group, count = np.unique(roots, return_inverse=True, return_counts=True)
    if len(names) < 2:
        return []
    sizes = np.array([len(s) for s in sets])
    tokens = np.unique(np.concatenate(sets), return_inverse=True)[1]
    starts = np.concatenate([[0], np.cumsum(sizes)[:-1]])
    mine, out = np.zeros(int(tokens.max()) + 1, bool), []
    for i in np.nonzero(group != count.argmax())[0]:
        own = tokens[starts[i] : starts[i] + sizes[i]]
        mine[own] = True
        shared = np.add.reduceat(mine[tokens], starts, dtype=np.int64)
        mine[own] = False
        # Groups that are joined take one number, so each is joined only once.
        for j in np.nonzero(shared >= threshold * (sizes + sizes[i] - shared))[0]:
            if group[i] != group[j]:
                out.append((int(ids[i]), int(ids[j])))
                group[group == group[j]] = group[i]
    return out


def remaining_links(large: DataFrame, links: DataFrame, sets: DataFrame, threshold: float, mass: int = MASS) -> DataFrame:
    """Links (a, b) that the representatives have missed: members of one block that `links` leaves in different groups.

    Only blocks whose members are in two groups or more are looked at, each by a task that returns fewer
    links than the block has groups. A block of more than `mass` shingles is dealt into parts, and each
    two parts are one task: rows in a task stay bounded, and every pair of the block meets.
    """
    members = large.select("key", "id").join(components(links).select(F.col("node").alias("id"), "root"), "id", "left").withColumn("root", F.coalesce("root", "id"))
    members = members.join(sets.select(F.col("doc_id").alias("id"), F.size("s").alias("n")), "id")
    mixed = members.groupBy("key").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.sum("n").alias("all")).where("lo < hi")
    mixed = mixed.select("key", F.ceil(F.col("all") / F.lit(mass)).alias("parts"))
    part = F.pmod(F.xxhash64("id"), F.col("parts"))
    dealt = members.select("key", "id", "root").join(mixed, "key").select("key", "id", "root", part.alias("p"), F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("q"))
    dealt = dealt.select("key", F.least("p", "q").alias("p"), F.greatest("p", "q").alias("q"), "id", "root")
    dealt = dealt.join(sets.select(F.col("doc_id").alias("id"), "s"), "id")

    def join(pdf: pd.DataFrame) -> pd.DataFrame:
        found = joining_links(pdf["id"].to_numpy(), pdf["root"].to_numpy(), [np.asarray(s, np.int64) for s in pdf["s"]], threshold)
        return pd.DataFrame(found, columns=["a", "b"]).astype("int64")

    return dealt.groupBy("key", "p", "q").applyInPandas(join, "a long, b long")


def similar_links(docs: DataFrame, rows: DataFrame, ngram: int = 5, threshold: float = 0.8) -> DataFrame:
    """Links (a, b) of numbers of rows: rows with equal shingle sets to the first of them, and pairs of different sets
    whose Jaccard similarity is `threshold` or more, decided on the whole sets. rows: the content key, number n,
    set_hash and keys of each row of docs.

    Rows without words have equal (empty) sets. The pairs of candidates() come first; remaining_links() then compares
    what they leave apart in each block, so the components of the links are those of all similar pairs that
    share a block.
    """
    marked = rows.select(F.col("n").alias("id"), "set_hash", "keys")
    firsts = materialize(marked.groupBy("set_hash").agg(F.min_by(F.struct("id", "keys"), "id").alias("x")).select("set_hash", "x.id", "x.keys"), "sets")
    equal = marked.select("set_hash", F.col("id").alias("b")).join(firsts.select("set_hash", F.col("id").alias("a")), "set_hash").where("a <> b").select("a", "b")
    two, large = shared_blocks(firsts.select("id", "keys"))
    pairs = materialize(candidates(two, large), "candidates")
    wanted = pairs.select(F.col("a").alias("n")).union(pairs.select("b")).distinct()
    wanted = materialize(rows.select(*KEY, "n").join(wanted, "n", "left_semi"), "wanted")
    every = keyed(docs)
    texts = every.join(small(wanted, 200_000), same_key(every, wanted)).select("n", F.col("__row.text").alias("text"))
    sets = texts.select(F.col("n").alias("doc_id"), words_of(F.translate("text", _UPPER, _LOWER)).alias("w")).select("doc_id", shingle_set("w", ngram).alias("s"))
    sets = materialize(sets.dropDuplicates(["doc_id"]), "shingles")
    # Sizes first: sets whose sizes differ too much cannot be similar, and carry no arrays through the joins.
    sizes = sets.select("doc_id", F.size("s").alias("n"))
    left, right = sizes.select(F.col("doc_id").alias("a"), F.col("n").alias("na")), sizes.select(F.col("doc_id").alias("b"), F.col("n").alias("nb"))
    fit = pairs.join(left, "a").join(right, "b").where(F.least("na", "nb") >= F.lit(threshold) * F.greatest("na", "nb"))
    both = fit.join(sets.select(F.col("doc_id").alias("b"), F.col("s").alias("sb")), "b").join(sets.select(F.col("doc_id").alias("a"), F.col("s").alias("sa")), "a")
    shared = F.size(F.array_intersect("sa", "sb"))
    near = both.where(shared >= F.lit(threshold) * (F.col("na") + F.col("nb") - shared)).select("a", "b")
    links = materialize(equal.union(near), "links")
    out = materialize(links.union(remaining_links(large, links, sets, threshold)), "links")
    forget(firsts, large, pairs, wanted, sets, links)
    return out
