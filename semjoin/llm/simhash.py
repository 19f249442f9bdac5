"""SimHash near-duplicates: fingerprints, pigeonhole blocks, Hamming check, components."""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semjoin.llm.common import KEY, components, content_key, forget, keyed, materialize, same_key, small, text_bytes, without_rows
from semjoin.llm.similar import similar_links, sketch

BITS = 64
#: A bucket with more distinct fingerprints than this leaves the grouped path for the exploded one.
GROUP_LIMIT = 20_000


def fingerprint(text: bytes, ngram: int = 3, seed: int = 42) -> int:
    """Unsigned 64-bit fingerprint: a bit is set if it is set in over half of the shingles' XXH64 hashes.

    A-Z are lower-cased; repeated shingles count each time; fewer words than `ngram` make one shingle;
    no words make fingerprint 0.
    """
    words = text.lower().split()
    if not words:
        return 0
    digest = xxhash.xxh64_intdigest
    if len(words) < ngram:
        shingles = [b" ".join(words)]
    else:
        shingles = map(b" ".join, zip(*(words[i:] for i in range(ngram)), strict=False))
    hashes = np.fromiter((digest(s, seed) for s in shingles), np.uint64)
    ones = np.zeros(BITS, np.int64)
    for at in range(0, len(hashes), 1 << 16):
        part = hashes[at : at + (1 << 16)].astype("<u8").view(np.uint8).reshape(-1, 8)
        ones += np.unpackbits(part, axis=1, bitorder="little").sum(0, dtype=np.int64)
    return sum(1 << int(i) for i in np.nonzero(2 * ones > len(hashes))[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", ngram: int = 3) -> DataFrame:
    """(doc_id, fp long) for every row; fp holds the 64 bits as a signed long. Null texts count as empty."""

    @F.pandas_udf("long")
    def of(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for texts in batches:
            yield pd.Series(np.array([fingerprint(bytes(t), ngram) for t in texts], dtype=np.uint64).view(np.int64))

    return docs.select(F.col(id_col).alias("doc_id"), of(text_bytes(text_col)).alias("fp"))


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def block_masks(max_bits: int, blocks: int) -> list[int]:
    """Bit masks of all choices of blocks - max_bits of the blocks: two fingerprints that differ in at
    most max_bits bits agree under one of the masks, as the differing bits touch max_bits blocks at most."""
    edges = [round(i * BITS / blocks) for i in range(blocks + 1)]
    masks = [sum(1 << j for j in range(edges[i], edges[i + 1])) for i in range(blocks)]
    return [sum(masks[i] for i in kept) for kept in itertools.combinations(range(blocks), blocks - max_bits)]


def _star_edges(values: np.ndarray, free: list[int], max_bits: int) -> list[tuple[int, int]]:
    """Edges that connect just what pairs of at most max_bits differing bits connect, among distinct
    values that agree outside the bits in `free`. Linear in values for each choice of cleared bits."""
    n = len(values)
    parent = np.arange(n)

    def find(i: int) -> int:
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    edges = []

    def link(i: int, j: int) -> None:
        a, b = find(i), find(j)
        if a != b:
            parent[max(a, b)] = min(a, b)
            edges.append((int(values[i].view(np.int64)), int(values[j].view(np.int64))))

    if n <= 200:
        diff = np.bitwise_count(values[:, None] ^ values[None, :])
        for i, j in zip(*np.nonzero(np.triu(diff <= max_bits, 1)), strict=True):
            link(int(i), int(j))
        return edges
    for bits in itertools.combinations(free, min(max_bits, len(free))):
        cleared = values & np.uint64(~sum(1 << b for b in bits) & (2**64 - 1))
        order = np.argsort(cleared, kind="stable")
        same = np.nonzero(cleared[order][1:] == cleared[order][:-1])[0]
        for k in same:
            link(int(order[k]), int(order[k + 1]))
    return edges


def close_edges(fps: DataFrame, max_bits: int = 2, blocks: int = 5, group_limit: int = GROUP_LIMIT) -> DataFrame:
    """Edges (a, b) between distinct fingerprints (column fp, no repeats) that connect exactly what all
    pairs within max_bits bits connect.

    Each fingerprint is emitted once for each choice of blocks; rows that share a block key are in one
    bucket. A bucket of two is one Hamming check. Buckets up to group_limit go to one task each, which
    links them without enumerating pairs. Larger buckets are exploded to copies with max_bits of the
    free bits cleared: copies that are equal are within max_bits by themselves, a group has at most
    2 ** max_bits of them, and the work stays linear however hot the bucket is.
    """
    spark = fps.sparkSession
    masks = block_masks(max_bits, blocks)
    keys = fps.select("fp", F.explode(F.array(*[F.struct(F.lit(c).alias("c"), F.col("fp").bitwiseAND(F.lit(_signed(m))).alias("k")) for c, m in enumerate(masks)])).alias("x")).select("fp", "x.c", "x.k")
    sizes = materialize(keys.groupBy("c", "k").agg(F.count(F.lit(1)).alias("n"), F.min("fp").alias("a"), F.max("fp").alias("b")).where("n > 1"), "buckets")
    pairs = sizes.where(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= max_bits).where("n = 2").select("a", "b")
    more = keys.join(sizes.where("n > 2").select("c", "k", "n"), ["c", "k"])

    def grouped(pdf: pd.DataFrame) -> pd.DataFrame:
        mask = masks[int(pdf["c"].iloc[0])]
        values = np.sort(pdf["fp"].to_numpy(np.int64).view(np.uint64))
        found = _star_edges(values, [i for i in range(BITS) if not mask >> i & 1], max_bits)
        return pd.DataFrame(found, columns=["a", "b"]).astype("int64")

    mid = more.where(F.col("n") <= group_limit).select("c", "k", "fp").groupBy("c", "k").applyInPandas(grouped, "a long, b long")
    edges = pairs.union(mid)
    if sizes.where(F.col("n") > group_limit).limit(1).count():
        cleared = [(c, [i for i in range(BITS) if not m >> i & 1]) for c, m in enumerate(masks)]
        choices = spark.createDataFrame([(c, _signed(~sum(1 << b for b in bits) & (2**64 - 1))) for c, free in cleared for bits in itertools.combinations(free, min(max_bits, len(free)))], "c int, clear long")
        hot = more.where(F.col("n") > group_limit).select("c", "fp").join(F.broadcast(choices), "c").select("clear", F.col("fp").bitwiseAND(F.col("clear")).alias("v"), "fp").distinct()
        stars = hot.groupBy("clear", "v").agg(F.array_sort(F.collect_list("fp")).alias("g")).where("size(g) > 1")
        edges = edges.union(stars.select(F.col("g")[0].alias("a"), F.explode(F.slice("g", 2, 2**max_bits)).alias("b")))
    return edges


def fingerprint_groups(marked: DataFrame, max_bits: int = 2, blocks: int = 5) -> DataFrame:
    """(fp, component_id): of each fingerprint in marked (doc_id, fp), the smallest doc_id reachable over links.
    Equal fingerprints are collapsed before any pair is formed."""
    fps = materialize(marked.groupBy("fp").agg(F.min("doc_id").alias("first")), "distinct")
    comps = components(close_edges(fps.select("fp"), max_bits, blocks))
    nodes = comps.union(comps.select("root", "root")).distinct().withColumnsRenamed({"node": "fp"})
    firsts = nodes.join(fps, "fp").groupBy("root").agg(F.min("first").alias("linked"))
    linked = nodes.join(firsts, "root").select("fp", "linked")
    ids = materialize(fps.join(linked, "fp", "left").select("fp", F.coalesce("linked", "first").alias("component_id")), "classes")
    forget(fps)
    return ids


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", ngram: int = 3, max_bits: int = 2, blocks: int = 5) -> DataFrame:
    """One row per row of docs: doc_id, fp (signed long), component_id (smallest doc_id reachable over links).

    Links join fingerprints that differ in at most max_bits bits. Null ids keep their rows and never become a
    component_id unless the whole component has none. Empty and null texts have fingerprint 0, linked like any
    other. Repeated rows stay. Extra columns are not read.
    """
    marked = materialize(fingerprints(docs, id_col, text_col, ngram), "fingerprints")
    return marked.join(fingerprint_groups(marked, max_bits, blocks), "fp").select("doc_id", "fp", "component_id")


def fingerprint_hex(fp) -> F.Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


def numbered(docs: DataFrame, ngram: int = 5, own_ngram: int = 3) -> DataFrame:
    """Each row of docs (doc_id, text) with its content key, a number n of its own, fp, set_hash and block keys;
    written, so that numbers stay."""

    @F.pandas_udf("fp long, set_hash long, keys array<long>")
    def of(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        for texts in batches:
            out = [(_signed(fingerprint(bytes(t), own_ngram)), *sketch(bytes(t), ngram)) for t in texts]
            yield pd.DataFrame(out, columns=["fp", "set_hash", "keys"])

    rows = docs.select(*content_key("doc_id", "text"), F.monotonically_increasing_id().alias("n"), of(text_bytes("text")).alias("x"))
    return materialize(rows.select(*KEY, "n", "x.*"), "rows")


def first_of_group(docs: DataFrame, ngram: int = 5, threshold: float = 0.8, max_bits: int = 2, blocks: int = 5) -> DataFrame:
    """docs without all but one row of each near-duplicate group: the one with the smallest id.

    Groups are the components of two kinds of links: fingerprints at most max_bits bits apart, and sets of
    shingles of `ngram` words with a Jaccard similarity of `threshold` or more. Rows, not ids, are grouped: each text
    of a repeated id is in the group of that text, and of equal rows one stays. Rows with null ids are left alone and
    stay. Texts without words, null ones too, are one group. Columns stay as they are.
    """
    rows = numbered(docs.where("doc_id is not null").select("doc_id", "text"), ngram)
    classes = fingerprint_groups(rows.select(F.col("n").alias("doc_id"), "fp"), max_bits, blocks)
    prints = rows.select("n", "fp").join(classes, "fp").where("n <> component_id").select(F.col("component_id").alias("a"), F.col("n").alias("b"))
    stars = components(prints.union(similar_links(docs, rows, ngram, threshold)))
    groups = stars.select(F.col("node").alias("n"), "root").union(stars.select("root", "root").distinct())
    members = materialize(rows.select(*KEY, "n").join(groups, "n"), "members")
    first = members.groupBy("root").agg(F.min(F.struct(*KEY, "n")).alias("k"))
    kept = materialize(first.select("k.__id", "k.__h1", "k.__h2", "k.n"), "kept")
    gone = materialize(members.join(kept.select("n"), "n", "left_anti").select(*KEY).distinct(), "gone")
    rest = without_rows(docs, gone)
    # One of the rows that equal a kept one must stay; these few are fetched by themselves.
    again = materialize(gone.join(kept.drop("n"), same_key(gone, kept), "left_semi"), "again")
    if not again.limit(1).count():
        return rest
    every = keyed(docs)
    equal = every.join(small(again, 200_000), same_key(every, again), "left_semi")
    return rest.union(equal.groupBy(*KEY).agg(F.first("__row").alias("__row")).select("__row.*"))
