"""Line dedup over a corpus: equal lines by hash, lines one edit apart by deletion neighbourhoods."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from semjoin.llm.common import SPACE, SPACE_RUN, forget, materialize, packed, small

_MIX1, _MIX2, _BASE = 0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x2545F4914F6CDD1D
_BASE_INV = pow(_BASE, -1, 1 << 64)
#: Broadcast of line keys only up to this many rows of 24 bytes.
BROADCAST_ROWS = 200_000
#: Lines with over one row in so many are joined by broadcast, whatever the number of lines.
HOT_SHARE = 50_000
#: Lines of so many code points are compared for one edit, however few words they have.
NEAR_CHARS = 20


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(_MIX2)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(_MIX1)
    return x ^ (x >> np.uint64(32))


def _powers(n: int, base: int) -> np.ndarray:
    out = np.full(n, np.uint64(base))
    out[:1] = 1
    return np.multiply.accumulate(out)


def deletion_hashes(line: str) -> tuple[int, np.ndarray]:
    """Hash of the line and of each of its variants with one code point deleted, in linear time.

    A line's hash is the sum of mix(code point) * BASE**position modulo 2**64: deleting position p
    divides what follows by BASE.
    """
    codes = np.frombuffer(line.encode("utf-32-le"), np.uint32).astype(np.uint64)
    with np.errstate(over="ignore"):
        terms = _mix(codes + np.uint64(_MIX1)) * _powers(len(codes), _BASE)
        upto = np.cumsum(terms, dtype=np.uint64)
        whole = upto[-1] if len(upto) else np.uint64(0)
        return int(_mix(np.array([whole + np.uint64(len(codes))]))[0]), _mix(upto - terms + (whole - upto) * np.uint64(_BASE_INV) + np.uint64(len(codes) - 1))


def block_keys(line: str, blocks: int) -> list[int]:
    """Own keys, then probes: hashes of the line without one of its blocks. Lines of equal length one
    substitution apart share the own key that leaves out the block of the change; of two lines one
    insertion apart, a probe of the longer one (blocks of a length less by one, and one code point more left out)
    is an own key of the shorter one."""
    n, out = len(line), []
    for size, more in ((n, 0), (max(n - 1, 0), 1)):
        for j in range(blocks):
            a, b = j * size // blocks, (j + 1) * size // blocks + more
            out.append(xxhash.xxh64_intdigest((line[:a] + line[b:]).encode(), size * blocks + j))
    return out


def within_one_edit(a: str, b: str) -> bool:
    if abs(len(a) - len(b)) > 1:
        return False
    i, n = 0, min(len(a), len(b))
    while i < n and a[i] == b[i]:
        i += 1
    return a[i + 1 :] == b[i + 1 :] if len(a) == len(b) else (a[i:] == b[i + 1 :] if len(a) < len(b) else a[i + 1 :] == b[i:])


def row_part(text: str | Column) -> Column:
    """What sets the line numbers of a text apart from those of other texts of the same id: 32 bits of a hash over
    31 bits of zeros."""
    return F.shiftleft(F.xxhash64(F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit(""))).bitwiseAND(F.lit(0xFFFFFFFF)), 31)


def lines_of(docs: DataFrame, id_col: str, text_col: str, min_words: int, near_chars: int | None = None, every: bool = False, by_text: bool = False) -> DataFrame:
    """(doc_id, line_no from 0, line, near) of the lines, white space at their ends cut: those with min_words
    words or near_chars code points, which are near, and with `every` all others that are not blank. With by_text,
    line_no has the row_part() of the text in front."""
    cut = docs.where(F.col(id_col).isNotNull()).select(F.col(id_col).alias("doc_id"), (row_part(text_col) if by_text else F.lit(0)).alias("part"), F.posexplode(F.split(F.coalesce(F.col(text_col), F.lit("")), "\n")).alias("line_no", "line"))
    cut = cut.select("doc_id", (F.col("part") + F.col("line_no")).alias("line_no"), F.trim("line", F.lit(SPACE)).alias("line")).where("line <> ''")
    space = SPACE_RUN[1:-2]
    near = F.col("line").rlike(f"^[^{space}]+(?:[{space}]++[^{space}]++){{{max(min_words, 1) - 1}}}")
    near = near if near_chars is None else (F.length("line") >= near_chars) | near
    return cut.withColumn("near", near) if every else cut.where(near).withColumn("near", F.lit(True))


#: Blocks of the first filter, which all lines pass through, and of the second one for the lines that are left.
COARSE, FINE = 2, 16


def _keyed(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """The line replaced by its coarse block keys, which are 0 if it is not near."""
    for pdf in batches:
        none = [0] * (2 * COARSE)
        keys = np.array([block_keys(x, COARSE) if near else none for x, near in zip(pdf["line"], pdf["near"], strict=True)], np.uint64).reshape(-1, 2 * COARSE).view(np.int64)
        yield pdf.drop(columns="line").assign(**{f"k{i}": keys[:, i] for i in range(2 * COARSE)})


def _fine_rows(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for pdf in batches:
        keys = np.array([block_keys(x, FINE) for x in pdf["line"]], np.uint64).reshape(-1, 2 * FINE).view(np.int64)
        yield pd.DataFrame({"h": np.repeat(pdf["h"].to_numpy(), 2 * FINE), "key": keys.ravel(), "own": np.tile(np.arange(2 * FINE) < FINE, len(pdf))})


def _meeting(keys: DataFrame) -> DataFrame:
    """(h): the lines that share a key (h, key, own) with another line for which it is an own key."""
    shared = keys.groupBy("key").agg(F.min("h").alias("lo"), F.max("h").alias("hi"), F.bool_or("own").alias("own")).where("lo <> hi and own").select("key")
    return keys.join(small(materialize(shared, "shared"), BROADCAST_ROWS), "key", "left_semi").select("h").distinct()


def _with_classes(rows: DataFrame, classes: DataFrame) -> DataFrame:
    """rows joined to their class (h, h2, n: its number of rows). Few classes are broadcast; of more, those with over
    one row in HOT_SHARE are, which are HOT_SHARE at most, and no class left for the shuffle is larger."""
    classes = materialize(classes, "moved")
    if classes.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS:
        return rows.join(F.broadcast(classes), ["h", "h2"])
    least = rows.count() // HOT_SHARE
    hot, rest = F.broadcast(classes.where(F.col("n") > least)), classes.where(F.col("n") <= least)
    return rows.join(hot, ["h", "h2"]).unionByName(rows.join(hot, ["h", "h2"], "left_anti").join(rest, ["h", "h2"]))


def _variant_rows(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Kinds: 0 a variant with its position, 1 a variant, 2 the whole line."""
    for pdf in batches:
        for h, line in zip(pdf["h"], pdf["line"], strict=True):
            whole, cut = deletion_hashes(line)
            with np.errstate(over="ignore"):
                placed = _mix(cut + _mix(np.arange(1, len(cut) + 1, dtype=np.uint64)))
            once = np.unique(cut)
            key = np.concatenate([placed, once, [np.uint64(whole)]]).astype(np.uint64).view(np.int64)
            kind = np.repeat(np.array([0, 1, 2], np.int8), [len(placed), len(once), 1])
            yield pd.DataFrame({"h": np.full(len(key), h), "key": key, "kind": kind})


def duplicate_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_words: int = 5, near_chars: int | None = None, every: bool = False, by_text: bool = False) -> DataFrame:
    """Rows (doc_id, line_no, keeper_doc_id, keeper_line_no, edits): each line that an earlier line repeats.

    A line counts if it has min_words words or near_chars code points (for scripts without spaces); with `every`, all
    other lines that are not blank count too, but for equal lines only. White space at its ends does not count. Earlier means a
    smaller (doc_id, line_no). A line goes if an equal line is earlier (edits 0), or if the earliest of the
    lines within one edit (a code point inserted, deleted or replaced) is earlier than all lines equal to
    it (edits 1); the keeper is that earliest line. Links are direct, not chained.

    Near lines: each distinct line emits hashed keys of itself without a block of it, and only lines that
    meet another there - which every line within one edit does - emit their whole deletion neighbourhood, as
    hashed keys; blocks are halves first, then sixteenths for the lines that are left. Two lines share a variant at the same position just if one substitution parts them, and a variant
    of one is the other just if one insertion does; so the earliest member of a key is all that a key needs
    to give, and hot keys stay linear. Pairs are verified on the texts.

    Rows with null ids are left alone and keep nothing. Rows of equal id are one document: the same
    line number of both is kept or goes together; with by_text that holds for rows of equal id and text alone, as
    line numbers then tell texts apart (see lines_of). Null and empty texts and empty tables have no lines.
    Extra columns are not read.
    """
    spots = F.struct("doc_id", "line_no")
    lines = lines_of(docs, id_col, text_col, min_words, near_chars, every, by_text)
    hashed = lines.select("doc_id", "line_no", "near", F.xxhash64("line").alias("h"), F.xxhash64("line", F.lit("second")).alias("h2"), "line")
    names = [f"k{i}" for i in range(2 * COARSE)]
    head = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in hashed.drop("line").schema)
    seen = materialize(hashed.mapInPandas(_keyed, head + "".join(f", {k} long" for k in names)), "lines")
    classes = materialize(seen.groupBy("h", "h2").agg(F.min(spots).alias("first"), F.count(F.lit(1)).alias("n"), F.bool_or("near").alias("near"), *[F.min(k).alias(k) for k in names]), "classes")
    seen, keys = seen.drop("near", *names), classes.where("near").select("h", F.posexplode(F.array(*names)).alias("at", "key"))
    classes = classes.drop(*names)
    near_classes = classes.where("near")

    meet = materialize(_meeting(keys.select("h", "key", (F.col("at") < COARSE).alias("own"))), "meet")
    at = materialize(near_classes.join(small(meet, BROADCAST_ROWS), "h", "left_semi").select(F.col("first.doc_id").alias("doc_id"), F.col("first.line_no").alias("line_no"), "h", "h2"), "survivors")
    holders = materialize(at.select(F.col("doc_id").alias("__id")).distinct(), "holders")
    held = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).join(small(holders, BROADCAST_ROWS), F.col("doc_id") == F.col("__id"), "left_semi")
    again = lines_of(held, "doc_id", "text", min_words, near_chars, by_text=by_text).withColumn("h", F.xxhash64("line")).withColumn("h2", F.xxhash64("line", F.lit("second")))
    texts = again.join(small(at, BROADCAST_ROWS), ["doc_id", "line_no", "h", "h2"]).select("h", "h2", "line", spots.alias("first")).dropDuplicates(["h", "h2"])
    texts = materialize(texts, "texts")
    fine = materialize(_meeting(materialize(texts.select("h", "line").mapInPandas(_fine_rows, "h long, key long, own boolean"), "fine")), "meet")
    texts = materialize(texts.join(small(fine, BROADCAST_ROWS), "h", "left_semi"), "texts")
    forget(meet, at, holders, fine)

    spot_of = texts.select("h", "first")
    variants = texts.select("h", "line").mapInPandas(_variant_rows, "h long, key long, kind byte").join(small(spot_of, BROADCAST_ROWS), "h")
    swaps = F.when(F.col("kind") == 0, F.lit(0)).otherwise(F.lit(1))
    groups = variants.groupBy(swaps.alias("swap"), "key").agg(
        F.min(F.struct("first", "h")).alias("a"), F.max(F.struct("first", "h")).alias("z"),
        F.min(F.when(F.col("kind") == 1, F.struct("first", "h"))).alias("cut"), F.min(F.when(F.col("kind") == 2, F.struct("first", "h"))).alias("whole"))
    wanted = materialize(groups.where("(swap = 0 and a.h <> z.h) or (swap = 1 and cut is not null and whole is not null and cut.h <> whole.h)"), "groups")
    met = variants.withColumn("swap", swaps).join(wanted, ["swap", "key"])
    keeper = F.when(F.col("swap") == 0, F.col("a")).when(F.col("kind") == 1, F.col("whole")).otherwise(F.col("cut"))
    near = met.select("h", F.col("first").alias("own_first"), keeper.alias("k")).where("k.h <> h and k.first < own_first")
    pairs = near.groupBy("h").agg(F.min("k").alias("k")).select("h", F.col("k.h").alias("kh"))
    pairs = pairs.join(texts.select("h", "h2", "line"), "h").join(texts.select(F.col("h").alias("kh"), F.col("line").alias("kline"), F.col("first").alias("keep")), "kh")
    verified = materialize(pairs.where(F.levenshtein("line", "kline", 1) == 1).select("h", "h2", "keep"), "near")
    forget(wanted)

    moved = classes.join(verified, ["h", "h2"], "left").where("n > 1 or keep is not null").select("h", "h2", "n", "first", "keep")
    hit = _with_classes(seen, moved)
    gone = hit.where(F.col("keep").isNotNull() | (F.col("first") < spots))
    kept = F.coalesce("keep", "first")
    return gone.select("doc_id", "line_no", kept["doc_id"].alias("keeper_doc_id"), kept["line_no"].alias("keeper_line_no"), F.when(F.col("keep").isNull(), 0).otherwise(1).alias("edits")).distinct()


def without_lines(docs: DataFrame, gone: DataFrame, by_text: bool = False) -> DataFrame:
    """docs with the lines in `gone` (doc_id, line_no) cut from their texts; a document that loses its last
    word goes. Other documents, and all other columns, stay as they are. by_text as in duplicate_lines()."""
    cuts = materialize(gone.groupBy(F.col("doc_id").alias("__id")).agg(F.array_sort(F.collect_set("line_no")).alias("__cut")), "cuts")
    joined = packed(docs).join(small(cuts, BROADCAST_ROWS), F.col("__row.doc_id") == F.col("__id"), "left")
    part = row_part("__row.text") if by_text else F.lit(0)
    kept = F.array_join(F.filter(F.split("__row.text", "\n"), lambda _, i: ~F.array_contains("__cut", part + i)), "\n")
    new = joined.withColumn("__new", F.when(F.col("__cut").isNull(), F.col("__row.text")).otherwise(kept))
    new = new.where(F.col("__cut").isNull() | (F.col("__new") == F.col("__row.text")) | (F.trim("__new", F.lit(SPACE)) != ""))
    return new.select(*[F.col("__new").alias(c) if c == "text" else F.col("__row")[c].alias(c) for c in docs.columns])


def first_lines(docs: DataFrame, **params) -> DataFrame:
    """docs without the lines that duplicate_lines() reports, each text of a repeated id by itself."""
    return without_lines(docs, duplicate_lines(docs.select("doc_id", "text"), by_text=True, **params), True)
