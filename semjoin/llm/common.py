"""Shared building blocks: written intermediates, size-checked broadcasts, exact ranks and components."""

from __future__ import annotations

import contextlib
import tempfile
import threading
import uuid
from collections.abc import Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Separators between words: U+0020 and U+0009 to U+000D. Fixed values.
SPACE = " \t\n\x0b\f\r"
SPACE_RUN = "[ \\t\\n\\x0B\\f\\r]+"

_own_dir: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder named in spark.checkpoint.dir; only where that is unset, a folder of our own
    (local temporary in local mode, below the warehouse otherwise)."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if named:
        return named.rstrip("/")
    if not _own_dir:
        local = spark.sparkContext.master.startswith("local[") or spark.sparkContext.master == "local"
        _own_dir.append("file://" + tempfile.mkdtemp(prefix="corpus-work-") if local else spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/corpus-work")
    return _own_dir[0]


def materialize(df: DataFrame, tag: str) -> DataFrame:
    """Write df to the shared folder and read it back: lineage is cut, lost executors cost nothing."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._work_path = path
    if getattr(_scope, "paths", None) is not None:
        _scope.paths.append(path)
    return out


_scope = threading.local()


@contextlib.contextmanager
def stage_scope(docs: DataFrame) -> Iterator[None]:
    """Around a stage whose input has been written and read again: deletes the intermediates that earlier
    stages of this thread left, but for those that docs itself still reads, and notes those of this stage."""
    old = getattr(_scope, "kept", [])
    if old:
        read = docs.inputFiles()
        _scope.kept = [p for p in old if any(p.removeprefix("file://") in f for f in read)]
        for p in set(old) - set(_scope.kept):
            _delete(docs.sparkSession, p)
    _scope.paths = []
    try:
        yield
    finally:
        _scope.kept, _scope.paths = getattr(_scope, "kept", []) + _scope.paths, None


def forget(*frames: DataFrame) -> None:
    """Delete tables that materialize() wrote and nobody will read again."""
    for df in frames:
        path = getattr(df, "_work_path", None)
        if path:
            _delete(df.sparkSession, path)


def _delete(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def packed(docs: DataFrame, *names: str) -> DataFrame:
    """The named columns of docs and each whole row as the column __row: helper columns beside it cannot clash with
    columns of docs, and select("__row.*") gives the rows back as they were."""
    return docs.select(F.struct("*").alias("__row"), *names)


def content_key(id_col: str | Column, text_col: str | Column) -> list[Column]:
    """__id, __h1, __h2: the id and 128 bits of the text. Rows of equal key are equal in id and text; rows that share
    an id alone are told apart. A null text counts as empty."""
    text = text_bytes(text_col)
    return [(F.col(id_col) if isinstance(id_col, str) else id_col).alias("__id"), F.xxhash64(text).alias("__h1"), F.xxhash64(text, F.lit("second")).alias("__h2")]


KEY = ["__id", "__h1", "__h2"]


def same_key(left: DataFrame, right: DataFrame) -> Column:
    """Join condition of equal content keys; null ids are equal."""
    return left["__id"].eqNullSafe(right["__id"]) & (left["__h1"] == right["__h1"]) & (left["__h2"] == right["__h2"])


def keyed(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """packed() rows with their content key."""
    rows = packed(docs)
    return rows.select("__row", *content_key(F.col("__row")[id_col], F.col("__row")[text_col]))


def without_rows(docs: DataFrame, gone: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs without the rows whose content key is in gone (KEY); columns stay as they are."""
    rows = keyed(docs, id_col, text_col)
    return rows.join(small(gone, 200_000), same_key(rows, gone), "left_anti").select("__row.*")


def small(df: DataFrame, max_rows: int) -> DataFrame:
    """df with a broadcast hint if it has at most max_rows rows (counted), else unchanged, for a shuffle join."""
    return F.broadcast(df) if df.limit(max_rows + 1).count() <= max_rows else df


def text_bytes(col: str | Column) -> Column:
    """UTF-8 bytes; a null text counts as empty."""
    return F.coalesce(F.col(col) if isinstance(col, str) else col, F.lit("")).cast("binary")


def words_of(text: Column) -> Column:
    """Words of a text: runs of anything but SPACE; null and blank texts have none."""
    trimmed = F.trim(F.coalesce(text, F.lit("")), F.lit(SPACE))
    return F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, SPACE_RUN))


def n_words_of(text: Column) -> Column:
    """Number of words_of(text), without keeping them."""
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit("[^ \\t\\n\\x0B\\f\\r]+")).cast("long")


def with_rank(df: DataFrame, groups: list[str], order: list[str], spread: list[str], out: str, total: int, chunk: int = 100_000) -> DataFrame:
    """Gapless 0-based rank of each row in its group, without sorting a group in one task.

    Rows are dealt by a hash of `spread` into total/chunk cells a group; a cell's offset is the sum of
    the sizes of the cells before it, and only inside a cell rows are sorted, by `order`. The rank
    depends on the rows and `total` alone, not on partitions.
    """
    from pyspark.sql import Window

    cells = max(1, -(-total // chunk))
    dealt = df.withColumn("__cell", F.pmod(F.xxhash64(*spread), F.lit(cells)).cast("int"))
    if cells == 1:
        dealt = dealt.withColumn("__offset", F.lit(0).cast("long"))
    else:
        sizes = dealt.groupBy(*groups, "__cell").agg(F.count(F.lit(1)).alias("__size"))
        w = Window.partitionBy(*groups) if groups else Window.partitionBy(F.lit(0))
        sizes = sizes.withColumn("__offset", F.coalesce(F.sum("__size").over(w.orderBy("__cell").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
        on = [*groups, "__cell"]
        cond = None
        s = sizes.select(*[F.col(c).alias(f"__s_{c}") for c in on], "__offset")
        for c in on:
            e = dealt[c].eqNullSafe(s[f"__s_{c}"])
            cond = e if cond is None else cond & e
        dealt = dealt.join(small(s, 200_000), cond, "left").drop(*[f"__s_{c}" for c in on])
    inner = Window.partitionBy(*groups, "__cell").orderBy(*order)
    return dealt.withColumn(out, (F.col("__offset") + F.row_number().over(inner) - 1).cast("long")).drop("__cell", "__offset")


def components(edges: DataFrame) -> DataFrame:
    """Connected components of edges (a long, b long): rows (node, root) for every node but the roots.

    Alternates two star contractions until the edges are a star forest. Each round is a constant number
    of joins and map-side combined minima, and is written to the shared folder; no group is collected.
    """
    def mark(df: DataFrame) -> tuple:
        return tuple(df.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("a", "b")), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())

    low, high = F.least("a", "b"), F.greatest("a", "b")
    cur = materialize(edges.select(low.alias("a"), high.alias("b")).where("a <> b").distinct(), "edges")
    was = mark(cur)
    while was[0]:
        both = cur.select(F.col("a").alias("u"), F.col("b").alias("v")).union(cur.select(F.col("b").alias("u"), F.col("a").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(least, "u").where("m <> v").select(F.col("m").alias("a"), F.col("v").alias("b")).distinct()
        below = large.groupBy("b").agg(F.min("a").alias("m"))
        nxt = large.join(below, "b").where("m <> a").select(F.col("m").alias("a"), F.col("a").alias("b")).union(below.select(F.col("m").alias("a"), "b"))
        nxt = materialize(nxt.distinct(), "edges")
        now = mark(nxt)
        forget(cur)
        cur, done, was = nxt, now == was, now
        if done:
            break
    return cur.select(F.col("b").alias("node"), F.col("a").alias("root"))
