"""Clusterings: exact integer k-means in column expressions, k-means at scale, density clustering."""

from __future__ import annotations

import math
import sys

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from semjoin.functions.text import order_key
from semjoin.sources.tables import keep


def cluster_count(n: int, ratio: float, least: int = 2, most: int | None = None) -> int:
    k = max(least, math.floor(n * ratio + 1e-9))
    return min(k, most) if most else k


#: Sums of doubles below this are exact.
_EXACT = float(2**53)


def _exact(x: np.ndarray, y: np.ndarray) -> bool:
    """Whether squared distances of these whole numbers are exact in doubles, also as products."""
    most = max((float(np.abs(z).max()) for z in (x, y) if z.size), default=0.0)
    return 4 * x.shape[1] * most * most < _EXACT


def nearest(x: np.ndarray, centers: np.ndarray) -> np.ndarray:
    """Number of the nearest center of each row of whole numbers, by exact squared distance; the lowest of equals."""
    out = np.zeros(len(x), np.int32)
    exact = _exact(x, centers)
    y = centers.astype(float if exact else np.int64)
    own = (y * y).sum(1)
    step = max(1, 2_000_000 // max(1, len(centers)))
    for at in range(0, len(x), step):
        part = x[at : at + step].astype(y.dtype)
        if exact:
            out[at : at + step] = (own - 2 * (part @ y.T)).argmin(1)
        else:
            out[at : at + step] = np.stack([((part - c) ** 2).sum(1) for c in y], 1).argmin(1)
    return out


def _towards_zero(x: int, n: int) -> int:
    return x // n if x >= 0 else -(-x // n)


def kmeans(points: DataFrame, k: int, seed: int = 7, rounds: int = 5) -> DataFrame:
    """(id, cluster) of points (id, v array of long): Lloyd rounds in exact integers.

    Starts from the k points first in md5 order. Each round broadcasts k centers, so that the plan does not grow with them,
    and gathers k sums; an empty cluster keeps its center; means are divided towards zero. Equal points are one point
    with a weight in the rounds, and one in a batch at the end: they have the same nearest center.
    """
    rows = points.orderBy(order_key(seed, "id"), "id").limit(k).collect()
    centers = [list(r["v"]) for r in rows]
    if not centers:
        return points.select("id", F.lit(0).alias("cluster"))
    dims, context = len(centers[0]), points.sparkSession.sparkContext

    def assigned(df: DataFrame, centers: list[list[int]]) -> Column:
        known = context.broadcast(np.array(centers, np.int64))

        def assign(v: pd.Series) -> pd.Series:
            if not len(v):
                return pd.Series([], dtype="int32")
            x = np.stack(v.to_numpy()).astype(np.int64)
            _, first, back = np.unique(x.view(f"V{8 * x.shape[1]}").ravel(), return_index=True, return_inverse=True)
            return pd.Series(nearest(x[first], known.value)[back])

        return F.pandas_udf(assign, "int")(df["v"]).alias("cluster")

    weighted = keep(points.groupBy("v").agg(F.count(F.lit(1)).alias("w")), "vectors")
    for _ in range(rounds):
        dealt = weighted.select("v", "w", assigned(weighted, centers))
        sums = dealt.groupBy("cluster").agg(F.sum("w").alias("n"), F.array(*[F.sum(F.col("v")[d] * F.col("w")) for d in range(dims)]).alias("s")).collect()
        new = list(centers)
        for r in sums:
            new[r["cluster"]] = [_towards_zero(x, r["n"]) for x in r["s"]]
        if new == centers:
            break
        centers = new
    return points.select("id", assigned(points, centers))


def kmeans_at_scale(points: DataFrame, k: int, seed: int = 7, rounds: int = 20) -> DataFrame:
    """(id, cluster) by k-means|| of the machine learning library, for data too large for exact rounds."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    data = points.select("id", array_to_vector(F.transform("v", lambda x: x.cast("double"))).alias("features"))
    model = KMeans(k=k, seed=seed, maxIter=rounds).fit(data)
    return model.transform(data).select("id", F.col("prediction").alias("cluster"))


#: Points of a cell of density clustering with `cells`: its time grows with their square.
MAX_DENSE = 20_000
#: Points of a block of density clustering; the distances of two blocks are in memory at once.
DENSE_BLOCK = 2_000


def squares(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Squared distances of the rows of x and y as doubles: exact for whole numbers that are not too large."""
    if x.dtype.kind in "iu" and _exact(x, y):
        x, y = x.astype(float), y.astype(float)
        out = x @ y.T
        out *= -2
        out += (x * x).sum(1)[:, None]
        out += (y * y).sum(1)
        return out
    x, y, out = x.astype(float), y.astype(float), np.empty((len(x), len(y)))
    for i in range(len(x)):
        out[i] = ((y - x[i]) ** 2).sum(1)
    return out


def core_squares(x: np.ndarray, lo: int, hi: int, min_samples: int) -> np.ndarray:
    """Of rows lo to hi: squared distance to the min_samples-th nearest of all rows, the row itself being the first."""
    k = min(min_samples, len(x))
    best = np.full((hi - lo, k), np.inf)
    for at in range(0, len(x), DENSE_BLOCK):
        some = squares(x[lo:hi], x[at : at + DENSE_BLOCK])
        nearer = np.flatnonzero(some.min(1) < best.max(1))
        best[nearer] = np.partition(np.concatenate([best[nearer], some[nearer]], 1), k - 1, 1)[:, :k]
    return best.max(1)


def tree_of(x: np.ndarray, core: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Edges (squared mutual reachability, lower row, higher row) of the spanning tree that is least in this order of
    edges. The order leaves no ties, so there is one such tree."""
    n = len(x)
    reach = squares(x, x)
    np.maximum(reach, core, out=reach)
    np.maximum(reach, core[:, None], out=reach)
    best, origin, open_ = np.full(n, np.inf), np.full(n, n), np.ones(n, bool)
    w, i, j = np.empty(n - 1), np.empty(n - 1, np.int64), np.empty(n - 1, np.int64)
    at = 0
    for step in range(n - 1):
        open_[at] = False
        row = reach[at]
        closer = open_ & ((row < best) | ((row == best) & (at < origin)))
        best[closer], origin[closer] = row[closer], at
        best[at] = np.inf
        equal = np.flatnonzero(best == best.min())
        if len(equal) > 1:
            equal = equal[np.lexsort((np.maximum(equal, origin[equal]), np.minimum(equal, origin[equal])))]
        at = int(equal[0])
        w[step], i[step], j[step] = best[at], min(at, origin[at]), max(at, origin[at])
    return w, i, j


def tree_between(x: np.ndarray, y: np.ndarray, core_x: np.ndarray, core_y: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """tree_of, of the edges from a row of x to a row of y alone: (squared mutual reachability, row of x, row of y)."""
    m, n = len(x), len(x) + len(y)
    reach = squares(x, y)
    np.maximum(reach, core_y, out=reach)
    np.maximum(reach, core_x[:, None], out=reach)
    back = np.ascontiguousarray(reach.T)
    # Rows of x come first. Of rows in the tree, best is above and limit below any edge.
    best, limit, origin = np.full(n, np.inf), np.full(n, np.inf), np.full(n, n)
    w, i, j = np.empty(n - 1), np.empty(n - 1, np.int64), np.empty(n - 1, np.int64)
    at = 0
    for step in range(n - 1):
        best[at], limit[at] = np.inf, -np.inf
        row, side = (reach[at], slice(m, n)) if at < m else (back[at - m], slice(0, m))
        closer, same = row < limit[side], row == limit[side]
        if same.any():
            closer |= same & (at < origin[side])
        for column in (best, limit):
            np.copyto(column[side], row, where=closer)
        origin[side][closer] = at
        at = int(best.argmin())
        equal = np.flatnonzero(best == best[at])
        if len(equal) > 1:
            at = int(equal[np.lexsort((np.maximum(equal, origin[equal]), np.minimum(equal, origin[equal])))[0]])
        w[step], i[step], j[step] = best[at], min(at, origin[at]), max(at, origin[at]) - m
    return w, i, j


def least_tree(n: int, w: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The least spanning tree of n nodes among these edges, in the order of tree_of, sorted: in each round every part
    takes its first edge that leads out."""
    order = np.lexsort((hi, lo, w))
    w, lo, hi = w[order], lo[order], hi[order]
    every, part, taken, left = np.arange(n), np.arange(n), [np.zeros(0, np.int64)], np.arange(len(w))
    while True:
        a, b = part[lo[left]], part[hi[left]]
        out = a != b
        left, a, b = left[out], a[out], b[out]
        if not len(left):
            break
        first, second = np.full(n, len(w)), np.full(n, len(w))
        first[a[::-1]], second[b[::-1]] = left[::-1], left[::-1]
        first = np.minimum(first, second)
        some = np.flatnonzero(first < len(w))
        taken.append(np.unique(first[some]))
        up = every.copy()
        up[some] = part[lo[first[some]]] + part[hi[first[some]]] - some
        tops = (up[up] == every) & (every <= up)
        up[tops] = every[tops]
        while not np.array_equal(up[up], up):
            up = up[up]
        part = up[part]
    pick = np.sort(np.concatenate(taken))
    return w[pick], lo[pick], hi[pick]


def hdbscan_labels(x: np.ndarray, min_cluster_size: int = 5, min_samples: int = 5) -> np.ndarray:
    """Cluster of each row, -1 for noise: spanning tree over mutual reachability, condensed hierarchy, the
    clusters of greatest stability. Rows must be in a fixed order; of equal distances the edge of lower rows comes first."""
    if len(x) < max(2, min_cluster_size):
        return np.full(len(x), -1)
    return labels_of_tree(len(x), *least_tree(len(x), *tree_of(x, core_squares(x, 0, len(x), min_samples))), min_cluster_size)


def labels_of_tree(n: int, w: np.ndarray, lo: np.ndarray, hi: np.ndarray, min_cluster_size: int) -> np.ndarray:
    """hdbscan_labels of a spanning tree whose edges are sorted."""
    edges = zip(np.sqrt(w).tolist(), lo.tolist(), hi.tolist(), strict=True)
    parent, size, kids, height = list(range(n)), [1] * n, [None] * n, [0.0] * n

    def find(i: int) -> int:
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    for w, i, j in edges:
        a, b = find(i), find(j)
        parent.append(len(parent))
        parent[a] = parent[b] = len(parent) - 1
        size.append(size[a] + size[b])
        kids.append((a, b))
        height.append(w)

    def members_of(r: int) -> list[int]:
        out, work = [], [r]
        while work:
            y = work.pop()
            if kids[y] is None:
                out.append(y)
            else:
                work += kids[y]
        return out

    lam = lambda w: 1 / w if w > 0 else 1e12
    stability: dict[int, float] = {}
    below: dict[int, list[int]] = {}

    def condense(root: int, born: float) -> None:
        """Follow a cluster down until it splits into two large enough; smaller parts fall off as noise."""
        total, node = 0.0, root
        while kids[node] is not None:
            a, b = kids[node]
            death = lam(height[node])
            big = [k for k in (a, b) if size[k] >= min_cluster_size]
            if len(big) == 2:
                total += size[node] * (death - born)
                below[root] = big
                stability[root] = total
                for k in big:
                    condense(k, death)
                return
            lost = size[node] - (size[big[0]] if big else 0)
            total += lost * (death - born)
            if not big:
                break
            node = big[0]
        stability[root] = total
        below[root] = []

    root = len(parent) - 1
    sys.setrecursionlimit(max(10_000, 4 * n))
    condense(root, 0.0)

    def select(c: int) -> tuple[float, list[int]]:
        inner = [select(k) for k in below[c]]
        deep = sum(s for s, _ in inner)
        if below[c] and (deep > stability[c] or c == root):
            return deep, [y for _, ys in inner for y in ys]
        return stability[c], [c]

    out = np.full(n, -1)
    chosen = select(root)[1]
    groups = sorted((min(m), m) for m in (members_of(c) for c in chosen))
    for number, (_, m) in enumerate(groups):
        out[m] = number
    return out


def hdbscan(points: DataFrame, min_cluster_size: int = 5, min_samples: int = 5, cells: bool = False, max_points: int | None = None, block: int = DENSE_BLOCK) -> DataFrame:
    """(id, cluster) with -1 for noise. Exact for any number of points: over two blocks of them the spanning tree is put
    together from those of all pairs of blocks, in many tasks, with the same result; time grows with the square of their
    number. With max_points more of them raise. With `cells` that is asked for: k-means at scale deals the points into cells
    of about max_points / 4, and each is clustered by itself, a cell that is too large after all in cells of its own."""
    if not cells:
        n = points.count()
        if max_points is not None and n > max_points:
            raise ValueError(f"over {max_points} points: use cells=True or k-means")
        if n > 2 * block:
            return _blockwise(points, min_cluster_size, min_samples, block)
        dealt = points.withColumn("cell", F.lit(0))
    else:
        max_points = max_points or MAX_DENSE
        dealt = _cells(points, max_points)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("id")
        got = hdbscan_labels(np.array(pdf["v"].tolist()), min_cluster_size, min_samples)
        cell = int(pdf["cell"].iloc[0])
        return pd.DataFrame({"id": pdf["id"].to_numpy(), "cluster": np.where(got < 0, -1, got + cell * (max_points or 0)).astype("int32")})

    return dealt.select("id", "v", "cell").groupBy("cell").applyInPandas(run, "id long, cluster int")


def _blockwise(points: DataFrame, min_cluster_size: int, min_samples: int, block: int) -> DataFrame:
    """hdbscan() of many points. The points are gathered and broadcast in whole; what grows with their square, the distances,
    is never in one place. Each edge of the least tree is in the least tree of its block, or of the edges between its two
    blocks, so these trees hold it."""
    spark = points.sparkSession
    ids, x = _gathered(points)
    n = len(x)
    starts = list(range(0, n, block))
    known = spark.sparkContext.broadcast(x)

    def cores(batches):
        for pdf in batches:
            for lo in (block * b for b in pdf["id"].tolist()):
                hi = min(lo + block, n)
                yield pd.DataFrame({"at": np.arange(lo, hi), "core": core_squares(known.value, lo, hi, min_samples)})

    found = spark.range(0, len(starts), 1, len(starts)).mapInPandas(cores, "at long, core double").toPandas()
    core = np.empty(n)
    core[found["at"].to_numpy()] = found["core"].to_numpy()
    near = spark.sparkContext.broadcast(core)
    pairs = [(a, b) for i, a in enumerate(starts) for b in starts[i:]]

    def trees(batches):
        for pdf in batches:
            for a, b in (pairs[p] for p in pdf["id"].tolist()):
                one, two = slice(a, a + block), slice(b, b + block)
                x, core = known.value, near.value
                w, i, j = tree_of(x[one], core[one]) if a == b else tree_between(x[one], x[two], core[one], core[two])
                yield pd.DataFrame({"w": w, "i": i + a, "j": j + b})

    edges = keep(spark.range(0, len(pairs), 1, min(len(pairs), 512)).mapInPandas(trees, "w double, i long, j long"), "edges")

    def label(pdf: pd.DataFrame) -> pd.DataFrame:
        tree = least_tree(n, pdf["w"].to_numpy(), pdf["i"].to_numpy(), pdf["j"].to_numpy())
        return pd.DataFrame({"id": ids, "cluster": labels_of_tree(n, *tree, min_cluster_size).astype("int32")})

    return edges.groupBy().applyInPandas(label, "id long, cluster int")


def _gathered(points: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """ids and vectors in the order of ids, as arrays all the way: rows of Python numbers would fill the driver."""
    table = points.select("id", "v").toArrow()
    ids, vectors = table["id"].to_numpy(), table["v"].combine_chunks()
    x = vectors.flatten().to_numpy().reshape(len(ids), -1)
    small = np.iinfo(np.int32)
    if x.dtype.kind == "i" and small.min < x.min() and x.max() <= small.max:
        x = x.astype(np.int32)
    order = np.argsort(ids, kind="stable")
    return ids[order], x[order]


def _cells(points: DataFrame, max_points: int, depth: int = 0) -> DataFrame:
    """points with `cell`, none of more than max_points points: large cells are dealt again, at last by a hash."""
    n = points.count()
    if n <= max_points:
        return points.withColumn("cell", F.lit(0))
    k = -(-4 * n // max_points)
    if depth < 3:
        found = points.join(kmeans_at_scale(points, k).withColumnRenamed("cluster", "cell"), "id")
    else:
        found = points.withColumn("cell", F.pmod(F.xxhash64("id"), F.lit(k)).cast("int"))
    found = keep(found, "cells")
    sizes = found.groupBy("cell").agg(F.count(F.lit(1)).alias("n")).collect()
    large = [r["cell"] for r in sizes if r["n"] > max_points]
    out = found.where(~F.col("cell").isin(large)) if large else found
    base = k
    for c in large:
        more = _cells(found.where(F.col("cell") == c).drop("cell"), max_points, depth + 1)
        out = out.unionByName(more.withColumn("cell", F.col("cell") + F.lit(base)))
        base += 100_000
    return out
