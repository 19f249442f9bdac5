"""Toxicity scores from a logistic model that is regularised on counterfactual texts."""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

_WORD = re.compile(r"\w+")
SPACE_BITS = 22
PREFIXES = (4, 5, 6)
#: Labelled rows to learn from at most, taken in the order of a hash of their ids.
MAX_TRAIN = 12_000

#: Groups of identity terms; a term is swapped for the next one of its group.
IDENTITY = (
    "women men", "woman man", "girls boys", "girl boy", "muslims christians jews hindus buddhists atheists", "muslim christian jewish hindu buddhist atheist",
    "black white asian latino arab", "gay straight lesbian bisexual transgender", "immigrants refugees natives citizens", "immigrant refugee native citizen", "african european american mexican chinese indian",
    "femmes hommes", "femme homme", "musulmans chrétiens juifs", "musulman chrétien juif", "noir blanc arabe", "frauen männer", "frau mann", "muslime christen juden", "schwarze weiße", "mujeres hombres", "mujer hombre", "musulmanes cristianos judíos", "negro blanco árabe",
)


def _next_terms(groups: tuple[str, ...] = IDENTITY) -> dict[str, str]:
    out = {}
    for g in groups:
        terms = g.split()
        out.update(zip(terms, terms[1:] + terms[:1], strict=True))
    return out


class Features(dict):
    """word -> hashed numbers of the word and its prefixes; bounded."""

    def __missing__(self, word: str) -> tuple[int, ...]:
        mask = (1 << SPACE_BITS) - 1
        out = tuple(zlib.crc32(x.encode("utf-8", "surrogatepass")) & mask for x in ["=" + word] + [f"{n}{word[:n]}" for n in PREFIXES if len(word) > n])
        if len(self) < 150_000:
            self[word] = out
        return out


def features_of(words: set[str], known: Features) -> set[int]:
    return {i for w in words for i in known[w]}


def swapped(words: set[str], terms: dict[str, str]) -> set[str]:
    return {terms.get(w, w) for w in words}


def counterfactual(words: set[str], terms: dict[str, str], order: list[str]) -> set[str]:
    """The words with identity terms swapped; words without any get a mention of one, which the words choose, so
    that each labelled text says what its score must be with a group named and without."""
    if words.isdisjoint(terms):
        return words | {order[zlib.crc32(" ".join(sorted(words)).encode("utf-8", "surrogatepass")) % len(order)]}
    return swapped(words, terms)


def train(rows: list[tuple], l1: float = 2e-4, l2: float = 1e-4, fairness: float = 1.0, rounds: int = 300, min_rows: int = 3) -> tuple[float, dict[int, float]]:
    """Intercept and weights from rows (label, features, features added by the swap, features it removes).

    Minimises mean logistic loss + l1 and l2 penalties + fairness * mean squared change of the score under
    the swap, over the rows with identity terms, by accelerated proximal gradients.
    """
    if not rows:
        return -3.0, {}
    y = np.array([r[0] for r in rows], np.float64)
    flat = np.concatenate([np.asarray(r[1], np.int64) for r in rows]) if rows else np.zeros(0, np.int64)
    ids, seen = np.unique(flat, return_counts=True)
    ids = ids[seen >= min(min_rows, max(1, len(rows) // 20))]
    d = len(ids)
    prior = min(max(y.mean(), 1e-3), 1 - 1e-3)
    if not d or y.min() == y.max():
        return float(np.log(prior / (1 - prior))), {}

    def index(values) -> np.ndarray:
        values = np.asarray(values, np.int64)
        at = np.minimum(np.searchsorted(ids, values), d - 1)
        return at[ids[at] == values]

    cols = [index(r[1]) for r in rows]
    row_of, col = np.repeat(np.arange(len(rows)), [len(c) for c in cols]), np.concatenate(cols)
    scale = 1.0 / np.sqrt(np.bincount(col, minlength=d) / len(rows) + 0.01)
    value = scale[col]
    swaps = [(index(r[2]), index(r[3])) for r in rows if len(r[2]) or len(r[3])]
    srow = np.concatenate([np.full(len(a) + len(b), i) for i, (a, b) in enumerate(swaps)]) if swaps else np.zeros(0, np.int64)
    scol = np.concatenate([np.concatenate([a, b]) for a, b in swaps]) if swaps else np.zeros(0, np.int64)
    sval = (np.concatenate([np.concatenate([np.ones(len(a)), -np.ones(len(b))]) for a, b in swaps]) if swaps else np.zeros(0)) * scale[scol]

    n = len(rows)
    norm = np.ones(d) / np.sqrt(d)
    for _ in range(8):
        norm = np.bincount(col, value * np.bincount(row_of, value * norm[col], minlength=n)[row_of], minlength=d)
        top = np.linalg.norm(norm)
        norm /= top
    stop = 0.0
    if len(scol):
        # The largest eigenvalue of the penalty by power iteration, with a margin, or else its bound by rows if that is less.
        side = np.random.default_rng(1).random(d)
        for _ in range(20):
            side = np.bincount(scol, sval * np.bincount(srow, sval * side[scol], minlength=len(swaps))[srow], minlength=d)
            largest = float(np.linalg.norm(side))
            side /= max(largest, 1e-30)
        stop = 2 * fairness * min(1.5 * largest / len(swaps), float(np.bincount(srow, sval**2).max()))
    step = 1.0 / (0.25 * (top + n) / n + 2 * l2 + stop)
    w, b = np.zeros(d), float(np.log(prior / (1 - prior)))
    vw, vb, t = w.copy(), b, 1.0
    for _ in range(rounds):
        z = vb + np.bincount(row_of, value * vw[col], minlength=n)
        err = (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y) / n
        grad = np.bincount(col, value * err[row_of], minlength=d) + 2 * l2 * vw
        if len(scol):
            change = np.bincount(srow, sval * vw[scol], minlength=len(swaps))
            grad += 2 * fairness / len(swaps) * np.bincount(scol, sval * change[srow], minlength=d)
        nw = vw - step * grad
        nw = np.sign(nw) * np.maximum(np.abs(nw) - step * l1, 0)
        nb = vb - step * err.sum()
        nt = (1 + np.sqrt(1 + 4 * t * t)) / 2
        vw, vb = nw + (t - 1) / nt * (nw - w), nb + (t - 1) / nt * (nb - b)
        w, b, t = nw, nb, nt
    keep = np.nonzero(w)[0]
    return float(b), {int(ids[k]): float(w[k] * scale[k]) for k in keep}


def held_out(id_col: str = "doc_id"):
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % 4 == 2


def fit(docs: DataFrame, labels: DataFrame, max_train: int = MAX_TRAIN, **params) -> tuple[float, dict[int, float]]:
    """Learn from labelled documents that are not held out, max_train of them at most; a document with several labels
    counts as toxic if one says so; null labels and ids are left out; rows that repeat an id each count; null texts are
    empty. Every text has a counterfactual (see there), and a score that differs from the counterfactual's is
    penalised by `fairness`. Empty tables give a model that scores all texts alike."""
    marks = labels.where("doc_id is not null and toxic is not null").where(~held_out()).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    chosen = marks.orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_train)
    sample = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(chosen), "doc_id")
    terms = _next_terms()
    order = sorted(terms)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        known = Features()
        for pdf in batches:
            out = []
            for text, label in zip(pdf["text"], pdf["toxic"], strict=True):
                words = set(_WORD.findall(text.lower()))
                own = features_of(words, known)
                other = features_of(counterfactual(words, terms, order), known)
                out.append((int(label), list(own), list(other - own), list(own - other)))
            yield pd.DataFrame(out, columns=["y", "x", "more", "less"])

    got = sample.mapInPandas(run, "y int, x array<int>, more array<int>, less array<int>")
    rows = [(r["y"], np.array(r["x"], np.int32), np.array(r["more"], np.int32), np.array(r["less"], np.int32)) for r in got.toLocalIterator()]
    return train(rows, **params)


def score(docs: DataFrame, model: tuple[float, dict[int, float]], threshold: float = 0.3) -> DataFrame:
    """One row per row of docs: doc_id, held_out, score, predicted. Only the text is read for the score; null
    and empty texts get the score of a text without known words; repeated rows are each scored."""
    known_model = docs.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("double")
    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        b, w = known_model.value
        known, hot = Features(), {}
        for texts in batches:
            out = []
            for text in texts:
                found = set()
                for word in set(_WORD.findall(text.lower())):
                    ids = hot.get(word)
                    if ids is None:
                        ids = tuple(i for i in known[word] if i in w)
                        if len(hot) < 300_000:
                            hot[word] = ids
                    found.update(ids)
                out.append(b + sum(w[i] for i in sorted(found)))
            yield pd.Series(1 / (1 + np.exp(-np.clip(np.array(out, np.float64), -30, 30))))

    scored = docs.select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), run(F.coalesce("text", F.lit(""))).alias("score"))
    return scored.withColumn("predicted", F.when(F.col("score") >= threshold, 1).otherwise(0))


def mention_changes(docs: DataFrame, labels: DataFrame, model: tuple[float, dict[int, float]], threshold: float = 0.3) -> DataFrame:
    """(term, n, false_plain, false_mention, change): held-out documents labelled clean, scored as they are and with one
    neutral sentence about a group behind them; how many pass the threshold, and the mean change of the score. Each
    document gets one term of IDENTITY, by a hash of its id."""
    order = F.array(*[F.lit(x) for x in sorted(_next_terms())])
    clean = labels.where("doc_id is not null and toxic is not null").groupBy("doc_id").agg(F.max("toxic").alias("toxic")).where("toxic = 0").select("doc_id")
    held = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).where(held_out()).join(F.broadcast(clean) if clean.limit(1_000_001).count() <= 1_000_000 else clean, "doc_id", "left_semi")
    held = held.withColumn("term", F.get(order, F.pmod(F.xxhash64("doc_id"), F.size(order)).cast("int")))
    both = held.select("doc_id", "term", F.explode(F.array(F.struct(F.lit(False).alias("named"), "text"), F.struct(F.lit(True).alias("named"), F.concat("text", F.lit(". "), "term", F.lit(" .")).alias("text")))).alias("x"))
    key = F.to_json(F.struct("doc_id", "term", "x.named"))
    scored = score(both.select(key.alias("doc_id"), F.col("x.text").alias("text")), model, threshold).select(F.from_json("doc_id", "doc_id long, term string, named boolean").alias("k"), "score", "predicted").select("k.*", "score", "predicted")
    named = F.col("named")
    return scored.groupBy("term").agg(F.count_if(named).alias("n"), F.count_if(~named & (F.col("predicted") == 1)).alias("false_plain"), F.count_if(named & (F.col("predicted") == 1)).alias("false_mention"), F.avg(F.when(named, F.col("score")).otherwise(-F.col("score")) * 2).alias("change"))
