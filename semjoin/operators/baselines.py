"""Baselines: pairwise, fixed blocks, adaptive blocks, feature filters, similarity, project-then-filter."""

from __future__ import annotations

import dataclasses
import itertools
import math
import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from semjoin.functions.text import ENCODERS, bottom_n, order_key, tokens
from semjoin.models import UNKNOWN, LanguageModel, Prompt, parse_list
from semjoin.plans.invoke import block_prompts, calls_of, pairs_of, row_prompts, run_prompts
from semjoin.sources.tables import CALLS


def block_join(a: DataFrame, b: DataFrame, predicate: str, model: LanguageModel, block: tuple[int, int] = (15, 15), stage: str = "match", buckets: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(matches, calls) of fixed blocks over the full tables."""
    answers = run_prompts(block_prompts(a, b, None, block, stage, buckets), "match", predicate, model, stage)
    return pairs_of(answers), calls_of(answers)


def pairwise_join(a: DataFrame, b: DataFrame, predicate: str, model: LanguageModel, max_calls: int = 1_000_000) -> tuple[DataFrame, DataFrame]:
    """One call for each pair; refused beyond max_calls."""
    n = a.count() * b.count()
    if n > max_calls:
        raise ValueError(f"{n} calls are over the limit of {max_calls}")
    return block_join(a, b, predicate, model, (1, 1))


@dataclasses.dataclass(frozen=True)
class Stats:
    m: int
    n: int
    p: float  # fixed tokens of a prompt
    ta: float
    tb: float
    to: float  # tokens of a reported pair


def measure(a: DataFrame, b: DataFrame, predicate: str, to: float = 2.0) -> Stats:
    one = lambda x: x.agg(F.count(F.lit(1)).alias("n"), F.avg(tokens(F.col("text")) + 1).alias("t")).first()
    ra, rb = one(a), one(b)
    return Stats(ra["n"], rb["n"], 30 + len(predicate) / 4, ra["t"] or 0.0, rb["t"] or 0.0, to)


def choose_blocks(s: Stats, budget: float, selectivity: float) -> tuple[int, int]:
    """Block sizes that fit the budget at the estimated selectivity and need the fewest tokens; of equals, the larger block."""
    best = None
    for ba in range(1, max(1, s.m) + 1):
        room = budget - s.p - ba * s.ta
        bb = min(s.n, math.floor(room / (s.tb + selectivity * ba * s.to))) if room > 0 else 0
        if bb < 1:
            break
        calls = math.ceil(s.m / ba) * math.ceil(s.n / bb)
        cost = calls * s.p + s.m * s.ta * math.ceil(s.n / bb) + s.n * s.tb * math.ceil(s.m / ba) + selectivity * s.m * s.n * s.to
        key = (cost, -ba * bb, ba)
        if best is None or key < best[0]:
            best = (key, (ba, bb))
    return best[1] if best else (1, 1)


def adaptive_block_join(a: DataFrame, b: DataFrame, predicate: str, model, token_budget: int = 4000, selectivity: float = 0.01, growth: float = 4.0, restart: bool = False, max_rounds: int = 12) -> tuple[DataFrame, DataFrame, list[tuple]]:
    """(matches, calls, rounds): blocks sized for a budget at an estimated selectivity.

    A block whose answer overflows the output the estimate allows is dropped and done again in blocks
    for a higher estimate; the others stand. With restart everything is done again. At an estimate of 1, and after
    max_rounds at the latest, blocks that still overflow are halved each round until none is left; a single pair that
    overflows raises. rounds lists
    (round, selectivity, block of A, block of B, calls, overflows). `model` maps an output limit to a model.
    """
    stats = measure(a, b, predicate)
    pending: DataFrame | None = None
    done: list[DataFrame] = []
    calls: list[DataFrame] = []
    rounds = []
    halved = 0
    for number in itertools.count():
        ba, bb = (max(1, x >> halved) for x in choose_blocks(stats, token_budget, selectivity))
        allowed = max(4, math.ceil(selectivity * ba * bb * stats.to) + 2)
        answers = run_prompts(block_prompts(a, b, None, (ba, bb), f"adaptive{number}") if pending is None else _tiled(pending, ba, bb, f"adaptive{number}"), "match", predicate, model(allowed), "match", split=False)
        calls.append(calls_of(answers))
        over = answers.where("row = 'call' and status = 'overflow'").select("call_id")
        n_over = over.count()
        n_calls = calls[-1].count()
        rounds.append((number, selectivity, ba, bb, n_calls, n_over))
        if not n_over or not restart:
            done.append(pairs_of(answers))
        if not n_over:
            break
        if ba == bb == 1 and halved:
            raise RuntimeError(f"{n_over} single pairs overflow the output allowed")
        compared, matched = calls[-1].where("status <> 'overflow'").agg(F.sum(F.col("n_a") * F.col("n_b"))).first()[0] or 0, pairs_of(answers).count()
        seen = matched / compared if compared else 0.0
        if not restart:
            prompts = block_prompts(a, b, None, (ba, bb), f"adaptive{number}") if pending is None else _tiled(pending, ba, bb, f"adaptive{number}")
            pending = prompts.join(F.broadcast(over), "call_id").select("a", "b")
        halved += selectivity >= 1.0
        selectivity = 1.0 if number + 2 > max_rounds else min(1.0, max(growth * selectivity, seen))
    out = done[0]
    for x in done[1:]:
        out = out.unionByName(x)
    log = calls[0]
    for x in calls[1:]:
        log = log.unionByName(x)
    return out, log, rounds


def _tiled(pending: DataFrame, ba: int, bb: int, stage: str) -> DataFrame:
    """Rectangles (a, b) cut into tiles of at most ba x bb."""
    cut = lambda c, n: F.transform(F.sequence(F.lit(0), F.greatest(F.size(c) - 1, F.lit(0)), F.lit(n)), lambda i: F.slice(c, i + 1, F.lit(n)))
    tiles = pending.select(F.explode(cut("a", ba)).alias("a"), "b").select("a", F.explode(cut("b", bb)).alias("b"))
    return tiles.select(F.concat_ws(":", F.lit(stage), F.col("a")[0]["id"], F.size("a"), F.col("b")[0]["id"], F.size("b")).alias("call_id"), F.lit(None).cast("int").alias("ca"), F.lit(None).cast("int").alias("cb"), "a", "b")


# Feature filters in conjunctive normal form.


@dataclasses.dataclass(frozen=True)
class Literal:
    """Distance of a feature is at most theta."""

    feature: str
    distance: str  # equal | gap | jaccard | edit | missing_word
    theta: float


def feature_words(t: Column) -> Column:
    return F.array_distinct(F.filter(F.split(F.lower(t), r"[^\p{L}\p{N}#]+"), lambda w: w != ""))


def feature_distance(name: str, x: Column, y: Column) -> Column:
    """Distances between two text features, cheap and without Python."""
    words = feature_words
    union = F.size(F.array_union(words(x), words(y)))
    return {
        "equal": F.when(x.eqNullSafe(y), 0.0).otherwise(1.0),
        "gap": F.abs(F.try_to_number(x, F.lit("999999999")).cast("double") - F.try_to_number(y, F.lit("999999999")).cast("double")),
        "jaccard": F.when(union == 0, 0.0).otherwise(1.0 - F.size(F.array_intersect(words(x), words(y))) / union),
        "edit": F.levenshtein(x, y).cast("double"),
        "missing_word": F.size(F.array_except(words(y), words(x))).cast("double"),
    }[name]


def literal_holds(lit: Literal) -> Column:
    return F.coalesce(feature_distance(lit.distance, F.col(f"a_{lit.feature}"), F.col(f"b_{lit.feature}")) <= lit.theta, F.lit(False))


def cnf_holds(clauses: list[list[Literal]]) -> Column:
    out = F.lit(True)
    for clause in clauses:
        any_of = F.lit(False)
        for lit in clause:
            any_of = any_of | literal_holds(lit)
        out = out & any_of
    return out


def recall_bound(hits: int, n: int, delta: float) -> float:
    """Lower confidence bound (Hoeffding) of recall from hits among n sampled true pairs."""
    return hits / n - math.sqrt(math.log(1 / delta) / (2 * n)) if n else 0.0


def fit_cnf(sample: list[dict], literals: list[Literal], recall_target: float = 0.9, delta: float = 0.05, max_or: int = 2) -> tuple[list[list[Literal]], float]:
    """(clauses, certified recall bound): greedy clauses that prune the most sampled pairs while the bound on
    the held-out half of the true pairs stays at the target. sample rows: {literal: bool, ..., "match": bool}.

    Candidates are fitted on even rows and certified on odd ones; delta is split over the clauses tried, and a
    clause that fails certification is left out. No useful clause leaves the list empty.
    """
    fit, held = sample[::2], sample[1::2]
    candidates = [list(c) for r in range(1, max_or + 1) for c in itertools.combinations(literals, r)]
    chosen: list[list[Literal]] = []
    alive = list(fit)
    bound = 1.0
    holds = lambda row, clause: any(row[x] for x in clause)
    for _ in range(20):
        if len(chosen) == 3:
            break
        truth = [r for r in alive if r["match"]]
        scored = []
        for c in candidates:
            kept_true = sum(holds(r, c) for r in truth)
            pruned = sum(not holds(r, c) for r in alive)
            if truth and kept_true >= recall_target * len(truth) and pruned > 0:
                scored.append((-pruned, len(c), str(c), c))
        if not scored:
            break
        clause = min(scored, key=lambda x: x[:3])[3]
        trial = [*chosen, clause]
        true_held = [r for r in held if r["match"]]
        low = recall_bound(sum(all(holds(r, k) for k in trial) for r in true_held), len(true_held), delta / max(1, len(candidates)))
        if low < recall_target:
            candidates.remove(clause)
            continue
        chosen, bound = trial, low
        alive = [r for r in alive if holds(r, clause)]
    return chosen, bound if chosen else 1.0


def _single(rows: DataFrame, stage: str) -> DataFrame:
    """A prompt for each pair (a_id, b_id, a_text, b_text)."""
    one = lambda x: F.array(F.struct(F.col(f"{x}_id").alias("id"), F.col(f"{x}_text").alias("text"))).alias(x)
    none = F.lit(None).cast("int")
    return rows.select(F.concat_ws(":", F.lit(stage), "a_id", "b_id").alias("call_id"), none.alias("ca"), none.alias("cb"), one("a"), one("b"))


def drawn_pairs(fa: DataFrame, fb: DataFrame, size: int, seed: int = 7) -> DataFrame:
    """`size` pairs of drawn rows, lowest by md5: a square of rows of both sides, longer on one where the other is short.
    Only drawn rows are paired."""
    take = lambda x, key, n: x.orderBy(order_key(seed, key), key).limit(n)
    side = math.ceil(math.sqrt(size))
    n_b = max(1, take(fb, "b_id", side).count())
    left = take(fa, "a_id", math.ceil(size / n_b))
    right = take(fb, "b_id", math.ceil(size / max(1, left.count())))
    return left.crossJoin(F.broadcast(right)).orderBy(order_key(seed, "a_id", "b_id"), "a_id", "b_id").limit(size)


def _word_candidates(fa: DataFrame, fb: DataFrame, lit: Literal) -> DataFrame:
    """(a_id, b_id), among them all pairs whose word sets hold `lit` (missing_word, or jaccard below 1): pairs meet on
    the rarest words of a row, so many that one of them must be shared. Rows of B that may miss all their words meet
    every row of A, as all of those pairs hold."""
    sets = [f.select(F.col(f"{s}_id").alias("id"), feature_words(F.col(f"{s}_{lit.feature}")).alias("w")).where("w is not null") for f, s in ((fa, "a"), (fb, "b"))]
    if lit.distance == "jaccard":
        sets = [x.withColumn("w", F.when(F.size("w") == 0, F.array(F.lit(""))).otherwise(F.col("w"))) for x in sets]
    each = [x.select("id", F.explode("w").alias("word")) for x in sets]
    known = each[0].unionByName(each[1]).groupBy("word").agg(F.count(F.lit(1)).alias("n"))
    size = F.size("w")
    need = F.lit(int(lit.theta) + 1) if lit.distance == "missing_word" else size - F.ceil(size * (1 - lit.theta) - 1e-9) + 1

    def rarest(rows: DataFrame) -> DataFrame:
        ranked = rows.join(known, "word").groupBy("id").agg(F.array_sort(F.collect_list(F.struct("n", "word"))).alias("w"))
        return ranked.select("id", F.explode(F.slice("w", 1, need.cast("int"))).alias("x")).select("id", "x.word")

    left = each[0] if lit.distance == "missing_word" else rarest(each[0])
    met = left.select(F.col("id").alias("a_id"), "word").join(rarest(each[1]).select(F.col("id").alias("b_id"), "word"), "word").select("a_id", "b_id")
    if lit.distance == "missing_word":
        few = sets[1].where(F.size("w") <= lit.theta).select(F.col("id").alias("b_id"))
        met = met.unionByName(sets[0].select(F.col("id").alias("a_id")).crossJoin(few))
    return met.distinct()


def cnf_candidates(fa: DataFrame, fb: DataFrame, clauses: list[list[Literal]]) -> DataFrame:
    """Pairs that satisfy the clauses: a hash join on clauses of one equality, or else on shared rare words for a
    clause of one word distance; a nested loop where there is neither. Ids are unique on each side."""
    single = [c[0] for c in clauses if len(c) == 1]
    keys = [x.feature for x in single if x.distance == "equal" and x.theta < 1]
    by_words = [x for x in single if x.distance == "missing_word" or (x.distance == "jaccard" and x.theta < 1)]
    if not keys and by_words:
        return _word_candidates(fa, fb, by_words[0]).join(fa, "a_id").join(fb, "b_id").where(cnf_holds(clauses))
    if not keys:
        return fa.crossJoin(fb).where(cnf_holds(clauses))
    on = F.lit(True)
    for k in keys:
        on = on & F.col(f"a_{k}").eqNullSafe(F.col(f"b_{k}"))
    return fa.join(fb, on).where(cnf_holds(clauses))


def feature_cnf_join(a: DataFrame, b: DataFrame, literals: list[Literal], predicate: str, model: LanguageModel, sample_size: int = 600, recall_target: float = 0.9, delta: float = 0.05, seed: int = 7, precision_target: float | None = None) -> dict:
    """a and b: (id, text, feature columns). Learns clauses from a labelled sample of pairs, prunes with them
    and verifies what is left pair by pair; without a useful clause all pairs are verified. With a precision_target,
    survivors are taken without being verified if a lower bound of their precision on the held-out half of the sample
    reaches it."""
    fa = a.select(F.col("id").alias("a_id"), F.col("text").alias("a_text"), *[F.col(c).alias(f"a_{c}") for c in a.columns if c not in ("id", "text")])
    fb = b.select(F.col("id").alias("b_id"), F.col("text").alias("b_text"), *[F.col(c).alias(f"b_{c}") for c in b.columns if c not in ("id", "text")])
    drawn = drawn_pairs(fa, fb, sample_size, seed)
    drawn = drawn.select("a_id", "b_id", "a_text", "b_text", *[literal_holds(x).alias(f"l{i}") for i, x in enumerate(literals)])
    labelled = run_prompts(_single(drawn, "feature"), "match", predicate, model, "feature")
    truth = {(r["a_id"], r["b_id"]) for r in pairs_of(labelled).collect()}
    sample = [{**{x: r[f"l{i}"] for i, x in enumerate(literals)}, "match": (r["a_id"], r["b_id"]) in truth} for r in drawn.orderBy(order_key(seed, "a_id", "b_id")).collect()]
    clauses, bound = fit_cnf(sample, literals, recall_target, delta)
    survivors = cnf_candidates(fa, fb, clauses)
    passed = [r["match"] for r in sample[1::2] if all(any(r[x] for x in c) for c in clauses)]
    precision = recall_bound(sum(passed), len(passed), delta)
    out = {"clauses": clauses, "bound": bound, "precision_bound": precision, "survivors": survivors.select("a_id", "b_id")}
    if precision_target is not None and clauses and precision >= precision_target:
        return {**out, "matches": survivors.select("a_id", "b_id"), "calls": calls_of(labelled)}
    answers = run_prompts(_single(survivors, "verify"), "match", predicate, model, "verify")
    return {**out, "matches": pairs_of(answers), "calls": calls_of(labelled).unionByName(calls_of(answers))}


def propose_features(a: DataFrame, b: DataFrame, predicate: str, model: LanguageModel, sample: int = 10, seed: int = 7) -> tuple[list[str], tuple]:
    """Names of features that the model proposes from samples of both sides, and the log line of that call."""
    text = lambda x: tuple(r["text"] for r in bottom_n(x, sample, seed).select("text").collect())
    left, right = text(a), text(b)
    reply = model.complete(Prompt("propose", predicate, left, right))
    names = [x for x in parse_list(reply.text) if x != UNKNOWN and re.fullmatch(r"\w+", x) and x not in ("id", "text")]
    return names, ("propose", 1, model.name, len(left), len(right), reply.in_tok, reply.out_tok, "ok" if names else "malformed", "propose")


def extract_features(rows: DataFrame, names: list[str], predicate: str, model: LanguageModel, batch: int = 25, side: str = "a") -> tuple[DataFrame, list[DataFrame]]:
    """rows (id, text) with a text column for each feature, asked in batches, and the call logs."""
    out, logs = rows, []
    for name in names:
        answers = run_prompts(row_prompts(rows, batch, f"extract-{side}-{name}"), "feature", predicate, model, "extract", (name,))
        out = out.join(answers.where("row = 'answer'").select(F.col("a_id").alias("id"), F.col("answer").alias(name)), "id", "left")
        logs.append(calls_of(answers))
    return out, logs


def model_feature_cnf_join(a: DataFrame, b: DataFrame, predicate: str, model: LanguageModel, batch: int = 25, **params) -> dict:
    """The feature baseline from end to end: the model proposes features and extracts each from every row, distances
    of them become clauses, and the model verifies what they leave (see feature_cnf_join)."""
    names, line = propose_features(a, b, predicate, model)
    fa, logs_a = extract_features(a, names, predicate, model, batch, "a")
    fb, logs_b = extract_features(b, names, predicate, model, batch, "b")
    literals = [Literal(n, d, t) for n in names for d, t in (("equal", 0.0), ("missing_word", 0.0), ("jaccard", 0.7), ("edit", 3.0))]
    out = feature_cnf_join(fa, fb, literals, predicate, model, **params)
    for log in [a.sparkSession.createDataFrame([line], CALLS), *logs_a, *logs_b]:
        out["calls"] = out["calls"].unionByName(log.select(*out["calls"].columns))
    return out | {"features": names}


def similarity_topk(points: DataFrame, queries: DataFrame, k: int = 3) -> DataFrame:
    """(q_id, id, dot, rank): the k points (id, v) with the largest inner product for each query (q_id, q),
    exact in integers. Queries are a stated, bounded set and are broadcast against all points; each task keeps
    k for a query before the shuffle."""
    from pyspark.sql import Window

    dot = F.aggregate(F.zip_with("v", "q", lambda x, y: x * y), F.lit(0).cast("long"), lambda s, x: s + x)
    scored = points.crossJoin(F.broadcast(queries)).where("id <> q_id").select("q_id", "id", dot.alias("dot"))
    w = Window.partitionBy("q_id").orderBy(F.desc("dot"), "id")
    return scored.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def similar_pairs(a: DataFrame, b: DataFrame, encoder: str, num: int, den: int) -> DataFrame:
    """(a_id, b_id) whose cosine is at least num/den > 0, decided in integers: dot^2 * den^2 >= num^2 * |a|^2 * |b|^2.

    A hash join on shared places, without loss: places are ordered from rare to common, and of each vector only
    those are keys from which on the rest still has num/den of its length. By the Cauchy-Schwarz inequality the first common place
    of a similar pair is a key of both, and the pair is made at that place alone. Vectors of zeros are like nothing."""
    unit = lambda x, i, v: x.select(F.col("id").alias(i), ENCODERS[encoder](F.coalesce(F.col("embed_text"), F.col("text")) if "embed_text" in x.columns else F.col("text")).alias(v))
    total = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0).cast("long"), lambda s, p: s + p)
    left = unit(a, "a_id", "va").withColumn("na", total("va", "va"))
    right = unit(b, "b_id", "vb").withColumn("nb", total("vb", "vb"))
    counted = left.select(F.explode(_places(F.col("va"))).alias("place")).unionByName(right.select(F.explode(_places(F.col("vb"))).alias("place"))).groupBy("place").count()
    order = [r["place"] for r in sorted(counted.collect(), key=lambda r: (r["count"], r["place"]))]  # one a dimension of the encoder
    if not order:
        return left.select("a_id").crossJoin(right.select("b_id")).limit(0)
    by_rarity = F.array(*[F.lit(x) for x in order])

    def keyed(x: DataFrame, v: str, n: str) -> DataFrame:
        ranked = x.withColumn(v, F.transform(by_rarity, lambda p: F.get(F.col(v), p)))
        rest = lambda i: F.aggregate(F.slice(v, i + 1, F.lit(len(order))), F.lit(0).cast("long"), lambda s, p: s + p * p)
        return ranked.withColumn("key", F.explode(F.filter(_places(F.col(v)), lambda i: rest(i) * den * den >= num * num * F.col(n))))

    joined = keyed(left, "va", "na").join(keyed(right, "vb", "nb"), "key")
    first = F.array_min(F.array_intersect(_places(F.col("va")), _places(F.col("vb"))))
    dot = total("va", "vb")
    return joined.where((F.col("key") == first) & (dot > 0) & (dot * dot * den * den >= num * num * F.col("na") * F.col("nb"))).select("a_id", "b_id")


def _places(v: Column) -> Column:
    return F.filter(F.transform(v, lambda x, i: F.when(x != 0, i)), lambda x: x.isNotNull())


def containment_join(docs: DataFrame, passages: DataFrame, broadcast_bytes: int = 64 << 20) -> DataFrame:
    """(a_id, b_id) of texts (a_id, text) that hold a passage (b_id, passage), exactly.

    Inner words of a passage stand between blanks in any text that holds it, so a run of three of them is
    a key: hash join on the run with the least hash, then the whole passage is looked for. Passages of fewer than five words have no
    such run and are compared with every text. Null passages and texts are in no pair; an empty passage is in every text."""

    def runs(text: str):
        # The outer array binds the words to a variable, so a text is split once, not once a run.
        hashes = lambda w: F.transform(F.sequence(F.lit(2), F.size(w) - 3), lambda i: F.xxhash64(F.get(w, i - 1), F.get(w, i), F.get(w, i + 1)))
        return F.transform(F.array(F.split(text, " ")), lambda w: F.when(F.size(w) >= 5, hashes(w)))[0]

    items = passages.select("b_id", "passage", F.array_min(runs("passage")).alias("key")).where(F.col("passage").isNotNull())
    long, short = items.where(F.col("key").isNotNull()), items.where(F.col("key").isNull()).select("b_id", "passage")
    texts = docs.select("a_id", "text").where(F.col("text").isNotNull())
    seen = texts.select("a_id", "text", F.explode(F.array_distinct(runs("text"))).alias("key"))
    few = (long.agg(F.sum(F.octet_length("passage") + 16)).first()[0] or 0) <= broadcast_bytes
    found = seen.join(F.broadcast(long), "key") if few else texts.join(seen.select("a_id", "key").join(long.select("b_id", "key"), "key").select("a_id", "b_id"), "a_id").join(long.select("b_id", "passage"), "b_id")
    out = found.where(F.contains("text", "passage")).select("a_id", "b_id")
    return out.unionByName(texts.join(short, F.contains("text", "passage")).select("a_id", "b_id"))


def project_filter_join(a: DataFrame, b: DataFrame, predicate: str, model: LanguageModel, options, num: int = 1, den: int = 2, encoder: str = "hash-word-64") -> dict[str, DataFrame]:
    """Project A, keep pairs by cosine of the projections, verify those with the model."""
    from semjoin.operators.cluster_join import project

    projected, calls = project(a, b, predicate, model, options)
    near = similar_pairs(projected, b, encoder, num, den)
    rows = near.join(a.select(F.col("id").alias("a_id"), F.col("text").alias("ta")), "a_id").join(b.select(F.col("id").alias("b_id"), F.col("text").alias("tb")), "b_id")
    answers = run_prompts(_single(rows.withColumnsRenamed({"ta": "a_text", "tb": "b_text"}), "verify"), "match", predicate, model, "verify")
    return {"matches": pairs_of(answers), "calls": calls.unionByName(calls_of(answers)), "survivors": near}
