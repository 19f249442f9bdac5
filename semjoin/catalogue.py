"""Named queries and their SQL twins: methods and measures here, relational and streaming ones in their modules."""

from __future__ import annotations

import functools
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from semjoin.functions import measures as M
from semjoin.functions import text as T
from semjoin.models import INSULTS, STOP_WORDS, UNKNOWN, NoisyModel, RulebookModel, ScriptedModel
from semjoin.operators import baselines, classifier, clustering, relational
from semjoin.operators import cluster_join as cj
from semjoin.plans import tuning
from semjoin.plans.advisor import CHOICES, SAMPLE_SEED, Advisor, JoinOptions, labels_are_valid, resolve
from semjoin.plans.api import limit_per_a, sem_extract, sem_filter, semantic_join
from semjoin.plans.sqlapi import register_classify, register_partners
from semjoin.plans.sqlapi import sql as semantic_sql
from semjoin.sources.tables import CALLS, keep, load
from semjoin.streaming import windows
from semjoin.workloads import SPECS, TAGS, register, truth_sql, workload

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
SEED = 7


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        if sql is not None:
            ORACLES[name or f.__name__] = sql
        return f

    return add


def values(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def values_sql(rows: list[tuple], names: str) -> str:
    one = lambda x: "NULL" if x is None else f"'{x}'" if isinstance(x, str) else str(x)
    return f"SELECT * FROM (VALUES {', '.join('(' + ', '.join(map(one, r)) + ')' for r in rows)}) t({names})"


# Rules as SQL.


def in_list(words: list[str]) -> str:
    return ", ".join(f"'{w}'" for w in words)


def quality_sql(t: str) -> str:
    return f"CASE WHEN contains({t}, '!!') OR contains({t}, ' | ') OR length({t}) < 100 OR regexp_matches({t}, '[%#*]{{3}}') THEN 'low' ELSE 'high' END"


def toxic_sql(t: str) -> str:
    return f"CASE WHEN regexp_matches(lower({t}), '{'|'.join(INSULTS)}') THEN 'abusive' ELSE 'civil' END"


def language_sql(src: str) -> str:
    """(id, label) of a source (id, text)."""
    votes = ", ".join(f"len(list_filter(w, lambda x: x IN ({in_list(v)}))) AS {k}" for k, v in STOP_WORDS.items())
    return f"SELECT id, CASE WHEN greatest(en, fr, de, es) = 0 THEN '{UNKNOWN}' WHEN en >= greatest(fr, de, es) THEN 'en' WHEN fr >= greatest(de, es) THEN 'fr' WHEN de >= es THEN 'de' ELSE 'es' END AS label FROM (SELECT id, {votes} FROM (SELECT id, regexp_split_to_array(lower(text), '[^\\p{{L}}\\p{{N}}]+') AS w FROM ({src}) s) x) y"


def embed_sql(src: str) -> str:
    cut = "array_to_string(list_transform(string_split(text, '|'), lambda f: substr(f, 1, 400)), '|')"
    words = f"list_filter(regexp_split_to_array(lower({cut}), '[^\\p{{L}}\\p{{N}}]+'), lambda x: x <> '')"
    buckets = f"list_transform({words}, lambda x: ('0x' || substr(md5(x), 1, 8))::UBIGINT % 64)"
    return f"SELECT id, list_transform(range(64), lambda i: CAST(len(list_filter(k, lambda y: y = i)) AS BIGINT)) AS v FROM (SELECT id, {buckets} AS k FROM ({src}) s) x"


def kmeans_ctes(src: str, k: str, rounds: int, tag: str) -> str:
    """CTEs that end in {tag}_out (id, cluster); k is an SQL expression."""
    out = [f"{tag}_p AS MATERIALIZED ({src})", f"{tag}_c0 AS MATERIALIZED (SELECT i, v FROM (SELECT row_number() OVER (ORDER BY md5(concat('{SEED}:', id)), id) - 1 AS i, v FROM {tag}_p) x WHERE i < {k})"]
    dist = "list_sum(list_transform(range(1, 65), lambda j: (p.v[j] - c.v[j]) * (p.v[j] - c.v[j])))"
    for r in range(rounds + 1):
        out.append(f"{tag}_n{r} AS MATERIALIZED (SELECT p.id, any_value(p.v) AS v, arg_min(c.i, CAST({dist} AS HUGEINT) * 1000 + c.i) AS cluster FROM {tag}_p p, {tag}_c{r} c GROUP BY p.id)")
        mean = f"SELECT cluster, list(x ORDER BY j) AS v FROM (SELECT cluster, j, CAST(sum(v[j]) AS BIGINT) // count(*) AS x FROM {tag}_n{r}, range(1, 65) t(j) GROUP BY cluster, j) y GROUP BY cluster"
        out.append(f"{tag}_c{r + 1} AS MATERIALIZED (SELECT c.i, coalesce(m.v, c.v) AS v FROM {tag}_c{r} c LEFT JOIN ({mean}) m ON m.cluster = c.i)")
    out.pop()
    out.append(f"{tag}_out AS (SELECT id, cluster FROM {tag}_n{rounds})")
    return ", ".join(out)


def sides_sql(name: str, ratio: float = 0.05, rounds: int = 5) -> str:
    """CTEs sa and sb (id, text, cluster ...) of a workload clustered as the engine does."""
    s = SPECS[name]
    k = lambda x: f"greatest(2, CAST(floor((SELECT count(*) FROM {x}0) * {ratio} + 1e-9) AS BIGINT))"
    parts = [f"a0 AS MATERIALIZED ({s['a']}), b0 AS MATERIALIZED ({s['b']})", kmeans_ctes(embed_sql("SELECT id, text FROM a0"), k("a"), rounds, "ka"), kmeans_ctes(embed_sql("SELECT id, text FROM b0"), k("b"), rounds, "kb")]
    parts += ["sa AS MATERIALIZED (SELECT x.*, y.cluster FROM a0 x JOIN ka_out y ON x.id = y.id), sb AS MATERIALIZED (SELECT x.*, y.cluster FROM b0 x JOIN kb_out y ON x.id = y.id)"]
    return "WITH " + ", ".join(parts)


def profiled_sql(name: str, s: int = 5, least: int = 6, on: str | None = None) -> str:
    """sides_sql and a CTE pp (ca, cb, na, nb, bypassed, sa, sb, n_match, n_cmp). on: what the model says, if not the truth."""
    on = on or SPECS[name]["on"]
    pool = lambda side, c: f"SELECT * FROM (SELECT q.*, row_number() OVER (PARTITION BY ca, cb ORDER BY md5(concat('{SEED}:', ca, ':', cb, ':', id)), id) AS rk FROM (SELECT p.ca, p.cb, t.* FROM pl p JOIN (SELECT *, row_number() OVER (PARTITION BY cluster ORDER BY md5(concat('{SEED}:', id)), id) AS rn FROM {side}) t ON t.cluster = p.{c} AND t.rn <= {4 * s} WHERE NOT p.bypassed) q) z WHERE rk <= {s}"
    return sides_sql(name) + (
        f", pl AS MATERIALIZED (SELECT ca, na, cb, nb, least(na, nb) < {least} AS bypassed FROM (SELECT cluster AS ca, count(*) AS na FROM sa GROUP BY 1) x, (SELECT cluster AS cb, count(*) AS nb FROM sb GROUP BY 1) y)"
        f", da AS MATERIALIZED ({pool('sa', 'ca')}), db AS MATERIALIZED ({pool('sb', 'cb')})"
        f", hit AS (SELECT a.ca, a.cb, count(*) AS n FROM da a JOIN db b ON a.ca = b.ca AND a.cb = b.cb AND {on} GROUP BY 1, 2)"
        ", la AS (SELECT ca, cb, count(*) AS n FROM da GROUP BY 1, 2), lb AS (SELECT ca, cb, count(*) AS n FROM db GROUP BY 1, 2)"
        ", pp AS MATERIALIZED (SELECT pl.*, coalesce(la.n, 0) AS sa, coalesce(lb.n, 0) AS sb, coalesce(hit.n, 0) AS n_match, coalesce(la.n * lb.n, 0) AS n_cmp FROM pl LEFT JOIN la USING (ca, cb) LEFT JOIN lb USING (ca, cb) LEFT JOIN hit USING (ca, cb))"
    )


def kept_sql(t: int) -> str:
    return f"(bypassed OR NOT (100 * n_match < {t} * n_cmp))"


def model_of(w) -> RulebookModel:
    return RulebookModel(w.rule)


# Advisor.


def _decisions(name: str, **options) -> Callable:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        w = workload(spark, sf_dir, name)
        r = semantic_join(w.a, w.b, w.predicate, model_of(w), JoinOptions(**options))
        return r.decision_table().where("field <> 'labels'").select("field", "value", "source")

    return run


query(values_sql([("strategy", "label", "advisor")], "field, value, source"), "advisor_decisions_w1")(_decisions("w1"))
query(values_sql([("strategy", "cluster", "advisor"), ("embedding", "all-mpnet-base-v2", "advisor"), ("projection", "off", "advisor"), ("clustering", "kmeans", "advisor")], "field, value, source"), "advisor_decisions_w2")(_decisions("w2"))
query(values_sql([("strategy", "label", "advisor")], "field, value, source"), "advisor_decisions_w3")(_decisions("w3", label_table=True))
query(values_sql([("strategy", "cluster", "override"), ("embedding", "hash-word-64", "override"), ("projection", "off", "override"), ("clustering", "kmeans", "override")], "field, value, source"), "advisor_override")(_decisions("w3", force_strategy="cluster", embedding="hash-word-64", projection="off", clustering="kmeans"))

def _choice_sql(field: str) -> str:
    """(value, source) of the raw reply `text` in SQL: the one allowed name that it holds as a whole token, or the default."""
    held = ", ".join(f"CASE WHEN regexp_matches(lower(text), '(^|[^\\p{{L}}\\p{{N}}_-]){x.lower()}($|[^\\p{{L}}\\p{{N}}_-])') THEN '{x}' END" for x in CHOICES[field])
    return f"SELECT '{field}' AS field, CASE WHEN len(x) = 1 THEN x[1] ELSE '{CHOICES[field][0]}' END AS value, CASE WHEN len(x) = 1 THEN 'advisor' ELSE 'fallback' END AS source FROM (SELECT list_filter([{held}], lambda y: y IS NOT NULL) AS x FROM conversations) t"


@query("SELECT field, value, source, count(*) AS n FROM (" + " UNION ALL ".join(_choice_sql(f) for f in CHOICES) + ") r GROUP BY 1, 2, 3")
def advisor_fallbacks(spark, sf_dir):
    """Each turn of the conversations taken as the raw reply to each question of the advisor: what is decided, and why."""
    turns = load(spark, sf_dir, "conversations")

    def decide(texts: pd.Series, fields: pd.Series) -> pd.DataFrame:
        got = [resolve(f, t) for f, t in zip(fields, texts.fillna(""), strict=True)]
        return pd.DataFrame({"value": [d.value for d in got], "source": [d.source for d in got]})

    asked = turns.select("text", F.explode(F.array(*map(F.lit, CHOICES))).alias("field"))
    said = asked.select("field", F.pandas_udf(decide, "value string, source string")("text", "field").alias("d"))
    return said.groupBy("field", "d.value", "d.source").agg(F.count(F.lit(1)).alias("n"))


_GUARDED = {"lang": "lang", "one class": "'a'", "row": "CAST(doc_id AS VARCHAR(20))", "mostly unknown": f"CASE WHEN doc_id % 5 = 0 THEN lang ELSE '{UNKNOWN}' END"}


@query(" UNION ALL ".join(f"SELECT '{n}' AS reason, count(DISTINCT CASE WHEN x <> '{UNKNOWN}' THEN x END) BETWEEN 2 AND least(20, greatest(3, count(*)) - 1) AND 2 * count(CASE WHEN x = '{UNKNOWN}' THEN 1 END) <= count(*) AS valid FROM (SELECT {x} AS x FROM documents) d" for n, x in _GUARDED.items()))
def label_guard(spark, sf_dir):
    """Whether columns of documents would do as labels of a label join."""
    docs, out = load(spark, sf_dir, "documents"), []
    for name, x in _GUARDED.items():
        column = docs.selectExpr(f"{x} AS x")
        rows, unknown = column.agg(F.count(F.lit(1)), F.count_if(F.col("x") == UNKNOWN)).first()
        # One class over the most that are allowed tells as much as all of them.
        classes = [r["x"] for r in column.where(F.col("x") != UNKNOWN).distinct().limit(21).collect()]
        out.append((name, labels_are_valid(classes, rows, unknown / max(1, rows))))
    return values(spark, out, "reason string, valid boolean")


# Serialization.

_PART_COLS = ["p_partkey", "p_name", "p_brand", "p_type", "p_size"]


@query("SELECT p_partkey AS id, concat_ws('|', " + ", ".join(f"substr(coalesce(CAST({c} AS VARCHAR), ''), 1, 400)" for c in _PART_COLS) + ") AS s FROM part")
def serialize_part(spark, sf_dir):
    part = load(spark, sf_dir, "part")
    return part.select(F.col("p_partkey").alias("id"), T.serialize(part, _PART_COLS).alias("s"))


@query("SELECT doc_id AS id, length(concat_ws('|', substr(text, 1, 400), lang, source)) AS n, md5(concat_ws('|', substr(text, 1, 400), lang, source)) AS h FROM documents")
def serialize_documents_capped(spark, sf_dir):
    docs = load(spark, sf_dir, "documents")
    s = T.serialize(docs, ["text", "lang", "source"])
    return docs.select(F.col("doc_id").alias("id"), F.length(s).alias("n"), F.md5(s).alias("h"))


@query("SELECT doc_id AS id, concat_ws('|', coalesce(nullif(lang, 'en'), ''), source, coalesce(nullif(source, 'src1'), '')) AS s FROM documents")
def serialize_nulls(spark, sf_dir):
    docs = load(spark, sf_dir, "documents").select("doc_id", F.nullif("lang", F.lit("en")).alias("l"), "source", F.nullif("source", F.lit("src1")).alias("x"))
    return docs.select(F.col("doc_id").alias("id"), T.serialize(docs, ["l", "source", "x"]).alias("s"))


# Label join.

def _label_pairs(name: str, **options):
    def run(spark, sf_dir):
        w = workload(spark, sf_dir, name)
        return semantic_join(w.a, w.b, w.predicate, model_of(w), JoinOptions(force_strategy="label", **options)).pairs

    return run


_W1 = SPECS["w1"]
query(f"SELECT a.id AS a_id, b.id AS b_id FROM ({_W1['a']}) a JOIN ({_W1['b']}) b ON {quality_sql('a.text')} = {quality_sql('b.text')}", "label_join_reviews")(_label_pairs("w1", labels=("low", "high")))
_W1B = SPECS["w1b"]
query(f"SELECT a.id AS a_id, b.id AS b_id FROM ({_W1B['a']}) a JOIN ({_W1B['b']}) b ON {toxic_sql('a.text')} = {toxic_sql('b.text')}", "label_join_toxic")(_label_pairs("w1b", labels=("abusive", "civil"), dedupe_text=True))
_LANG_A, _LANG_B = (language_sql(SPECS["w1c"][x]) for x in "ab")
query(f"SELECT a.id AS a_id, b.id AS b_id FROM ({_LANG_A}) a JOIN ({_LANG_B}) b ON a.label = b.label WHERE a.label <> '{UNKNOWN}'", "label_join_language")(_label_pairs("w1c", labels=tuple(STOP_WORDS)))
_TAG_LABEL = f"SELECT a.id AS id, min(b.text) AS label FROM ({SPECS['w3']['a']}) a JOIN ({SPECS['w3']['b']}) b ON {SPECS['w3']['on']} GROUP BY a.id"
query(f"SELECT a.id AS a_id, b.id AS b_id FROM ({_TAG_LABEL}) a JOIN ({SPECS['w3']['b']}) b ON a.label = b.text", "label_join_tags")(_label_pairs("w3", label_table=True))
query(truth_sql("w2b"), "label_join_w2_vacuous")(_label_pairs("w2", labels=tuple(f"person {i}" for i in range(9))))


@query(f"SELECT coalesce(l.label, '{UNKNOWN}') AS label, count(*) AS n FROM ({SPECS['w3']['a']}) a LEFT JOIN (SELECT * FROM ({_TAG_LABEL}) t WHERE label IN ('bolt', 'gear')) l ON l.id = a.id GROUP BY 1")
def label_join_unknown_dropped(spark, sf_dir):
    w = workload(spark, sf_dir, "w3")
    got, _ = classifier.classify(w.a, ["bolt", "gear", UNKNOWN], w.predicate, model_of(w))
    wide, _ = classifier.classify(w.a, [*sorted(TAGS), UNKNOWN], w.predicate, model_of(w))
    listed = wide.select("id", classifier.keep_listed(F.col("label"), ["bolt", "gear"]).alias("label"))
    return listed.join(got.select("id"), "id").groupBy("label").agg(F.count(F.lit(1)).alias("n"))


@query(truth_sql("w3"))
def label_join_multi(spark, sf_dir):
    w = workload(spark, sf_dir, "w3")
    labels = F.array(*[F.when(F.contains(F.concat(F.lit(" "), "text", F.lit(" ")), F.lit(f" {t} ")), F.lit(t)) for t in TAGS])
    a = w.a.select("id", F.filter(labels, lambda x: x.isNotNull()).alias("labels"))
    return classifier.multi_label_join(a, w.b.select("id", F.array("text").alias("labels")))


@query(f"SELECT a.label, a.n AS n_a, b.n AS n_b, a.n * b.n AS n_pairs FROM (SELECT label, count(*) AS n FROM ({_LANG_A}) x GROUP BY 1) a JOIN (SELECT label, count(*) AS n FROM ({_LANG_B}) x GROUP BY 1) b USING (label) WHERE label <> '{UNKNOWN}'")
def label_groups_count(spark, sf_dir):
    w = workload(spark, sf_dir, "w1c")
    return semantic_join(w.a, w.b, w.predicate, model_of(w), JoinOptions(force_strategy="label", labels=tuple(STOP_WORDS))).groups()


def _groups_all(name: str, rule: str, a: str, b: str, label, **options) -> None:
    """The label join of whole tables, as groups. a and b: SQL of (id, text); label: their (id, label) in SQL."""
    count = lambda src: f"SELECT label, count(*) AS n FROM ({src}) x GROUP BY 1"

    def run(spark, sf_dir):
        register(spark, sf_dir, a, b)
        sides = [spark.sql(x).selectExpr("CAST(id AS BIGINT) AS id", "text") for x in (a, b)]
        return semantic_join(*sides, SPECS[name]["predicate"], RulebookModel(rule), JoinOptions(force_strategy="label", buckets=64, **options)).groups()

    query(f"SELECT a.label AS label, a.n AS n_a, b.n AS n_b, a.n * b.n AS n_pairs FROM ({count(label[0])}) a JOIN ({count(label[1])}) b USING (label) WHERE label <> '{UNKNOWN}'", f"label_groups_{rule}_all")(run)


_HALF = "SELECT doc_id AS id, text FROM documents WHERE doc_id % 2 = {}"
_PARTS_ALL = "SELECT p_partkey AS id, concat(p_name, ' ', p_brand) AS text FROM part"
_HALVES = _HALF.format(0), _HALF.format(1)
_groups_all("w1c", "language", *_HALVES, [language_sql(x) for x in _HALVES], labels=tuple(STOP_WORDS))
_groups_all("w1", "quality", *_HALVES, [f"SELECT id, {quality_sql('text')} AS label FROM ({x}) h" for x in _HALVES], labels=("low", "high"))
_groups_all("w1b", "toxic", *_HALVES, [f"SELECT id, {toxic_sql('text')} AS label FROM ({x}) h" for x in _HALVES], labels=("abusive", "civil"))
_groups_all("w3", "tag", _PARTS_ALL, SPECS["w3"]["b"], [f"SELECT a.id AS id, min(b.text) AS label FROM ({_PARTS_ALL}) a JOIN ({SPECS['w3']['b']}) b ON {SPECS['w3']['on']} GROUP BY a.id", f"SELECT id, text AS label FROM ({SPECS['w3']['b']}) t"], label_table=True)

_PAGES = "SELECT page_id AS id, html AS text FROM pages"
_PAGE_LANG = f"SELECT id, CASE WHEN l IN ({in_list(list(STOP_WORDS))}) THEN l ELSE '{UNKNOWN}' END AS label FROM (SELECT page_id AS id, regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) AS l FROM pages) p"
_VECTORS_BY_LABEL = [f"SELECT vec_id AS id, CAST(label AS VARCHAR(20)) AS text FROM embeddings WHERE vec_id % 2 = {x}" for x in (0, 1)]
_groups_all("w8", "equal", *_VECTORS_BY_LABEL, [f"SELECT id, text AS label FROM ({x}) v" for x in _VECTORS_BY_LABEL], labels=tuple(map(str, range(10))))
_groups_all("w10", "page_language", _PAGES, _PAGES, [_PAGE_LANG, _PAGE_LANG], labels=tuple(STOP_WORDS))


def _segment(salt: int):
    def run(spark, sf_dir):
        c = load(spark, sf_dir, "customer").select(F.col("c_custkey").alias("id"), F.col("c_mktsegment").alias("label"))
        return classifier.label_join_totals(c.where("id % 2 = 0"), c.where("id % 2 = 1"), F.col("id") % 97, F.col("id") % 89, salt)

    return run


_SEG = "SELECT a.text AS label, count(*) AS n, CAST(sum(a.id % 97 + b.id % 89) AS BIGINT) AS s FROM ({}) a JOIN ({}) b ON a.text = b.text GROUP BY 1".format(SPECS["w9"]["a"], SPECS["w9"]["b"])
query(_SEG, "label_join_segment")(_segment(1))
query(_SEG, "label_join_segment_salted")(_segment(8))


@query(f"SELECT label, count(*) AS n FROM (SELECT o_orderkey AS id, o_orderpriority AS label FROM orders) o GROUP BY 1")
def label_sizes_priority(spark, sf_dir):
    return load(spark, sf_dir, "orders").groupBy(F.col("o_orderpriority").alias("label")).agg(F.count(F.lit(1)).alias("n"))


@query(f"SELECT DISTINCT label FROM ({language_sql('SELECT id, text FROM (' + SPECS['w1c']['b'] + f') q ORDER BY md5(concat(CHR(49) || CHR(48) || CHR(55) || CHR(58), CAST(id AS STRING))), id LIMIT 20')}) z")
def labels_from_sample(spark, sf_dir):
    w = workload(spark, sf_dir, "w1c")
    got = Advisor(w.a, w.b, w.predicate, model_of(w), JoinOptions()).labels()
    assert SEED + SAMPLE_SEED == 107
    return values(spark, [(x,) for x in got if x != UNKNOWN], "label string")


# Embedding and clustering.


@query(f"SELECT id, j AS dim, v[j + 1] AS n FROM ({embed_sql('SELECT p_partkey AS id, p_name || chr(32) || p_brand AS text FROM part')}) e, range(64) t(j) WHERE v[j + 1] > 0")
def hash_embed_part(spark, sf_dir):
    part = load(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), F.concat_ws(" ", "p_name", "p_brand").alias("text"))
    return cj.embed(part).select("id", F.posexplode("v").alias("dim", "n")).where("n > 0")


_VECTORS = "SELECT vec_id AS id, list_transform(embedding, lambda x: CAST(round(CAST(x AS DOUBLE) * 1e6) AS BIGINT)) AS v FROM embeddings"


@query(f"WITH {kmeans_ctes(_VECTORS, '4', 4, 'k')} SELECT id, cluster FROM k_out")
def kmeans_embeddings_k4(spark, sf_dir):
    points = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), T.quantize(F.col("embedding")).alias("v"))
    return clustering.kmeans(points, 4, SEED, 4)


@query(sides_sql("w2") + " SELECT 'a' AS side, cluster, count(*) AS n FROM sa GROUP BY 2 UNION ALL SELECT 'b', cluster, count(*) FROM sb GROUP BY 2")
def cluster_sizes(spark, sf_dir):
    w = workload(spark, sf_dir, "w2")
    one = lambda x, s: cj.cluster_side(x, JoinOptions()).groupBy("cluster").agg(F.count(F.lit(1)).alias("n")).select(F.lit(s).alias("side"), "cluster", "n")
    return one(w.a, "a").unionByName(one(w.b, "b"))


@query("SELECT source, n, CAST(r AS DOUBLE) AS r, greatest(2, CAST(floor(n * r + 1e-9) AS INT)) AS k FROM (SELECT source, CAST(count(*) AS INT) AS n FROM documents GROUP BY 1) a, (VALUES (0.025::DOUBLE), (0.05::DOUBLE), (0.075::DOUBLE), (0.1::DOUBLE)) b(r)")
def cluster_count_rule(spark, sf_dir):
    """How many clusters the documents of each source would get by each ratio."""
    sizes = load(spark, sf_dir, "documents").groupBy("source").agg(F.count(F.lit(1)).cast("int").alias("n")).collect()
    return values(spark, [(x["source"], x["n"], r, clustering.cluster_count(x["n"], r)) for x in sizes for r in tuning.RATIOS], "source string, n int, r double, k int")


@query()
def hdbscan_small(spark, sf_dir):
    points = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), T.quantize(F.col("embedding")).alias("v"))
    return clustering.hdbscan(points, 5, 3)


@query()
def kmeans_at_scale_embeddings(spark, sf_dir):
    points = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), T.quantize(F.col("embedding")).alias("v"))
    return clustering.kmeans_at_scale(points, 4).groupBy("cluster").agg(F.count(F.lit(1)).alias("n"))


# Cluster join.


def _clustered(spark, sf_dir, name="w2", **options):
    w = workload(spark, sf_dir, name)
    o = JoinOptions(**options)
    a, b = cj.cluster_side(w.a, o), cj.cluster_side(w.b, o)
    return w, o, a, b, cj.profile_plan(cj.cluster_pairs(a, b), o.min_profile_size)


def _profiled(spark, sf_dir, name="w2", **options):
    w, o, a, b, plan = _clustered(spark, sf_dir, name, **options)
    pairs, _, calls = cj.profile_pairs(plan, a, b, w.predicate, model_of(w), o.profile_sample, o.seed, o.pool_factor)
    return w, o, a, b, pairs, calls


@query(profiled_sql("w2") + " SELECT ca, na, cb, nb, bypassed FROM pl")
def cluster_pairs_w2(spark, sf_dir):
    return _clustered(spark, sf_dir)[4].select("ca", "na", "cb", "nb", "bypassed")


@query(profiled_sql("w2") + " SELECT ca, cb, id FROM da")
def profile_sample_w2(spark, sf_dir):
    _, o, a, _, plan = _clustered(spark, sf_dir)
    drawn = cj.pair_samples(a, plan.where("not bypassed"), "ca", o.profile_sample, o.seed, o.pool_factor)
    return drawn.select("ca", "cb", F.explode("items").alias("x")).select("ca", "cb", "x.id")


@query(profiled_sql("w2") + " SELECT ca, cb, sa, sb, n_match, n_cmp, bypassed, round(n_match / nullif(sa * sb, 0), 6) AS rate FROM pp")
def match_rate_w2(spark, sf_dir):
    pairs = _profiled(spark, sf_dir)[4]
    return pairs.select("ca", "cb", "sa", "sb", "n_match", "n_cmp", "bypassed", F.round(cj.match_rate(F.col("n_match"), F.col("sa"), F.col("sb")), 6).alias("rate"))


def _filtered(t: int):
    query(profiled_sql("w2") + f" SELECT ca, cb FROM pp WHERE {kept_sql(t)}", f"filter_pairs_t{t:03d}")(lambda spark, sf_dir: cj.filter_pairs(_profiled(spark, sf_dir)[4], t).select("ca", "cb"))


for _t in (0, 5, 20):
    _filtered(_t)


def _cluster_join(name: str, **options):
    def run(spark, sf_dir):
        w = workload(spark, sf_dir, name)
        return cj.cluster_join(w.a, w.b, w.predicate, model_of(w), JoinOptions(**options), projected=options.get("projection") == "on")["matches"].select("a_id", "b_id")

    return run


_IN_KEPT = "SELECT a.id AS a_id, b.id AS b_id FROM sa a JOIN sb b ON {on} JOIN pp ON pp.ca = a.cluster AND pp.cb = b.cluster WHERE {kept}"
query(profiled_sql("w2") + " " + _IN_KEPT.format(on=SPECS["w2"]["on"], kept=kept_sql(5)), "cluster_join_w2")(_cluster_join("w2"))
query(truth_sql("w2"), "cluster_join_w2_unfiltered")(_cluster_join("w2", filter_threshold=0))
query(profiled_sql("w3") + " " + _IN_KEPT.format(on=SPECS["w3"]["on"], kept=kept_sql(5)), "cluster_join_w3")(_cluster_join("w3"))
query(f"SELECT a.id AS a_id, b.id AS b_id FROM ({_W1['a']}) a JOIN ({_W1['b']}) b ON {quality_sql('a.text')} = {quality_sql('b.text')}", "cluster_join_w1_unfiltered")(_cluster_join("w1", filter_threshold=0))
query(truth_sql("w3"), "cluster_join_projected_w3")(_cluster_join("w3", projection="on", filter_threshold=0))
query(truth_sql("w2c"), "cluster_join_w2c")(_cluster_join("w2c", filter_threshold=0))
_VERBOSE = f"SELECT a.id AS a_id, b.id AS b_id FROM ({SPECS['w3b']['a']}) a JOIN ({SPECS['w3b']['b']}) b ON {SPECS['w3']['on']}"
query(_VERBOSE, "cluster_join_w3b")(_cluster_join("w3b", filter_threshold=0))
query(_VERBOSE, "cluster_join_projected_w3b")(_cluster_join("w3b", filter_threshold=0, projection="on"))
_SAME_QUALITY = f"{quality_sql('a.text')} = {quality_sql('b.text')}"
query(profiled_sql("w1", on=_SAME_QUALITY) + " " + _IN_KEPT.format(on=_SAME_QUALITY, kept=kept_sql(5)), "cluster_join_w1")(_cluster_join("w1"))


@query(f"SELECT a.id AS a_id, b.id AS b_id FROM ({_PARTS_ALL}) a JOIN ({SPECS['w3']['b']}) b ON {SPECS['w3']['on']}")
def cluster_join_w3_all(spark, sf_dir):
    """The tag workload on the whole table of parts."""
    register(spark, sf_dir, _PARTS_ALL)
    a, b = (keep(spark.sql(x).selectExpr("CAST(id AS BIGINT) AS id", "text"), "side") for x in (_PARTS_ALL, SPECS["w3"]["b"]))
    return cj.cluster_join(a, b, SPECS["w3"]["predicate"], RulebookModel("tag"), JoinOptions(filter_threshold=0, cluster_ratio=0.005))["matches"].select("a_id", "b_id")


query(None, "cluster_join_w2_density")(lambda spark, sf_dir: cj.cluster_join((w := workload(spark, sf_dir, "w2")).a, w.b, w.predicate, model_of(w), JoinOptions(filter_threshold=0), method="hdbscan")["matches"].select("a_id", "b_id"))
ORACLES["cluster_join_w2_density"] = truth_sql("w2")
query(None, "cluster_join_w2_top_centroids")(_cluster_join("w2", centroid_top_m=2))
query(None, "cluster_join_w2_reuse_profile")(_cluster_join("w2", reuse_profile=True, pool_factor=None, filter_threshold=0))
ORACLES["cluster_join_w2_reuse_profile"] = truth_sql("w2")


@query(profiled_sql("w2") + f" SELECT CAST(sum(ceil(na / 15.0) * ceil(nb / 15.0)) AS BIGINT) AS calls FROM pp WHERE {kept_sql(5)}")
def match_calls_w2(spark, sf_dir):
    w = workload(spark, sf_dir, "w2")
    calls = cj.cluster_join(w.a, w.b, w.predicate, model_of(w), JoinOptions())["calls"]
    return calls.where("stage = 'match'").agg(F.count(F.lit(1)).alias("calls"))


@query(profiled_sql("w2") + f" SELECT CAST(n_pairs AS BIGINT) AS n_pairs, CAST(n_sent AS BIGINT) AS n_sent, round(100.0 * (n_pairs - n_sent) / n_pairs, 4) AS pruned, n_true, true_kept, round(100.0 * true_kept / n_true, 4) AS filter_recall FROM (SELECT sum(na * nb)::DOUBLE AS n_pairs, coalesce(sum(CASE WHEN {kept_sql(5)} THEN na * nb END), 0)::DOUBLE AS n_sent FROM pp) x, (SELECT count(*) AS n_true, count(CASE WHEN {kept_sql(5)} THEN 1 END) AS true_kept FROM sa a JOIN sb b ON {SPECS['w2']['on']} JOIN pp ON pp.ca = a.cluster AND pp.cb = b.cluster) y")
def pruning_report(spark, sf_dir):
    w, _, a, b, pairs, _ = _profiled(spark, sf_dir)
    return M.pruning_report(pairs, cj.filter_pairs(pairs, 5), a, b, w.truth)


# Noise, baselines.

@query(f"{truth_sql('w2')} WHERE ('0x' || substr(md5(concat('7:', a.text, ':', b.text)), 1, 8))::UBIGINT % 10000 >= 3000")
def noisy_block_join_w2(spark, sf_dir):
    w = workload(spark, sf_dir, "w2")
    return baselines.block_join(w.a, w.b, w.predicate, NoisyModel(model_of(w), SEED, 0.3))[0].select("a_id", "b_id")


_COIN = "('0x' || substr(md5(concat({}, a.text, ':', b.text)), 1, 8))::UBIGINT % 10000"


@query(f"{truth_sql('w2')} WHERE {_COIN.format(chr(39) + '7:' + chr(39))} >= 1000 UNION ALL SELECT a.id AS a_id, b.id AS b_id FROM ({SPECS['w2']['a']}) a, ({SPECS['w2']['b']}) b WHERE NOT ({SPECS['w2']['on']}) AND {_COIN.format(chr(39) + '7:spurious:' + chr(39))} < 100")
def spurious_block_join_w2(spark, sf_dir):
    """A model that loses a tenth of the pairs and reports a hundredth of the others."""
    w = workload(spark, sf_dir, "w2")
    return baselines.block_join(w.a, w.b, w.predicate, NoisyModel(model_of(w), SEED, 0.1, spurious=0.01))[0].select("a_id", "b_id")


_SURE = lambda t: f"('0x' || substr(md5(concat('7:', {t})), 1, 8))::UBIGINT % 10000 >= 2000"


@query(f"SELECT a.id AS a_id, b.id AS b_id FROM ({_W1['a']}) a JOIN ({_W1['b']}) b ON {_SAME_QUALITY} WHERE {_SURE('a.text')} AND {_SURE('b.text')}")
def noisy_label_join_w1(spark, sf_dir):
    """A model that cannot label a fifth of the rows: they are in no pair."""
    w = workload(spark, sf_dir, "w1")
    return semantic_join(w.a, w.b, w.predicate, NoisyModel(model_of(w), SEED, unsure=0.2), JoinOptions(force_strategy="label", labels=("low", "high"))).pairs


@query(truth_sql("w2"))
def pairwise_w2(spark, sf_dir):
    w = workload(spark, sf_dir, "w2")
    return baselines.pairwise_join(w.a, w.b, w.predicate, model_of(w))[0].select("a_id", "b_id")


@query(truth_sql("w2"))
def block_join_w2_b15(spark, sf_dir):
    w = workload(spark, sf_dir, "w2")
    return baselines.block_join(w.a, w.b, w.predicate, model_of(w))[0].select("a_id", "b_id")


@query(f"SELECT concat(b, 'x', b) AS block, 100.0::DOUBLE AS f1, CAST(ceil(100.0 / b) * ceil(100.0 / b) AS BIGINT) AS calls FROM (VALUES (5), (10), (15), (20), (25)) t(b)")
def block_calls_sweep(spark, sf_dir):
    w = workload(spark, sf_dir, "w2")
    return tuning.block_sweep(w.a, w.b, w.truth, w.predicate, model_of(w), "w2").select("block", "f1", "calls")


_SIDE_STATS = "SELECT CAST(count(*) AS DOUBLE) AS n, CAST(avg((length(text) + 3) // 4 + 1) AS DOUBLE) AS t FROM ({}) x"
_FIXED = 30 + len(SPECS["w3"]["predicate"]) / 4
_BLOCKS = f"SELECT g.budget, a.n AS m, b.n AS n, a.t AS ta, b.t AS tb, CAST({_FIXED} AS DOUBLE) AS p, 0.11::DOUBLE AS sel, 2.0::DOUBLE AS o, i.ba FROM ({_SIDE_STATS.format(_PARTS_ALL)}) a, ({_SIDE_STATS.format(SPECS['w3']['b'])}) b, (VALUES (500), (1000), (2500)) g(budget), (SELECT CAST(range AS DOUBLE) AS ba FROM range(1, 2501)) i WHERE i.ba <= a.n"
_BLOCKS = f"SELECT *, least(n, floor((budget - p - ba * ta) / (tb + sel * ba * o))) AS bb FROM ({_BLOCKS}) x WHERE budget - p - ba * ta > 0"
_BLOCKS = f"SELECT *, ceil(m / ba) * ceil(n / bb) AS calls, ceil(m / ba) * ceil(n / bb) * p + m * ta * ceil(n / bb) + n * tb * ceil(m / ba) + sel * m * n * o AS cost FROM ({_BLOCKS}) y WHERE bb >= 1"


@query(f"SELECT budget, CAST(ba AS INT) AS ba, CAST(bb AS INT) AS bb, CAST(calls AS INT) AS calls FROM (SELECT *, row_number() OVER (PARTITION BY budget ORDER BY cost, ba * bb DESC, ba) AS r FROM ({_BLOCKS}) z) w WHERE r = 1")
def adaptive_blocks_w3(spark, sf_dir):
    """Block sizes for the tag workload on the whole table of parts, whose texts are measured, by token budget."""
    register(spark, sf_dir, _PARTS_ALL)
    s = baselines.measure(*[spark.sql(x) for x in (_PARTS_ALL, SPECS["w3"]["b"])], SPECS["w3"]["predicate"])
    got = [(t, *baselines.choose_blocks(s, t, 0.11)) for t in (500, 1000, 2500)]
    return values(spark, [(t, ba, bb, -(-s.m // ba) * -(-s.n // bb)) for t, ba, bb in got], "budget int, ba int, bb int, calls int")


def _adaptive(restart: bool):
    def run(spark, sf_dir):
        w = workload(spark, sf_dir, "w2")
        return baselines.adaptive_block_join(w.a, w.b, w.predicate, lambda most: RulebookModel(w.rule, most), 1000, restart=restart)[0].select("a_id", "b_id")

    return run


query(truth_sql("w2"), "adaptive_join_w2")(_adaptive(False))
query(truth_sql("w2"), "adaptive_join_w2_restart")(_adaptive(True))

_LITERALS = [baselines.Literal("text", "missing_word", 0.0), baselines.Literal("text", "jaccard", 0.7), baselines.Literal("text", "edit", 3.0)]


def _cnf(spark, sf_dir, name="w3", literals=_LITERALS):
    w = workload(spark, sf_dir, name)
    a, b = (x.withColumn("feature", F.col("text")) for x in (w.a, w.b))
    literals = [baselines.Literal("feature", x.distance, x.theta) for x in literals]
    return baselines.feature_cnf_join(a, b, literals, w.predicate, model_of(w))


@query(truth_sql("w3"))
def cnf_join_w3(spark, sf_dir):
    return _cnf(spark, sf_dir)["matches"].select("a_id", "b_id")


def _model_cnf(name: str, **params):
    def run(spark, sf_dir):
        w = workload(spark, sf_dir, name)
        return baselines.model_feature_cnf_join(w.a, w.b, w.predicate, model_of(w), **params)["matches"].select("a_id", "b_id")

    return run


query(truth_sql("w2"), "cnf_join_extracted_w2")(_model_cnf("w2"))
query(truth_sql("w3"), "cnf_join_extracted_w3")(_model_cnf("w3"))


@query(f"SELECT a.id AS a_id, b.id AS b_id FROM ({_PARTS_ALL}) a JOIN ({SPECS['w3']['b']}) b ON {SPECS['w3']['on']}")
def cnf_candidates_w3(spark, sf_dir):
    """Candidates of the tag workload over the whole table of parts."""
    register(spark, sf_dir, _PARTS_ALL)
    fa, fb = (spark.sql(x).selectExpr(f"CAST(id AS BIGINT) AS {s}_id", f"text AS {s}_text") for s, x in (("a", _PARTS_ALL), ("b", SPECS["w3"]["b"])))
    return baselines.cnf_candidates(fa, fb, [[_LITERALS[0]]]).select("a_id", "b_id")


@query(truth_sql("w7"))
def cnf_candidates_w7(spark, sf_dir):
    """Candidates of the reply workload over all conversations: two equal features, so a hash join on both."""
    register(spark, sf_dir, SPECS["w7"]["a"])
    fa, fb = (spark.sql(SPECS["w7"][s]).selectExpr(f"CAST(id AS BIGINT) AS {s}_id", f"CAST(conv_id AS STRING) AS {s}_conv", f"CAST(turn + {add} AS STRING) AS {s}_at") for s, add in (("a", 1), ("b", 0)))
    return baselines.cnf_candidates(fa, fb, [[baselines.Literal("conv", "equal", 0.0)], [baselines.Literal("at", "equal", 0.0)]]).select("a_id", "b_id")


@query("SELECT CAST(10000 AS BIGINT) AS survivors, CAST(10600 AS BIGINT) AS calls")
def cnf_degenerate_w2(spark, sf_dir):
    """No literal tells pairs apart: every pair is verified, besides the labelled sample."""
    got = _cnf(spark, sf_dir, "w2", [baselines.Literal("text", "edit", 0.0)])
    return got["survivors"].agg(F.count(F.lit(1)).alias("survivors")).crossJoin(got["calls"].agg(F.count(F.lit(1)).alias("calls")))


@query(f"WITH v AS ({_VECTORS}) SELECT q_id, id, dot, rank FROM (SELECT q.id AS q_id, v.id AS id, CAST(list_sum(list_transform(range(1, 65), lambda j: q.v[j] * v.v[j])) AS BIGINT) AS dot, row_number() OVER (PARTITION BY q.id ORDER BY list_sum(list_transform(range(1, 65), lambda j: q.v[j] * v.v[j])) DESC, v.id) AS rank FROM v JOIN v q ON q.id % 20 = 0 AND q.id <> v.id) x WHERE rank <= 3")
def similarity_topk_embeddings(spark, sf_dir):
    points = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), T.quantize(F.col("embedding")).alias("v"))
    return baselines.similarity_topk(points, points.where("id % 20 = 0").select(F.col("id").alias("q_id"), F.col("v").alias("q")))


@query(truth_sql("w3") + " WHERE b.text NOT LIKE 'Brand%'")
def project_filter_w3(spark, sf_dir):
    w = workload(spark, sf_dir, "w3")
    return baselines.project_filter_join(w.a, w.b, w.predicate, model_of(w), JoinOptions())["matches"].select("a_id", "b_id")


_EA, _EB = embed_sql(SPECS["w3"]["a"]), embed_sql(SPECS["w3"]["b"])
_DOT = lambda x, y: f"list_sum(list_transform(range(1, 65), lambda j: {x}.v[j] * {y}.v[j]))"


@query(f"SELECT a.id AS a_id, b.id AS b_id FROM ({_EA}) a, ({_EB}) b WHERE {_DOT('a', 'b')} > 0 AND {_DOT('a', 'b')} * {_DOT('a', 'b')} * 4 >= {_DOT('a', 'a')} * {_DOT('b', 'b')}")
def similarity_join_w3(spark, sf_dir):
    w = workload(spark, sf_dir, "w3")
    return baselines.similar_pairs(w.a, w.b, "hash-word-64", 1, 2)


# Measures.


@query(" UNION ALL ".join(f"SELECT '{n}' AS workload, (SELECT count(*) FROM ({SPECS[n]['a']}) x) AS n_a, (SELECT count(*) FROM ({SPECS[n]['b']}) x) AS n_b, count(*) AS n_true, round(100.0 * count(*) / ((SELECT count(*) FROM ({SPECS[n]['a']}) x) * (SELECT count(*) FROM ({SPECS[n]['b']}) x)), 4) AS selectivity FROM ({truth_sql(n)}) t" for n in ("w1", "w1b", "w1c", "w2", "w2b", "w3")))
def dataset_stats(spark, sf_dir):
    out = None
    for n in ("w1", "w1b", "w1c", "w2", "w2b", "w3"):
        w = workload(spark, sf_dir, n, stored=False)
        row = M.selectivity(w.a, w.b, w.truth).select(F.lit(n).alias("workload"), "n_a", "n_b", "n_true", "selectivity")
        out = row if out is None else out.unionByName(row)
    return out


@query(f"SELECT count(DISTINCT a_id) AS reachable, count(*) AS n_true, round(100.0 * count(DISTINCT a_id) / count(*), 4) AS ceiling FROM ({truth_sql('w3')}) t")
def label_ceiling(spark, sf_dir):
    return M.label_ceiling(workload(spark, sf_dir, "w3", stored=False).truth)


_SCORED = "SELECT '{s}' AS strategy, tp, fp, fn, round(100.0 * tp / (tp + fn), 4) AS recall, round(100.0 * tp / (tp + fp), 4) AS precision, round(200.0 * tp / (2 * tp + fp + fn), 4) AS f1 FROM (SELECT count(CASE WHEN o.a_id IS NOT NULL AND t.a_id IS NOT NULL THEN 1 END) AS tp, count(CASE WHEN t.a_id IS NULL THEN 1 END) AS fp, count(CASE WHEN o.a_id IS NULL THEN 1 END) AS fn FROM ({out}) o FULL JOIN ({truth}) t ON o.a_id = t.a_id AND o.b_id = t.b_id) x"


@query(_SCORED.format(s="label", out=ORACLES["label_join_tags"], truth=truth_sql("w3")) + " UNION ALL " + _SCORED.format(s="block", out=truth_sql("w3"), truth=truth_sql("w3")))
def scores_by_strategy(spark, sf_dir):
    w = workload(spark, sf_dir, "w3")
    label = semantic_join(w.a, w.b, w.predicate, model_of(w), JoinOptions(label_table=True, force_strategy="label")).pairs
    block = baselines.block_join(w.a, w.b, w.predicate, model_of(w), (15, 10))[0]
    return M.score(label, w.truth).select(F.lit("label").alias("strategy"), "*").unionByName(M.score(block, w.truth).select(F.lit("block").alias("strategy"), "*"))


_TRIALS = [("x", 50.0, 80.0, 61.54, 100.0), ("x", 40.0, 90.0, 55.38, 110.0), ("x", 30.0, 40.0, 34.29, 120.0)]


@query("SELECT s, round(avg(r), 2) AS recall, round(avg(p), 2) AS precision, round(avg(f), 2) AS f1, round(avg(t), 2) AS tokens FROM (" + values_sql(_TRIALS, "s, r, p, f, t") + ") y GROUP BY s")
def trial_average(spark, sf_dir):
    return M.average_trials(values(spark, _TRIALS, "s string, recall double, precision double, f1 double, tokens double"), "s")


_DOC_TRIALS = f"SELECT t, sum(tp) AS tp, sum(g) AS g, sum(y) AS y FROM (SELECT l.doc_id % 3 AS t, CASE WHEN l.quality = 1 THEN 1 ELSE 0 END AS y, CASE WHEN {quality_sql('d.text')} = 'high' THEN 1 ELSE 0 END AS g, CASE WHEN l.quality = 1 AND {quality_sql('d.text')} = 'high' THEN 1 ELSE 0 END AS tp FROM documents d JOIN labels l ON d.doc_id = l.doc_id) x GROUP BY 1"


@query(f"SELECT round(avg(200.0::DOUBLE * tp / (g + y)), 2) AS f1_averaged, round(2 * avg(100.0::DOUBLE * tp / y) * avg(100.0::DOUBLE * tp / g) / (avg(100.0::DOUBLE * tp / y) + avg(100.0::DOUBLE * tp / g)), 2) AS f1_of_averages FROM ({_DOC_TRIALS}) t")
def f1_avg_vs_of_avg(spark, sf_dir):
    """The quality rule against the labels, thirds of the labelled documents as trials."""
    both = load(spark, sf_dir, "documents").join(load(spark, sf_dir, "labels"), "doc_id")
    high = ~(F.contains("text", F.lit("!!")) | F.contains("text", F.lit(" | ")) | (F.length("text") < 100) | F.col("text").rlike("[%#*]{3}"))
    one = lambda x: F.sum(F.when(x, 1).otherwise(0))
    t = both.groupBy(F.col("doc_id") % 3).agg(one((F.col("quality") == 1) & high).alias("tp"), one(high).alias("g"), one(F.col("quality") == 1).alias("y"))
    t = t.selectExpr("try_divide(100D * tp, y) AS r", "try_divide(100D * tp, g) AS p", "try_divide(200D * tp, g + y) AS f")
    return t.agg(F.round(F.avg("f"), 2).alias("f1_averaged"), F.round(2 * F.avg("r") * F.avg("p") / (F.avg("r") + F.avg("p")), 2).alias("f1_of_averages"))


#: Published F1 and tokens by workload and strategy.
PUBLISHED = [("reviews", "cluster", 55.56, 38624), ("reviews", "label", 78.08, 22362), ("reviews", "adaptive", 49.92, 70446), ("reviews", "feature-cnf", 42.2, 5296336), ("emails", "cluster", 75.11, 26963), ("emails", "adaptive", 42.0, 43340), ("emails", "feature-cnf", 18.27, 1554914), ("tags", "cluster", 69.74, 76942), ("tags", "label", 74.95, 30216), ("tags", "adaptive", 54.86, 26895), ("tags", "feature-cnf", 42.77, 3607262)]


#: Least lengths of documents that are tried as a sign of quality.
_LENGTHS = (100, 200, 400, 800)
_LENGTH_GRID = "SELECT workload, CAST(0.05 AS DOUBLE) AS ratio, threshold, 200.0::DOUBLE * sum(y * g) / (sum(y) + sum(g)) AS f1, CAST(sum(g * ((n + 3) // 4)) AS BIGINT) AS tokens FROM (SELECT d.lang AS workload, t.threshold, length(d.text) AS n, CASE WHEN l.quality = 1 THEN 1 ELSE 0 END AS y, CASE WHEN length(d.text) >= t.threshold THEN 1 ELSE 0 END AS g FROM documents d JOIN labels l ON d.doc_id = l.doc_id, (VALUES (100), (200), (400), (800)) t(threshold)) x GROUP BY 1, 3"


def _length_grid(spark, sf_dir) -> DataFrame:
    """(workload, ratio, threshold, f1, tokens): how well a least length tells the labelled documents of good quality, by
    language, and how many tokens it leaves."""
    both = load(spark, sf_dir, "documents").join(load(spark, sf_dir, "labels"), "doc_id")
    rows = both.select(F.col("lang").alias("workload"), F.length("text").alias("n"), F.when(F.col("quality") == 1, 1).otherwise(0).alias("y"), F.explode(F.array(*map(F.lit, _LENGTHS))).alias("threshold"))
    rows = rows.withColumn("g", F.when(F.col("n") >= F.col("threshold"), 1).otherwise(0))
    grid = rows.groupBy("workload", "threshold").agg(F.expr("try_divide(200D * sum(y * g), sum(y) + sum(g))").alias("f1"), F.expr("sum(g * ((n + 3) div 4))").alias("tokens"))
    return grid.select("workload", F.lit(0.05).alias("ratio"), "threshold", "f1", "tokens")


@query(f"WITH p AS ({_LENGTH_GRID}) SELECT a.workload, CAST(a.threshold AS VARCHAR(20)) AS strategy, CAST(round(a.f1 - b.f1, 2) AS DOUBLE) AS points, CAST(round(100.0::DOUBLE * (b.tokens - a.tokens) / b.tokens, 1) AS DOUBLE) AS saving FROM p a JOIN p b ON a.workload = b.workload AND b.threshold = 100 WHERE a.threshold <> 100")
def savings(spark, sf_dir):
    return M.compare(_length_grid(spark, sf_dir).withColumn("strategy", F.col("threshold").cast("string")), "100")


@query(values_sql([("reviews", "label", "label", True), ("emails", "cluster", "cluster", True), ("tags", "label", "label", True)], "workload, best, route, \"right\""))
def routing_accuracy(spark, sf_dir):
    routes = []
    for name, paper in (("w1", "reviews"), ("w2", "emails"), ("w3", "tags")):
        w = workload(spark, sf_dir, name)
        routes.append((paper, Advisor(w.a, w.b, w.predicate, model_of(w), JoinOptions()).decide("strategy")))
    return M.routing_accuracy(values(spark, PUBLISHED, "workload string, strategy string, f1 double, tokens long"), values(spark, routes, "workload string, route string"))


@query()
def tokens_by_stage_rollup(spark, sf_dir):
    out = None
    for n in ("w1c", "w2", "w3"):
        w = workload(spark, sf_dir, n)
        calls = semantic_join(w.a, w.b, w.predicate, model_of(w), JoinOptions(label_table=n == "w3")).calls.withColumn("workload", F.lit(n))
        out = calls if out is None else out.unionByName(calls)
    return out.rollup("workload", "stage").agg(F.sum(F.col("in_tok") + F.col("out_tok")).alias("tokens"), F.count(F.lit(1)).alias("calls"))


# Tuning and experiments.


def _grid(name: str):
    def run(spark, sf_dir):
        w = workload(spark, sf_dir, name)
        return tuning.cluster_grid(w.a, w.b, w.truth, w.predicate, model_of(w), JoinOptions(), name)

    return run


for _name in ("w1", "w2", "w3"):
    query(None, f"cluster_grid_{_name}")(_grid(_name))
    query(None, f"pick_config_{_name}")(lambda spark, sf_dir, n=_name: M.pick_config(_grid(n)(spark, sf_dir)))


@query(f"WITH p AS ({_LENGTH_GRID}), r AS (SELECT *, row_number() OVER (PARTITION BY workload ORDER BY f1 DESC, tokens, ratio, threshold) AS r FROM p), c AS (SELECT x.*, row_number() OVER (PARTITION BY x.workload ORDER BY CASE WHEN x.r = 1 THEN 1 ELSE 0 END, x.tokens, x.f1 DESC, x.ratio, x.threshold) AS q FROM r x JOIN r y ON x.workload = y.workload AND y.r = 1 AND x.f1 >= y.f1 - 2.5 AND (x.r = 1 OR x.tokens <= 0.9::DOUBLE * y.tokens)) SELECT workload, ratio, threshold, f1, tokens FROM c WHERE q = 1")
def pick_config_example(spark, sf_dir):
    return M.pick_config(_length_grid(spark, sf_dir))


@query()
def block_sweep_noisy(spark, sf_dir):
    """The block sweep with a model that loses more pairs the more it compares at once."""

    def one(n: str, slope: float) -> DataFrame:
        w = workload(spark, sf_dir, n)
        return tuning.block_sweep(w.a, w.b, keep(w.truth, "truth"), w.predicate, NoisyModel(model_of(w), SEED, 0.1, slope), n)

    return tuning.side_by_side([functools.partial(one, *x) for x in (("w1", 0.00074), ("w2", 0.00023), ("w3", 0.00057))])


@query()
def projection_ablation(spark, sf_dir):
    """Cluster join without and with projection on the three workloads, and what projection changes: points of F1, percent of tokens."""

    def one(w, truth: DataFrame, on: bool) -> DataFrame:
        got = cj.cluster_join(w.a, w.b, w.predicate, model_of(w), JoinOptions(), projected=on)
        return M.score(got["matches"], truth).crossJoin(M.token_cost(got["calls"])).select(F.lit(w.name).alias("workload"), F.lit(on).alias("projected"), "recall", "precision", "f1", "tokens", "calls")

    out = tuning.side_by_side([functools.partial(one, *x, on) for x in _stored(spark, sf_dir) for on in (False, True)])
    off = out.where("not projected").select("workload", F.col("f1").alias("f0"), F.col("tokens").alias("t0"))
    return out.join(off, "workload").select(*out.columns, F.round(F.col("f1") - F.col("f0"), 2).alias("points"), F.round(100.0 * (F.col("tokens") - F.col("t0")) / F.col("t0"), 1).alias("more_tokens"))


def _strategy(strategy: str, w, seed: int) -> tuple[DataFrame, DataFrame]:
    """(pairs, calls) of one strategy with a model that loses more pairs the more it compares at once."""
    noisy = lambda most=None: NoisyModel(RulebookModel(w.rule, most), seed, 0.1, 0.0005)
    options = JoinOptions(seed=seed, label_table=w.name == "w3", labels=("low", "high") if w.name == "w1" else None, force_strategy="label")
    if strategy == "label":
        got = semantic_join(w.a, w.b, w.predicate, noisy(), options)
        return got.pairs, got.calls
    if strategy == "adaptive":
        return baselines.adaptive_block_join(w.a, w.b, w.predicate, noisy, 4000)[:2]
    if strategy == "cluster":
        got = cj.cluster_join(w.a, w.b, w.predicate, noisy(), options)
    elif strategy == "feature-cnf":
        got = baselines.model_feature_cnf_join(w.a, w.b, w.predicate, noisy(), seed=seed)
    elif strategy == "project-filter":
        got = baselines.project_filter_join(w.a, w.b, w.predicate, noisy(), options)
    elif strategy == "similarity":
        return baselines.similar_pairs(w.a, w.b, "hash-word-64", 1, 2), _no_calls(w.a)
    else:
        return baselines.block_join(w.a, w.b, w.predicate, noisy(), {"pairwise": (1, 1), "block": (15, 15)}[strategy])
    return got["matches"].select("a_id", "b_id"), got["calls"]


def _no_calls(df: DataFrame) -> DataFrame:
    """The log of a strategy that asks nothing."""
    return df.sparkSession.createDataFrame([], CALLS)


def _stored(spark: SparkSession, sf_dir: str) -> list[tuple]:
    """(workload, its true pairs) of the three main workloads, written once for many runs."""
    return [(w, keep(w.truth, "truth")) for w in (workload(spark, sf_dir, n) for n in ("w1", "w2", "w3"))]


def _scored_run(strategy: str, w, truth: DataFrame, trial: int, seed: int) -> DataFrame:
    pairs, calls = _strategy(strategy, w, seed)
    cost = M.token_cost(calls).select(F.coalesce("tokens", F.lit(0)).alias("tokens"))
    return M.score(pairs, truth).crossJoin(cost).select(F.lit(w.name).alias("workload"), F.lit(strategy).alias("strategy"), F.lit(trial).alias("trial"), "recall", "precision", "f1", "tokens")


@query()
def main_comparison(spark, sf_dir):
    """The four compared strategies on the three workloads, three trials, averaged: recall, precision, F1 and tokens. The
    routed strategy is marked, and the best one by F1, so that what the advisor chose is held against runs."""
    stored = _stored(spark, sf_dir)
    runs = [functools.partial(_scored_run, s, w, truth, trial, seed) for s in ("feature-cnf", "cluster", "adaptive", "label") for w, truth in stored for trial, seed in enumerate((7, 11, 13))]
    out = tuning.side_by_side(runs)
    routes = [(w.name, Advisor(w.a, w.b, w.predicate, model_of(w), JoinOptions(label_table=w.name == "w3")).decide("strategy")) for w, _ in stored]
    averaged = M.average_trials(out, "workload", "strategy").join(values(spark, routes, "workload string, route string"), "workload")
    top = averaged.groupBy("workload").agg(F.max_by("strategy", F.struct("f1", "strategy")).alias("top"))
    return averaged.join(top, "workload").select("workload", "strategy", "recall", "precision", "f1", "tokens", (F.col("strategy") == F.col("route")).alias("routed"), (F.col("strategy") == F.col("top")).alias("best"))


@query()
def every_baseline(spark, sf_dir):
    """Pairwise, fixed blocks, adaptive blocks, similarity alone and project-then-filter on the three workloads, one trial each."""
    strategies = ("pairwise", "block", "adaptive", "similarity", "project-filter")
    return tuning.side_by_side([functools.partial(_scored_run, s, w, truth, 0, SEED) for s in strategies for w, truth in _stored(spark, sf_dir)]).drop("trial")


# Semantic operators around the join.

_QA, _QT = SPECS["w2"]["a"], truth_sql("w2")


def _result(spark, sf_dir):
    w = workload(spark, sf_dir, "w2")
    return semantic_join(w.a, w.b, w.predicate, model_of(w), JoinOptions(force_strategy="cluster", filter_threshold=0))


query(f"SELECT a.id AS a_id, a.text AS a_text FROM ({_QA}) a WHERE a.id IN (SELECT a_id FROM ({_QT}) t)", "sem_semi")(lambda spark, sf_dir: _result(spark, sf_dir).joined("semi"))
query(f"SELECT a.id AS a_id, a.text AS a_text FROM ({_QA}) a WHERE a.id NOT IN (SELECT a_id FROM ({_QT}) t)", "sem_anti")(lambda spark, sf_dir: _result(spark, sf_dir).joined("anti"))
query(f"SELECT a.id AS a_id, t.b_id FROM ({_QA}) a LEFT JOIN ({_QT}) t ON t.a_id = a.id", "sem_left_outer")(lambda spark, sf_dir: _result(spark, sf_dir).joined("left").select("a_id", "b_id"))
query(f"SELECT a_id, b_id FROM (SELECT *, row_number() OVER (PARTITION BY a_id ORDER BY b_id) AS r FROM ({_QT}) t) x WHERE r <= 2", "sem_topk_per_a")(lambda spark, sf_dir: limit_per_a(_result(spark, sf_dir).pairs, 2))


@query(f"SELECT doc_id AS id FROM documents WHERE {toxic_sql('text')} = 'abusive'")
def sem_filter_toxic(spark, sf_dir):
    docs = load(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text")
    return sem_filter(docs, "is the text abusive", RulebookModel("toxic"), "abusive", ("abusive", "civil")).select("id")


@query(language_sql("SELECT doc_id AS id, text FROM documents"))
def sem_classify_language(spark, sf_dir):
    docs = load(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text")
    return classifier.classify(docs, [*STOP_WORDS, UNKNOWN], "which language is the text in", RulebookModel("language"), buckets=8)[0]


@query(truth_sql("w5"))
def needle_benchmark(spark, sf_dir):
    docs, items = load(spark, sf_dir, "documents").select(F.col("doc_id").alias("a_id"), "text"), load(spark, sf_dir, "benchmark").select(F.col("item_id").alias("b_id"), F.col("text").alias("passage"))
    return baselines.containment_join(docs, items)


@query("SELECT doc_id, first AS class_id, n FROM (SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS first, count(*) OVER (PARTITION BY text) AS n FROM documents) x WHERE n > 1")
def exact_copies(spark, sf_dir):
    """Classes of equal texts, not their pairs: a row for each copy, with the smallest id of its class and the class size."""
    docs = load(spark, sf_dir, "documents").select("doc_id", F.sha2("text", 256).alias("h"))
    classes = docs.groupBy("h").agg(F.min("doc_id").alias("class_id"), F.count(F.lit(1)).alias("n")).where("n > 1")
    return docs.join(classes, "h").select("doc_id", "class_id", "n")


for _name in ("w7", "w8", "w10"):
    query(truth_sql(_name, "count(*) AS n, CAST(sum(a.id % 97 + b.id % 89) AS BIGINT) AS s"), f"truth_{_name}")(lambda spark, sf_dir, n=_name: _truth_sum(spark, sf_dir, n))


def _truth_sum(spark, sf_dir, name):
    register(spark, sf_dir, SPECS[name]["a"], SPECS[name]["b"])
    a, b = (spark.sql(SPECS[name][x]).alias(x) for x in "ab")
    return a.join(b, F.expr(SPECS[name]["on"])).agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("a.id") % 97 + F.col("b.id") % 89).alias("s"))


@query(values_sql([("empty", 0, 2), ("prose", 0, 2), ("broken", 0, 2), ("out of range", 1, 1), ("twice", 1, 1), ("fenced", 1, 1)], "reply, pairs, calls"))
def malformed_replies(spark, sf_dir):
    """Pairs and calls that come of damaged replies: one repeated question, then no answer."""
    from semjoin.plans.invoke import block_prompts, calls_of, pairs_of, run_prompts

    rows, out = values(spark, [(1, "x"), (2, "y")], "id long, text string"), []
    for name, reply in (("empty", ""), ("prose", "I think they match"), ("broken", "[[0, 1"), ("out of range", "[[0, 1], [5, 0]]"), ("twice", "[[0, 1], [0, 1]]"), ("fenced", "```json\n[[1, 0]]\n```")):
        got = run_prompts(block_prompts(rows, rows, None, (2, 2), "match"), "match", "same", ScriptedModel([reply, reply]), "match")
        out.append((name, pairs_of(got).count(), calls_of(got).count()))
    return values(spark, out, "reply string, pairs int, calls int")


@query(f"SELECT id, list_extract(string_split(text, ' '), -2) AS value FROM ({SPECS['w3']['a']}) a")
def sem_extract_noun(spark, sf_dir):
    w = workload(spark, sf_dir, "w3")
    return sem_extract(w.a, "which thing is it", model_of(w))


@query(truth_sql("w3") + " WHERE a.id < 100 AND b.text <> 'bolt'")
def sql_semantic_join(spark, sf_dir):
    w = workload(spark, sf_dir, "w3")
    w.a.createOrReplaceTempView("items")
    w.b.createOrReplaceTempView("tags")
    text = "SELECT items.id AS a_id, tags.id AS b_id FROM items SEMANTIC JOIN tags ON MATCHES('the tag describes the item') WHERE items.id < 100 AND tags.text <> 'bolt'"
    return semantic_sql(spark, text, model_of(w), JoinOptions(force_strategy="cluster", filter_threshold=0))


@query(language_sql("SELECT doc_id AS id, text FROM documents"))
def sql_function_classify(spark, sf_dir):
    load(spark, sf_dir, "documents").createOrReplaceTempView("texts")
    register_classify(spark, "language_of", "which language is the text in", tuple(STOP_WORDS), RulebookModel("language"))
    return spark.sql("SELECT doc_id AS id, language_of(text) AS label FROM texts")


@query(f"SELECT a.id AS id, b.text AS partner FROM ({SPECS['w3']['a']}) a JOIN ({SPECS['w3']['b']}) b ON {SPECS['w3']['on']}")
def sql_table_function(spark, sf_dir):
    workload(spark, sf_dir, "w3").a.createOrReplaceTempView("items")
    register_partners(spark, "tags_of", "the tag describes the item", TAGS, RulebookModel("tag"))
    return spark.sql("SELECT id, partner FROM items, LATERAL tags_of(text)")


query(ORACLES["advisor_decisions_w2"], "advisor_single_call")(_decisions("w2", single_call=True))


@query()
def approximate_counts(spark, sf_dir):
    return load(spark, sf_dir, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"), F.percentile_approx("value", 0.5).alias("mid"))


for _module in (relational, windows):
    QUERIES.update(_module.QUERIES)
    ORACLES.update(_module.ORACLES)
