"""The workloads of the experiments on the given tables, in SQL that Spark and other engines both run.

Class counts, the modulus and the tag list were fitted to published selectivities, so the closeness of
those is by design.
"""

from __future__ import annotations

import dataclasses
import re

from pyspark.sql import DataFrame, SparkSession

from semjoin.sources.tables import TABLES, keep, views

TAGS = ("anvil", "bolt", "gear", "gizmo", "plate", "ring", "rod", "widget", "Brand#7", "Brand#20")


def _classes(label: str, names: tuple[str, str], a: tuple[int, int], b: tuple[int, int]) -> dict[str, str]:
    ranked = f"SELECT d.doc_id AS id, d.text AS text, l.{label} AS lab, row_number() OVER (PARTITION BY l.{label} ORDER BY md5(concat('7:', CAST(d.doc_id AS STRING))), d.doc_id) AS rn FROM documents d JOIN labels l ON d.doc_id = l.doc_id"
    return {
        "a": f"SELECT id, text, lab FROM ({ranked}) r WHERE (lab = 0 AND rn <= {a[0]}) OR (lab = 1 AND rn <= {a[1]})",
        "b": f"SELECT id, text, lab FROM ({ranked}) r WHERE (lab = 0 AND rn > {a[0]} AND rn <= {a[0] + b[0]}) OR (lab = 1 AND rn > {a[1]} AND rn <= {a[1] + b[1]})",
        "on": "a.lab = b.lab",
    }


def _notes(kind: str) -> str:
    return f"(SELECT event_id, user_id % 9 AS p, CAST(ts AS DATE) AS d FROM events WHERE event_type = '{kind}' ORDER BY md5(concat('7:', CAST(event_id AS STRING))), event_id LIMIT 100) e"


_LANG = "SELECT doc_id AS id, text, lang, row_number() OVER (ORDER BY md5(concat('7:', CAST(doc_id AS STRING))), doc_id) AS rn FROM (SELECT doc_id, text, lang FROM documents ORDER BY md5(concat('7:', CAST(doc_id AS STRING))), doc_id LIMIT 100) d"
_SAYS = "SELECT event_id AS id, concat('person ', CAST(p AS STRING), ' says first notice was on ', CAST(d AS STRING)) AS text, p, d FROM " + _notes("error")
_TOLD = "SELECT event_id AS id, concat('person ', CAST(p AS STRING), ' was told on ', CAST(d AS STRING)) AS text, p, d FROM " + _notes("signup")
_PARTS = "SELECT p_partkey AS id, concat(p_name, ' ', p_brand) AS text FROM (SELECT p_partkey, p_name, p_brand FROM part ORDER BY p_partkey LIMIT 250) p"
_TAGS = " UNION ALL ".join(f"SELECT CAST({i} AS BIGINT) AS id, '{t}' AS text" for i, t in enumerate(TAGS))
_WORD = "contains(concat(' ', a.text, ' '), concat(' ', b.text, ' '))"

#: name: rule of the stand-in model, the sentence, SQL of both sides and of the truth.
SPECS: dict[str, dict] = {
    "w1": {"rule": "quality", "predicate": "both texts are of the same editorial quality", **_classes("quality", ("low", "high"), (22, 28), (30, 20))},
    "w1b": {"rule": "toxic", "predicate": "both texts are abusive or both are civil", **_classes("toxic", ("civil", "abusive"), (28, 22), (21, 29))},
    "w1c": {"rule": "language", "predicate": "both texts are in the same language", "a": f"SELECT id, text, lang FROM ({_LANG}) x WHERE rn <= 50", "b": f"SELECT id, text, lang FROM ({_LANG}) x WHERE rn > 50", "on": "a.lang = b.lang"},
    "w2": {"rule": "contradiction", "predicate": "the two notes cannot both be true", "a": _SAYS, "b": _TOLD, "on": "a.p = b.p AND b.d < a.d"},
    "w2b": {"rule": "contradiction", "predicate": "both notes are about the same person", "a": _SAYS, "b": _TOLD, "on": "a.p = b.p"},
    "w3": {"rule": "tag", "predicate": "the tag describes the item", "a": _PARTS, "b": _TAGS, "on": _WORD},
    "w3b": {
        "rule": "tag", "predicate": "the tag describes the item",
        "a": f"SELECT p.id AS id, concat(substr(d.text, 1, 300), ' ', p.text) AS text, p.text AS short FROM ({_PARTS}) p CROSS JOIN (SELECT count(*) AS n FROM documents) c JOIN documents d ON d.doc_id = p.id % c.n",
        "b": _TAGS, "on": "contains(concat(' ', a.short, ' '), concat(' ', b.text, ' '))",
    },
    "w5": {"rule": "contains", "predicate": "the text holds the passage", "a": "SELECT doc_id AS id, text FROM documents", "b": "SELECT item_id AS id, text FROM benchmark", "on": "contains(a.text, b.text)"},
    "w6": {"rule": "equal", "predicate": "one text is a copy of the other", "a": "SELECT doc_id AS id, text FROM documents", "b": "SELECT doc_id AS id, text FROM documents", "on": "a.text = b.text AND a.id < b.id"},
    "w7": {"rule": "equal", "predicate": "the second turn answers the first", "a": "SELECT conv_id * 1000 + turn AS id, text, conv_id, turn FROM conversations WHERE role = 'user'", "b": "SELECT conv_id * 1000 + turn AS id, text, conv_id, turn FROM conversations WHERE role = 'assistant'", "on": "a.conv_id = b.conv_id AND b.turn = a.turn + 1"},
    "w8": {"rule": "equal", "predicate": "both vectors have the same label", "a": "SELECT vec_id AS id, label FROM embeddings WHERE vec_id % 2 = 0", "b": "SELECT vec_id AS id, label FROM embeddings WHERE vec_id % 2 = 1", "on": "a.label = b.label"},
    "w9": {"rule": "equal", "predicate": "both customers are in the same segment", "a": "SELECT c_custkey AS id, c_mktsegment AS text FROM customer WHERE c_custkey % 2 = 0", "b": "SELECT c_custkey AS id, c_mktsegment AS text FROM customer WHERE c_custkey % 2 = 1", "on": "a.text = b.text"},
    "w10": {"rule": "equal", "predicate": "both pages are in the same language", "a": "SELECT page_id AS id, regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) AS text FROM pages", "b": "SELECT page_id AS id, regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) AS text FROM pages", "on": "a.text = b.text"},
}
SPECS["w2c"] = SPECS["w2"] | {"b": "SELECT id, concat('person ', CAST(p AS STRING), ' was told in the ', CASE WHEN third = 1 THEN 'early' WHEN third = 11 THEN 'middle' ELSE 'late' END, ' part of the month') AS text, p, third FROM (SELECT event_id AS id, p, CASE WHEN extract(DAY FROM d) <= 10 THEN 1 WHEN extract(DAY FROM d) <= 20 THEN 11 ELSE 21 END AS third FROM " + _notes("signup") + ") x", "on": "a.p = b.p AND b.third < extract(DAY FROM a.d)"}


@dataclasses.dataclass(frozen=True)
class Workload:
    name: str
    a: DataFrame
    b: DataFrame
    truth: DataFrame
    predicate: str
    rule: str


def truth_sql(name: str, select: str = "a.id AS a_id, b.id AS b_id") -> str:
    s = SPECS[name]
    return f"SELECT {select} FROM ({s['a']}) a JOIN ({s['b']}) b ON {s['on']}"


def register(spark: SparkSession, sf_dir: str, *sql: str) -> None:
    """Views of the tables that the statements name, and of no others: each costs a look at its files."""
    views(spark, sf_dir, *[t for t in TABLES if any(re.search(rf"\b{t}\b", x) for x in sql)])


def workload(spark: SparkSession, sf_dir: str, name: str, stored: bool = True) -> Workload:
    """The two sides (id, text) and the true pairs. Sides are written once, as several strategies read them."""
    s = SPECS[name]
    register(spark, sf_dir, s["a"], s["b"])
    sides = [spark.sql(s[x]).selectExpr("CAST(id AS BIGINT) AS id", "text") for x in "ab"]
    if stored:
        sides = [keep(x, f"{name}-side") for x in sides]
    return Workload(name, *sides, spark.sql(truth_sql(name)), s["predicate"], s["rule"])
