"""SQL twins of the queries that SQL can express, generated from the operators' fixed values."""

from __future__ import annotations

from semjoin.llm.quality import RULES, SYMBOLS

_BLANK = r"[ \t\n\x0B\f\r]"


def quality_sql(max_false_reject: float = 0.10, delta: float = 0.05) -> str:
    blanks = "concat(' ', chr(9), chr(10), chr(11), chr(12), chr(13))"
    value = {
        "symbols": "n_symbols / greatest(n_words, 1)::DOUBLE", "marks": "n_marks / greatest(n_words, 1)::DOUBLE",
        "dup_lines": "n_dup_lines / greatest(n_lines, 1)::DOUBLE", "repeats": "n_repeat_words / greatest(n_words, 1)::DOUBLE",
    }
    p = max_false_reject / len(RULES)
    grid = ", ".join(f"('{r}', {c}::DOUBLE)" for r in RULES for c in RULES[r])
    tail = f"list_sum(list_transform(range(0, k + 1), lambda i: exp(lgamma(n + 1) - lgamma(i + 1) - lgamma(n - i + 1) + i * ln({p}) + (n - i) * ln(1 - {p}))))"
    over = "CASE rule " + " ".join(f"WHEN '{r}' THEN {v}" for r, v in value.items()) + " END"
    return f"""
WITH t AS (SELECT doc_id, coalesce(lang, '?') AS s, coalesce(text, '') AS x FROM documents),
w AS (SELECT *, list_filter(regexp_split_to_array(x, '{_BLANK}+'), lambda y: y <> '') AS ws, list_filter(string_split(x, chr(10)), lambda y: regexp_matches(y, '{_BLANK.replace("[", "[^")}')) AS ls FROM t),
g AS (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, ws[i], ws[i + 1], ws[i + 2]) AS c FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 1)) AS i FROM w) q),
r AS (SELECT doc_id, count(DISTINCT i + o) AS n_repeat_words FROM g, range(3) k(o) WHERE c > 1 GROUP BY doc_id),
f AS (SELECT w.doc_id, s, len(ws) AS n_words, length(translate(x, {blanks}, '')) AS word_chars, length(x) - length(translate(x, '{SYMBOLS}', '')) AS n_symbols, length(x) - length(translate(x, '!', '')) AS n_marks,
  len(ls) - len(list_distinct(ls)) AS n_dup_lines, len(ls) AS n_lines, coalesce(r.n_repeat_words, 0) AS n_repeat_words FROM w LEFT JOIN r ON r.doc_id = w.doc_id),
b AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM f),
good AS (SELECT b.* FROM b JOIN (SELECT doc_id FROM labels GROUP BY doc_id HAVING min(quality) = 1) l ON l.doc_id = b.doc_id WHERE NOT base_failed),
grid AS (SELECT * FROM (VALUES {grid}) v(rule, cutoff)),
tried AS (SELECT s, rule, cutoff, count(*) AS n, count(CASE WHEN {over} > cutoff THEN 1 END) AS k, (SELECT count(DISTINCT s) FROM good) * {sum(map(len, RULES.values()))} AS m FROM good, grid GROUP BY s, rule, cutoff),
cuts AS (SELECT s, rule, min(cutoff) AS cutoff FROM tried WHERE k <= n * {p} AND {tail} <= {delta} / m GROUP BY s, rule),
bad AS (SELECT DISTINCT b.doc_id FROM b JOIN cuts c ON c.s = b.s WHERE {over} > c.cutoff)
SELECT b.doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND bad.doc_id IS NULL AS kept FROM b LEFT JOIN bad ON bad.doc_id = b.doc_id"""


ORACLES = {"op4_quality_rules": quality_sql()}
