"""Relational queries and label groups read their whole tables and equal their SQL twins."""

import pytest

from semjoin import catalogue
from semjoin.operators import relational

SF = "/root/testdata/sf0.01"
NAMES = sorted(n for n in catalogue.QUERIES if n.startswith(("win_", "fn_", "join_", "agg_collect", "label_groups_")) and n != "label_groups_count") + ["exact_copies"]


def test_names_and_bounds():
    assert {"win_rank", "win_running", "join_inner", "join_anti", "join_self", "fn_string", "fn_date", "fn_math", "fn_array", "fn_map", "fn_json", "agg_collect"} <= set(NAMES)
    assert {"label_groups_language_all", "label_groups_quality_all", "label_groups_toxic_all", "label_groups_tag_all"} <= set(NAMES)
    assert not any(f"{key} {op}" in sql for sql in relational.ORACLES.values() for key in ("WHERE doc_id", "WHERE event_id", "WHERE p_partkey", "WHERE o_orderkey") for op in ("<", "%"))


@pytest.mark.parametrize("name", NAMES)
def test_whole_table_equals_sql(spark, name):
    import duckdb

    con = duckdb.connect()
    for t in catalogue.load.__globals__["TABLES"]:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    cur = con.execute(catalogue.ORACLES[name])
    names = [x[0] for x in cur.description]
    got = catalogue.QUERIES[name](spark, SF)
    assert sorted(names) == sorted(got.columns)
    assert sorted(str(tuple(r[c] for c in names)) for r in got.collect()) == sorted(map(str, cur.fetchall()))
