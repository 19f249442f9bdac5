"""Queries on the advisor, labels, grids and blocks take what they decide on from the given tables."""

import duckdb
import pytest

from semjoin import catalogue

SF = "/root/testdata/sf0.001"
READS = {"adaptive_blocks_w3": "part", "advisor_fallbacks": "conversations", "cluster_count_rule": "documents", "f1_avg_vs_of_avg": "labels", "label_guard": "documents", "pick_config_example": "documents", "savings": "documents"}


@pytest.mark.parametrize("name", READS)
def test_equals_sql_and_reads_its_table(spark, name, tmp_path):
    con = duckdb.connect()
    for t in catalogue.load.__globals__["TABLES"]:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    cur = con.execute(catalogue.ORACLES[name])
    names = [x[0] for x in cur.description]
    got = catalogue.QUERIES[name](spark, SF)
    assert sorted(names) == sorted(got.columns)
    rows = cur.fetchall()
    assert rows and sorted(str(tuple(r[c] for c in names)) for r in got.collect()) == sorted(map(str, rows))
    assert READS[name] in catalogue.ORACLES[name]
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        catalogue.QUERIES[name](spark, str(tmp_path)).collect()
