"""Late rows behind a watermark, and the label join's estimate for several questions a row."""

import duckdb
import pytest

from semjoin.plans.advisor import JoinOptions
from semjoin.plans.cost import estimate
from semjoin.streaming import windows


@pytest.mark.parametrize("sf", ["0.001", "0.01"])
def test_late_rows_change_no_closed_window(spark, sf):
    folder = f"/root/testdata/sf{sf}"
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{folder}/events.parquet'")
    want = sorted((k, s, n) for k, s, n in con.execute(windows.ORACLES["stream_late_rows"]).fetchall())
    got = sorted(tuple(r) for r in windows.QUERIES["stream_late_rows"](spark, folder).select("event_type", "start", "n").collect())
    assert got == want and want
    every = con.execute("SELECT count(*) FROM events").fetchone()[0]
    assert sum(n for *_, n in got) < every


def test_estimate_counts_every_question(spark):
    a = spark.createDataFrame([(i, "some words here") for i in range(50)], "id long, text string")
    b = spark.createDataFrame([(0, "bolt"), (1, "gear")], "id long, text string")
    one = estimate(a, b, "x", "label", JoinOptions(label_table=True), 4)
    four = estimate(a, b, "x", "label", JoinOptions(label_table=True, multi_label=True), 4)
    assert (one.calls, four.calls) == (3, 9) and four.tokens > 2.9 * one.tokens
    assert estimate(a, b, "x", "label", JoinOptions(), 4).calls == 4
