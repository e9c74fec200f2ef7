"""Searches go on until nothing is live: a replay in SQL that stops at 24 rounds shows less of one that needs more."""

import datetime

import duckdb
import pytest

from rangecut import workloads
from rangecut.catalog import replay
from rangecut.plans import search
from rangecut.plans.keys import lineitem
from rangecut.sources.tables import load

SF = "/root/testdata/sf0.001"


def replayed(rounds):
    con = duckdb.connect()
    con.execute(f"CREATE VIEW lineitem AS SELECT * FROM '{SF}/lineitem.parquet'")
    return con.sql(replay.totals(replay.lineitem(), 8, 0.002, 10, ["0"] * rounds, kind="per_interval", beta=1)).fetchall()[0]


def like_one_row(spark, quantities):
    """Lines that are alike in all but the quantity, so that a round draws all of them or none."""
    columns = "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_shipdate timestamp"
    return spark.createDataFrame([(679, 1, 1, 1, q, 1.0, datetime.datetime(2000, 1, 1)) for q in quantities], columns).coalesce(1)


def test_rounds_past_the_replay_of_24(spark):
    result = search.per_interval_rounds(load(spark, SF, "lineitem"), lineitem(), 8, 0.002, 1, 10)
    assert not result.state.live()
    assert (result.rounds, result.sample) == replayed(40) == (27, 103)
    assert replayed(24) == (24, 97)


def test_rounds_past_64(spark, tmp_path):
    like_one_row(spark, [float(q) for q in range(60)]).write.parquet(f"{tmp_path}/lineitem.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW lineitem AS SELECT * FROM '{tmp_path}/lineitem.parquet/*.parquet'")
    ours = con.sql(replay.totals(replay.lineitem(), 2, 0.02, 1, replay.budget_limits(2, 1, 70))).fetchall()[0]
    theirs = con.sql(replay.totals(replay.lineitem(), 2, 0.02, 1, ["0"] * 70, kind="per_interval", beta=1)).fetchall()[0]
    assert (ours, theirs) == ((3, 60), (65, 60))
    assert workloads.rounds_by_parts(spark, str(tmp_path), [2], 0.02, 1, portable=True) == [("narrowing", 2, 1, *ours), ("per interval", 2, 1, *theirs)]


@pytest.mark.parametrize("finder", [search.budget_rounds, search.per_interval_rounds])
def test_equal_rows_end_a_search_without_a_limit(spark, finder):
    result = finder(like_one_row(spark, [1.0] * 10), lineitem(), 2, 0.02, 10, max_rounds=None)
    assert result.rounds == 1 and result.sample == 10
    assert result.state.unsettled() == [0]  # no cut can split them
