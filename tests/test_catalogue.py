"""The driver contract: names, and a sample of queries against their SQL."""

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
SAMPLE = ["m02_two_round_splitters", "m06_exact_splitters", "b02_regular_sample", "o_global_row_number", "o_asof_join", "o_global_lag", "o_merge_join", "o_grouped_quantiles", "w06_dist_skew3_keys"]


def cells(row):
    return tuple(f"{v:.6g}" if isinstance(v, float) else repr(v) for v in row)


@pytest.mark.parametrize("name", SAMPLE)
def test_query_equals_its_sql(spark, name):
    con = duckdb.connect()
    for t in ("orders", "lineitem", "events"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    out = entry.queries()[name](spark, SF)
    columns = sorted(out.columns)
    there = con.sql(entry.oracle_sql()[name])
    assert sorted(there.columns) == columns
    want = sorted(cells(r[there.columns.index(c)] for c in columns) for r in there.fetchall())
    assert sorted(cells(r[c] for c in columns) for r in out.collect()) == want


def test_entry_and_names(spark):
    rows = entry.entry(spark).collect()
    assert len(rows) == 8 and sum(r.rows for r in rows) == 6000
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_core_stands_without_the_training_data_operators(tmp_path):
    import shutil
    import subprocess
    import sys
    from pathlib import Path

    root = Path(entry.__file__).parent
    shutil.copy(root / "__spark_entry__.py", tmp_path)
    shutil.copytree(root / "rangecut", tmp_path / "rangecut", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    code = "import __spark_entry__ as e; q = e.queries(); assert 'm01_one_round_splitters' in q and 'pipeline' not in q; e.oracle_sql()"
    assert subprocess.run([sys.executable, "-c", code], cwd=tmp_path).returncode == 0
