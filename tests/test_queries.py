"""Every query against its SQL twin, and the entry module without the subpackage that may be missing."""

import subprocess
import sys
from pathlib import Path

import duckdb
import pytest

from ranksort import catalog

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
ROOT = Path(__file__).resolve().parent.parent


@pytest.fixture(scope="module")
def database(sf):
    connection = duckdb.connect()
    for table in TABLES:
        connection.execute(f"CREATE VIEW {table} AS SELECT * FROM read_parquet('{sf}/{table}.parquet')")
    return connection


def plain(value):
    if isinstance(value, float):
        return round(value, 6) + 0.0
    if hasattr(value, "isoformat"):
        return value.isoformat()
    return value


@pytest.mark.parametrize("name", sorted(catalog.QUERIES))
def test_query(spark, sf, database, name):
    found = catalog.QUERIES[name](spark, sf)
    columns = sorted(found.columns)
    rows = sorted((tuple(plain(r[c]) for c in columns) for r in found.collect()), key=repr)
    if name not in catalog.ORACLES:
        assert rows
        return
    result = database.execute(catalog.ORACLES[name])
    names = [d[0] for d in result.description]
    assert sorted(names) == columns
    at = [names.index(c) for c in columns]
    assert rows == sorted((tuple(plain(r[i]) for i in at) for r in result.fetchall()), key=repr)


#: Queries that once made their input up.
MADE_OF_LINES = ["cost_model", "pivot_ledger", "pivot_slots", "rank_schedule", "round_ledger", "sql_table_functions", "switch_sweep"]


@pytest.mark.parametrize("name", MADE_OF_LINES)
def test_made_of_a_given_table(spark, sf, name):
    assert any("lineitem" in file for file in catalog.QUERIES[name](spark, sf).inputFiles())


def test_ends_that_tie(spark, tmp_path):
    """agg_positional: of ties the least key, in whichever order rows come; nulls as in SQL."""
    rows = [(k, "A", b) for k, b in [(3, 1.0), (1, 1.0), (2, 1.0), (6, 9.0), (4, 9.0), (5, 9.0), (None, 0.0), (None, 10.0), (7, None)]] + [(None, "B", 1.0)]
    spark.createDataFrame(rows, "c_custkey long, c_mktsegment string, c_acctbal double").coalesce(1).write.parquet(str(tmp_path / "customer.parquet"))
    found = catalog.QUERIES["agg_positional"](spark, str(tmp_path)).orderBy("c_mktsegment").collect()
    assert [tuple(r) for r in found] == [("A", 1, 4, 9), ("B", None, None, 1)]
    connection = duckdb.connect()
    connection.execute(f"SET threads = 1; CREATE VIEW customer AS SELECT * FROM read_parquet('{tmp_path}/customer.parquet/*.parquet') ORDER BY c_custkey")
    assert sorted(connection.execute(catalog.ORACLES["agg_positional"]).fetchall()) == [tuple(r) for r in found]


def test_entry_without_the_subpackage(tmp_path):
    for name in ("__spark_entry__.py", "ranksort"):
        (tmp_path / name).symlink_to(ROOT / name) if name.endswith(".py") else None
    import shutil

    shutil.copytree(ROOT / "ranksort", tmp_path / "ranksort", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    code = "import __spark_entry__ as e; q = e.queries(); assert 'sort_m4' in q and not any(n.startswith('op') for n in q) and 'pipeline' not in q; assert e.oracle_sql().keys() <= q.keys()"
    (tmp_path / "__spark_entry__.py").unlink()
    shutil.copy(ROOT / "__spark_entry__.py", tmp_path)
    done = subprocess.run([sys.executable, "-c", code], cwd=tmp_path, capture_output=True, text=True, env={"PYTHONPATH": str(tmp_path), "PATH": "/usr/bin:/bin"})
    assert done.returncode == 0, done.stderr
