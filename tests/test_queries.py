"""Driver queries against their DuckDB twins on the smallest tables, the entry point, and the guard of the subpackage."""

import datetime
import glob
import os
import subprocess
import sys

import pytest

from contrastmine.plans.queries import ORACLE_SQL, QUERIES

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
PICK = sorted(n for n in QUERIES if n in ORACLE_SQL)


def plain(v):
    if isinstance(v, float):
        return round(v, 6)
    if isinstance(v, datetime.datetime):
        return v.replace(tzinfo=None).isoformat()
    return tuple(map(plain, v)) if isinstance(v, (list, tuple)) else v


@pytest.fixture(scope="module")
def duck(sf):
    import duckdb

    con = duckdb.connect()
    con.execute("set TimeZone = 'UTC'")
    for p in glob.glob(f"{sf}/*.parquet"):
        con.execute(f"create view {os.path.basename(p)[:-8]} as select * from '{p}'")
    return con


@pytest.mark.parametrize("name", PICK)
def test_query_equals_twin(spark, duck, sf, name):
    df = QUERIES[name](spark, sf)
    columns = sorted(df.columns)
    got = sorted(repr(tuple(plain(r[c]) for c in columns)) for r in df.collect())
    cur = duck.execute(ORACLE_SQL[name])
    names = [d[0] for d in cur.description]
    want = sorted(repr(tuple(plain(r[names.index(c)]) for c in columns)) for r in cur.fetchall())
    assert len(names) == len(columns) and got == want


def test_entry(spark):
    import __spark_entry__ as e

    assert {r.pattern_text for r in e.entry(spark).collect()} >= {"junk"}
    assert set(e.oracle_sql()) <= set(e.queries())


def test_everything_works_without_the_subpackage(tmp_path):
    """The driver deletes the training-data operators: the entry must still import and give the other queries."""
    import shutil

    copy = tmp_path / "repo"
    shutil.copytree(ROOT, copy, ignore=shutil.ignore_patterns(".git", "llm", "corpus_pipeline.py", "__pycache__", ".pytest_cache"))
    code = "import __spark_entry__ as e; q = e.queries(); assert 'sjep_docs' in q and not any(n.startswith('op') and n[2].isdigit() for n in q) and 'pipeline' not in q and set(e.oracle_sql()) <= set(q)"
    subprocess.run([sys.executable, "-c", code], cwd=copy, check=True, env=os.environ | {"PYTHONPATH": str(copy)}, timeout=120)


def test_executors_need_no_copy_of_the_package(tmp_path):
    """Python workers that cannot import the package: its functions must travel with the tasks, table function included."""
    code = f"""
import sys
sys.path.insert(0, {ROOT!r})
from pyspark.sql import SparkSession
spark = SparkSession.builder.master("local[2]").config("spark.sql.shuffle.partitions", "2").config("spark.ui.enabled", "false").config("spark.checkpoint.dir", {str(tmp_path)!r}).getOrCreate()
from contrastmine.functions.measures import register_table_function
from contrastmine.plans.queries import QUERIES
for name in ("engine_local", "engine_hybrid", "engine_matrix_linked", "engine_matrix_bitset", "zdd_sjep", "prefix_tree_sjep", "closed_dfs_jep", "matrix_linked_vs_bitset"):
    assert QUERIES[name](spark, "/root/testdata/sf0.001").count() >= 0, name
register_table_function(spark)
spark.createDataFrame([([0, 1], 1), ([0], 0)], "items array<int>, label int").coalesce(1).createOrReplaceTempView("t")
assert [r.pattern for r in spark.sql("select * from mine_patterns(table(t), 1, 0, 2.0D, 0.0D, 2, -1, false)").collect()] == [[1]]
"""
    env = {k: v for k, v in os.environ.items() if k != "PYTHONPATH"}
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env=env, timeout=300)
