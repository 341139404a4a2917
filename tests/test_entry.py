import os
import subprocess
import sys

import duckdb
import pytest

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
SF = "/root/testdata/sf0.001"
needs_tables = pytest.mark.skipif(not os.path.isdir(SF), reason="needs the test tables")


def test_registry_names():
    from graphdrift.plans import registry

    assert set(registry.oracle_sql()) <= set(registry.queries()) and len(registry.queries()) > 100


def test_imports_without_text_operators(tmp_path):
    for name in ("graphdrift", "__spark_entry__.py"):
        os.symlink(f"{ROOT}/{name}", tmp_path / name) if name.endswith(".py") else None
    import shutil

    shutil.copytree(f"{ROOT}/graphdrift", tmp_path / "graphdrift", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    code = "import __spark_entry__ as e; assert e.queries() and not any(n.startswith('op7') for n in e.queries()); e.oracle_sql()"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, env=os.environ | {"PYTHONPATH": str(tmp_path)}, check=True)


@needs_tables
@pytest.mark.parametrize("name", ["custsupp_edges", "weekly_churn", "step_once", "cut_matrix", "apply_changes", "op_as_of_join"])
def test_equals_sql(spark, name):
    from graphdrift.plans import registry

    con = duckdb.connect()
    for f in os.listdir(SF):
        con.sql(f"create view {f.split('.')[0]} as select * from '{SF}/{f}'")
    got = registry.queries()[name](spark, SF)
    columns = ", ".join(f'"{c}"' for c in got.columns)
    want = con.sql(f"select {columns} from ({registry.oracle_sql()[name]})").fetchall()
    assert sorted(map(str, map(tuple, got.collect()))) == sorted(map(str, want))


@needs_tables
def test_entry(spark):
    import __spark_entry__

    rows = __spark_entry__.entry(spark).orderBy("iteration").collect()
    assert [r.iteration for r in rows] == [1, 2, 3] and rows[-1]["cut"] < rows[0]["edges"]
