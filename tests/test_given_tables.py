"""Queries whose data were made up read a given table now."""

import os

import duckdb
import pytest

SF = "/root/testdata/sf0.001"
pytestmark = pytest.mark.skipif(not os.path.isdir(SF), reason="needs the test tables")


def files_of(frame):
    return {os.path.basename(f) for f in frame.inputFiles()}


@pytest.mark.parametrize(("name", "given"), [("lattice3d_graph", "orders"), ("op_data_source", "orders"), ("op_recursion", "orders"), ("op_udtf", "customer")])
def test_reads_a_table_and_equals_sql(spark, name, given):
    from graphdrift.plans import registry

    con = duckdb.connect()
    for f in os.listdir(SF):
        con.sql(f"create view {f.split('.')[0]} as select * from '{SF}/{f}'")
    got = registry.queries()[name](spark, SF)
    assert f"{given}.parquet" in files_of(got) or f"{given}.parquet" in got._jdf.queryExecution().toString()
    want = con.sql(f"select {', '.join(got.columns)} from ({registry.oracle_sql()[name]})").fetchall()
    rows = sorted(map(tuple, got.collect()))
    assert rows and rows == sorted(want)


def test_power_law_of_a_table(spark):
    from graphdrift.plans import registry
    from graphdrift.sources import generators

    ids = {r[0] for r in spark.read.parquet(f"{SF}/customer.parquet").select("c_custkey").collect()}
    got = registry.queries()["powerlaw_graph"](spark, SF).collect()
    assert {v for r in got for v in r} == ids
    numbers = sorted(ids)
    plain = generators.powerlaw_clustered(spark, len(ids), 5).collect()
    assert sorted(map(tuple, got)) == sorted((numbers[a], numbers[b]) for a, b in plain)
