"""Supersteps bring states to the cached arcs; the arcs are not shuffled."""

import pytest
from pyspark.sql import functions as F

from graphdrift.config import MigrationConfig
from graphdrift.functions import lineage
from graphdrift.operators import engine, migrate
from graphdrift.operators.graph import vertices_of
from graphdrift.operators.initial import assign_hash

PAIRS = [(0, i) for i in range(1, 9)] + [(1, 2), (2, 9), (4, 9), (4, 5)]


@pytest.fixture
def edges(spark):
    spark.conf.set("spark.sql.shuffle.partitions", "2")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    yield spark.createDataFrame(PAIRS, "src long, dst long")
    spark.conf.set("spark.sql.shuffle.partitions", "8")
    spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def exchanges(frame):
    """Those that joins and sums ask for; the one before the cache is not among them."""
    return frame.select("*")._jdf.queryExecution().executedPlan().toString().count("ENSURE_REQUIREMENTS")


@pytest.mark.parametrize("hub", [1_000_000, 3])
def test_arcs_are_read_where_they_are_cached(edges, monkeypatch, hub):
    monkeypatch.setattr(migrate, "HUB_ARCS", hub)
    run = migrate.Adaptation.start(edges, assign_hash(vertices_of(edges), 3), MigrationConfig(k=3))
    assert (run.hubs is None) == (hub > 8)
    program = engine.reach_program()
    values = lineage.cut(run.state.select("vid", F.col("home").alias("part")).withColumn("value", program.init))
    messages = [engine.combine_messages(engine.local_and_remote(*how), program) for how in ((run.outward, values, program, run), (run.sym, values, program))]
    got, want = (sorted(map(tuple, m.collect())) for m in messages)
    assert got == want and sum(r[-1] for r in got) == 2 * len(PAIRS)
    # the state's own, and then one by the vertex
    assert exchanges(run.beside_arcs(run.sym, run.state.select(F.col("vid").alias("dst"), "part"), "dst")) <= 1
    assert exchanges(run._counted()) <= 2
    # what is told, the messages, the places
    assert exchanges(messages[0]) <= 3 < exchanges(messages[1]) + 1
    run.close()


def test_a_cut_frame_leaves_no_shuffle_files(spark, monkeypatch):
    seen, key = [], "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(key)
    frame = spark.range(100).groupBy((F.col("id") % 7).alias("k")).count()
    watched = frame.select("*")
    monkeypatch.setattr(type(watched), "checkpoint", lambda df, eager=True: seen.append(spark.conf.get(key)) or df)
    lineage.cut(frame)
    assert seen == ["true"] and spark.conf.get(key) == before
