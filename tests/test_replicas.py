"""Runs as one task each equal the distributed loop, for every setting of the heuristic."""

import random

import numpy as np
import pytest

from graphdrift.config import MigrationConfig
from graphdrift.operators import initial, replicas
from graphdrift.operators.graph import vertices_of
from graphdrift.operators.migrate import adapt

BASE = MigrationConfig(k=4, slack=1.05)
SETTINGS = {
    "base": BASE, "all": BASE.but(s=1.0), "none": BASE.but(s=0.0), "self": BASE.but(count_self=True), "any": BASE.but(candidate_rule="any"), "lowest": BASE.but(tie_break="lowest"),
    "hash": BASE.but(admission="hash"), "drop": BASE.but(quota_remainder="drop"), "open": BASE.but(use_quota=False), "deferred": BASE.but(deferred=True, s=0.8), "caps": BASE.but(caps=(40, 30, 9, 60)),
    "one": BASE.but(k=1), "many": BASE.but(k=70), "static": BASE.but(adaptive=False), "seed": BASE.but(seed=5),
}


@pytest.fixture(scope="module")
def graph(spark):
    random.seed(3)
    pairs = {tuple(sorted(random.sample(range(40), 2))) for _ in range(90)} | {(0, v) for v in range(1, 25)}
    return spark.createDataFrame(sorted(pairs), "src long, dst long")


def test_hubs_in_pieces(spark, graph, monkeypatch):
    monkeypatch.setattr("graphdrift.operators.migrate.HUB_ARCS", 4)
    spark.conf.set("spark.sql.shuffle.partitions", "3")
    start = initial.assign_hash(vertices_of(graph), 4, True, 0)
    state, _ = adapt(graph, start, BASE, 3)
    states, _ = replicas.adapt_many(graph, start.selectExpr("7 run", "*"), {7: BASE}, 3)
    assert sorted(map(tuple, states.select("vid", "part").collect())) == sorted(map(tuple, state.select("vid", "part").collect()))
    spark.conf.set("spark.sql.shuffle.partitions", "8")


@pytest.mark.parametrize("name", SETTINGS)
def test_equals_the_distributed_loop(spark, graph, name):
    cfg = SETTINGS[name]
    spark.conf.set("spark.sql.shuffle.partitions", "2")
    start = initial.assign_hash(vertices_of(graph), cfg.k, True, cfg.seed)
    state, history = adapt(graph, start, cfg, 4)
    states, histories = replicas.adapt_many(graph, start.selectExpr("7 run", "*"), {7: cfg}, 4)
    want = [tuple(r) for r in history.orderBy("iteration").drop("step_ms").collect()]
    got = [tuple(r) for r in histories.orderBy("iteration").select(history.drop("step_ms").columns).collect()]
    assert got == want
    key = ["vid", "part", "home", "settle"]
    assert sorted(map(tuple, states.select(key).collect())) == sorted(map(tuple, state.select(key).collect()))
    spark.conf.set("spark.sql.shuffle.partitions", "8")


def test_rules_are_the_placements(spark, graph):
    ids = sorted(r.vid for r in vertices_of(graph).collect())
    v = spark.createDataFrame([(i,) for i in ids], "vid long")
    spark.conf.set("spark.sql.shuffle.partitions", "2")
    for rule, want in {"hsh": initial.assign_hash(v, 4, False, 3), "hsh_mixed": initial.assign_hash(v, 4, True, 3), "rnd": initial.assign_random(v, 4, 3)}.items():
        assert replicas.placed(rule, np.array(ids), 4, 3).tolist() == [r.part for r in want.orderBy("vid").collect()], rule
    spark.conf.set("spark.sql.shuffle.partitions", "8")


def test_a_sweep_sends_the_edges_once_a_task(spark, graph, monkeypatch):
    sent, packed = [], replicas.packed
    monkeypatch.setattr(replicas, "packed", lambda rows, tasks, kind: sent.append((kind, len(tasks))) or packed(rows, tasks, kind))
    spark.conf.set("spark.sql.shuffle.partitions", "2")
    runs = {i: BASE.but(seed=i) for i in range(20)}
    start = initial.assign_hash(vertices_of(graph), 4, True, 19)
    none, histories = replicas.adapt_many(graph, {i: start if i > 17 else "hsh_mixed" for i in runs}, runs, 3)
    assert none is None and dict(sent) == {replicas.EDGE: 8, replicas.VERTEX: 8, 0: 2} and len(sent) == 3
    want = adapt(graph, start, runs[19], 3)[1].orderBy("iteration").drop("step_ms")
    got = histories.where("run = 19").orderBy("iteration").select(want.columns)
    assert [tuple(r) for r in got.collect()] == [tuple(r) for r in want.collect()] and histories.count() == 60
    spark.conf.set("spark.sql.shuffle.partitions", "8")
