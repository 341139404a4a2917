"""Runs on the slices of a growing graph, as tasks that take it once, equal a run a slice."""

import random

import pytest

from graphdrift.operators import replicas
from graphdrift.plans import workloads


@pytest.mark.parametrize("strategy", ["adp", "scratch"])
def test_equals_a_run_a_slice(spark, monkeypatch, strategy):
    random.seed(8)
    pairs = sorted({tuple(sorted(random.sample(range(90), 2))) for _ in range(300)})
    # the first slice and one between are without ties, and some ties are older than the first
    ties = spark.createDataFrame([(a, b, s) for i, (a, b) in enumerate(pairs) for s in [(-1, 1, 3, 4)[i % 4 if i > 40 else 3]]], "src long, dst long, slice int").cache()
    monkeypatch.setattr(workloads, "call_ties", lambda s, d, days=10: (ties, 6))
    side_by_side = [tuple(r) for r in workloads.drift(spark, "", strategy, 4).orderBy("slice").collect()]
    asked = []
    monkeypatch.setattr(replicas, "fits", lambda e: asked.append(1) or len(asked) > 1)
    each = [tuple(r) for r in workloads.drift(spark, "", strategy, 4).orderBy("slice").collect()]
    assert len(asked) > 1 and side_by_side == each and len(each) == 6


def test_first_slices_without_ties(spark, monkeypatch):
    ties = spark.createDataFrame([(1, 2, 2), (2, 3, 2)], "src long, dst long, slice int")
    monkeypatch.setattr(workloads, "call_ties", lambda s, d, days=10: (ties, 3))
    for strategy in ("adp", "scratch"):
        rows = [tuple(r) for r in workloads.drift(spark, "", strategy, 2).orderBy("slice").collect()]
        assert [r[2] for r in rows] == [0, 0, 2] and [r[1] for r in rows[:2]] == [0, 0]
