"""Edges that the tasks of runs side by side read packed from the shared folder."""

import numpy as np
import pytest

from graphdrift.config import MigrationConfig
from graphdrift.operators import replicas

PAIRS = [(1, 2), (2, 9), (1, 9), (4, 9), (4, 5)]


def pairs_of(spark, gap=1, low=0):
    return spark.createDataFrame([(a * gap + low, b * gap + low) for a, b in PAIRS], "src long, dst long")


@pytest.mark.parametrize("gap,low", [(1, 0), (1000, -4), (2**40, -(2**41))])
def test_what_is_held_comes_back(spark, monkeypatch, gap, low):
    monkeypatch.setattr(replicas, "PAIRS", 2)
    held = replicas.hold(pairs_of(spark, gap, low))
    assert (held.size, held.low, held.high) == (5, gap + low, 9 * gap + low) and held.narrow == (gap < 2**40)
    assert sorted(map(tuple, held.frame().collect())) == sorted(map(tuple, pairs_of(spark, gap, low).collect()))
    none = replicas.hold(pairs_of(spark).where("src < 0"))
    assert none.size == 0 and none.fits and none.frame().count() == 0


def test_tasks_read_the_edges_without_a_shuffle(spark, monkeypatch):
    held, plans, cut = replicas.hold(pairs_of(spark)), [], replicas.cut
    monkeypatch.setattr(replicas, "cut", lambda df: plans.append((df._jdf.queryExecution().executedPlan().toString(), df.rdd.getNumPartitions())) or cut(df))
    runs = {i: MigrationConfig(k=3, seed=i) for i in range(5)}
    found = replicas.adapt_many(held, dict.fromkeys(runs, "hsh_mixed"), runs, 2)[1]
    assert found.count() == 10 and len(plans) == 1
    assert "Exchange" not in plans[0][0] and plans[0][1] == 5


@pytest.mark.parametrize("gap,low", [(1, 0), (7, -4), (100_000, 5)])
def test_a_graph_of_short_pairs_is_that_of_ids(monkeypatch, gap, low):
    monkeypatch.setattr(replicas, "BLOCK", 37)
    rng = np.random.default_rng(3)
    ends = np.unique(np.sort(rng.integers(0, 90, (400, 2)), axis=1), axis=0)
    ends = rng.permutation(ends[ends[:, 0] < ends[:, 1]]) * gap + low
    src, dst = ends.T
    first = int(ends.min())
    both = np.concatenate([src, dst]).astype(np.uint64)
    one = replicas.Graph(replicas.ids_of(both), both)
    two = replicas.Graph.of_pairs((src - first).astype(np.uint64) << np.uint64(32) | (dst - first).astype(np.uint64), first)
    assert (one.vid == two.vid).all() and (one.first == two.first).all() and (one.near_to == two.near_to).all()


def test_graphs_of_the_gigabyte_fit():
    """Customers, orders and parts; parts bought together: both were beyond the bound."""
    assert replicas.fits(replicas.Held(None, 44_996_100, 0, 11_100_000))
    assert replicas.fits(replicas.Held(None, 71_760_000, 0, 1_200_000))
    assert not replicas.fits(replicas.Held(None, 71_760_000, 0, 2**32))
    assert not replicas.fits(replicas.Held(None, 90_000_000, 0, 1_200_000))
    assert replicas.ONE_TASK_EDGES * 4 // 3 * 12 < 1e9
