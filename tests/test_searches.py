"""The array searches against the distributed ones, which they stand for where a graph fits in a task."""

import random

import pytest

from graphdrift.operators import apps, search
from graphdrift.sources import generators

PAIRS = sorted({tuple(sorted(random.Random(i).sample(range(120), 2))) for i in range(150)}) + [(200 + i, 201 + i) for i in range(9)]


@pytest.fixture
def edges(spark):
    return spark.createDataFrame(PAIRS, "src long, dst long").cache()


def by_loop(monkeypatch, make):
    """What the distributed search gives."""
    with monkeypatch.context() as m:
        m.setattr(apps, "fits", lambda e: False)
        m.setattr(generators, "fits", lambda e: False)
        return sorted(map(tuple, make().collect()))


def by_arrays(monkeypatch, make):
    """What the arrays give; a search over frames would fail."""
    with monkeypatch.context() as m:
        m.setattr(apps, "symmetric", None)
        m.setattr(generators, "symmetric", None)
        return sorted(map(tuple, make().collect()))


@pytest.mark.parametrize("find", [apps.diameter_exact, apps.diameter_sweep])
def test_diameters(spark, edges, monkeypatch, find):
    assert by_arrays(monkeypatch, lambda: find(edges)) == by_loop(monkeypatch, lambda: find(edges))


def test_roots_in_more_than_one_word_and_round(edges, monkeypatch):
    monkeypatch.setattr(search, "WORDS", 1)
    graph = search.Graph(search.np.unique(search.np.array(PAIRS)), search.np.array(PAIRS).T.ravel().astype(search.np.uint64).copy())
    far = [search.levels(graph, r).max() for r in range(len(graph.vid))]
    assert search.eccentricities(graph, search.np.arange(len(graph.vid))).tolist() == far
    assert max(search.diameter(graph, t, 3) for t in range(3)) == max(far)


@pytest.mark.parametrize("size", [5, 130])
def test_fire(edges, monkeypatch, size):
    def burn():
        return generators.forest_fire(edges, size, 0.5, 3, 2)

    assert by_arrays(monkeypatch, burn) == by_loop(monkeypatch, burn)


def test_no_edges(spark):
    assert apps.diameter_exact(spark.createDataFrame([], "src long, dst long")).first()[0] == 0
    assert generators.forest_fire(spark.createDataFrame([], "src long, dst long"), 3).count() == 0
