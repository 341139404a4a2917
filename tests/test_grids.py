"""The experiment grids are those of SURVEY 2.6."""

from itertools import product

import pytest

from graphdrift.plans import registry, workloads

HISTORY = "iteration int, proposed long, damped long, refused long, moved long, cut long, edges long, max_load long, min_load long, step_ms long"
PAIRS = [(i, i + 1) for i in range(40)]


@pytest.fixture
def runs(spark, monkeypatch):
    """Sweeps asked for, as (graph, labels of starts, configs, steps); none is run."""
    asked, at = [], {}

    def graph(s, d, name):
        at["graph"] = name
        return s.createDataFrame(PAIRS, "src long, dst long").coalesce(1)

    def many(edges, starts, cfgs, steps):
        asked.append((at["graph"], [n for n, _ in starts or ()], cfgs, steps))
        rows = [(n, i, 0, 0, 0, 2 if i == 1 else 0, 10 + c.seed - i, 20, 1, 1, 18, True) for n, c in cfgs.items() for i in (1, 2)]
        return spark.createDataFrame(rows, "label string, " + HISTORY.replace("step_ms", "remote") + ", quiet boolean")

    monkeypatch.setattr(workloads, "graph_from", graph)
    monkeypatch.setattr(workloads, "many", many)
    return asked


@pytest.mark.parametrize("name,graph", [("w2_s_sweep", "lattice"), ("w2_s_sweep_powerlaw", "copurchase")])
def test_w2(spark, runs, name, graph):
    got = registry.queries()[name](spark, "")
    ((on, _, cfgs, steps),) = runs
    assert sorted((on, c.s, c.seed, steps) for c in cfgs.values()) == sorted((graph, s, seed, None) for s, seed in product((0.1, 0.25, 0.5, 0.75, 0.9, 1.0), range(10)))
    assert {(r.s_percent, r.seed) for r in got.collect()} == set(product((10, 25, 50, 75, 90, 100), range(10)))


def test_spread_over_seeds(spark):
    rows = [(25, seed, i, 2 - i, 10 + seed - i) for seed in (0, 1) for i in (1, 2)]
    got = workloads.sweep_spread(spark.createDataFrame(rows, "s_percent int, seed int, iteration int, moved long, cut long")).collect()
    assert {r.value: (r["mean"], round(r["std"], 6), r.runs) for r in got} == {"cut": (8.5, 0.707107, 2), "moves": (1.0, 0.0, 2), "last_move": (1.0, 0.0, 2)}


@pytest.mark.parametrize("name,kinds", [("w3_initial_quality", {"hsh_mixed", "rnd"}), ("w3_initial_quality_stream", {"dgr", "mnn", "mnn_literal"})])
def test_w3(spark, runs, name, kinds):
    got = registry.queries()[name](spark, "").collect()
    graphs = {"lattice", "knn", "copurchase", "custsupp", "cop", "pagelinks", "succession"}
    assert {(g, *n.split(":"), c.seed) for g, names, cfgs, _ in runs for n, c in cfgs.items()} == {(g, k, str(i), i) for g, k, i in product(graphs, kinds, range(10))}
    assert all(set(names) == set(cfgs) and steps is None for _, names, cfgs, steps in runs)
    assert all((r.before, r.after, r.moves, r.last_move, r.quiet) == (9, 8 + r.seed, 2, 1, True) for r in got)


def test_w5(spark, monkeypatch):
    asked = []

    def adapt(edges, state, cfg, steps):
        asked.append((edges.count(), steps))
        return state, spark.createDataFrame([(1, 0, 0, 0, 0, 1, edges.count(), 1, 1, 7)], HISTORY)

    def graph(s, d, name):
        assert name == "cop"
        return s.createDataFrame(PAIRS, "src long, dst long").coalesce(1)

    monkeypatch.setattr(workloads, "graph_from", graph)
    monkeypatch.setattr(workloads, "to_quiet", adapt)
    burnt = []
    monkeypatch.setattr(workloads.generators, "forest_fire", lambda e, n, **more: burnt.append((n, more)) or spark.createDataFrame([(0, 100 + len(burnt))], "src long, dst long"))
    monkeypatch.setattr(workloads, "diameter_sweep", lambda e: spark.createDataFrame([(e.count(),)], "lower_bound int"))
    rows = registry.queries()["w5_bursts_adaptive"](spark, "").orderBy("phase").collect()
    assert asked == [(40, 50), (41, 50), (42, 50), (43, 50), (44, 50)] and len(burnt) == 4 and all(set(m) == {"seed"} for _, m in burnt)
    assert [(r.phase, r.step_ms, r.diameter) for r in rows] == [(0, 7, 40), (1, 7, 41), (2, 7, 42), (3, 7, 43), (4, 7, 44)]
