"""Registered workloads adapt until nothing moves: compared with a loop in plain Python."""

from collections import Counter

import pytest

from graphdrift.config import MigrationConfig
from graphdrift.functions.hashing import ADMIT, COIN, FACTOR, MASK, PLACE, TIE
from graphdrift.operators import replicas
from graphdrift.plans import registry, workloads


def mixed(x, seed, use, t=0, part=0):
    v = (((x ^ (x >> 32)) & MASK) + seed * 7919 + use * 15485863 + t * 104729 + part * 1299709) & MASK
    for _ in range(2):
        v = ((v >> 16 ^ v) * FACTOR) & MASK
    return v >> 16 ^ v


def brute(pairs, cfg):
    """(moved, cut left) of each iteration until more than cfg.patience in a row move nothing."""
    near = {}
    for a, b in pairs:
        near.setdefault(a, []).append(b)
        near.setdefault(b, []).append(a)
    k, place = cfg.k, {v: mixed(v, cfg.seed, PLACE) % cfg.k for v in near}
    load = Counter(place.values())
    cap = max(-(-len(place) * round(cfg.slack * 100) // (100 * k)), *load.values())
    out, still, t = [], 0, 0
    while still <= cfg.patience:
        t += 1
        wants = {}
        for v, others in near.items():
            n = Counter(place[x] for x in others)
            n.setdefault(place[v], 0)
            best = max(n, key=lambda p: (n[p], p == place[v], mixed(v, cfg.seed, TIE, t, p), -p))
            if best != place[v] and mixed(v, cfg.seed, COIN, t) < cfg.s * 2**32:
                wants.setdefault((place[v], best), []).append((-(n[best] - n[place[v]]), mixed(v, cfg.seed, ADMIT, t), v))
        moves = {}
        for (i, j), rows in wants.items():
            room = max(0, cap - load[j])
            turn = ((i if i < j else i - 1) - t) % (k - 1)
            for *_, v in sorted(rows)[: room // (k - 1) + (turn < room % (k - 1))]:
                moves[v] = j
        place |= moves
        load = Counter(place.values())
        still = 0 if moves else still + 1
        out.append((len(moves), sum(place[a] != place[b] for a, b in pairs)))
    return out


PAIRS = [(x + 4 * y, x + 4 * y + d) for x in range(4) for y in range(4) for d, ok in ((1, x < 3), (4, y < 3)) if ok]

CFG = MigrationConfig(k=4, patience=1)


@pytest.fixture
def small(spark, monkeypatch):
    spark.conf.set("spark.sql.shuffle.partitions", "2")
    monkeypatch.setattr(registry, "_ONE", CFG)
    monkeypatch.setattr(workloads, "graph_from", lambda s, d, name: s.createDataFrame(PAIRS, "src long, dst long"))
    yield spark
    spark.conf.set("spark.sql.shuffle.partitions", "8")


def test_w4_runs_to_quiescence(small):
    want = brute(PAIRS, CFG)
    rows = registry.queries()["w4_convergence"](small, "").orderBy("iteration").collect()
    assert [(r.moved, r["cut"]) for r in rows] == want and len(rows) > 4 and all(r.quiet for r in rows)


def test_a_run_that_meets_its_bound_says_so(small, monkeypatch):
    monkeypatch.setattr(workloads, "MAX_ITER", 2)
    with pytest.warns(UserWarning, match="not quiet after 2"):
        rows = registry.queries()["w4_convergence"](small, "").collect()
    assert len(rows) == 2 and not any(r.quiet for r in rows)


@pytest.mark.parametrize("name,runs", [("adapt_history", 1), ("w9_ablation", 8), ("w10_scale", 5), ("w2_s_sweep", 60)])
def test_no_step_count(spark, monkeypatch, name, runs):
    asked = []

    def seen(edges, starts, cfgs, iterations=None):
        asked.append((iterations, len(cfgs)))
        cells = ", ".join(f"{c} {'int' if c == 'iteration' else 'long'}" for c in replicas.COLUMNS)
        return starts, spark.createDataFrame([(0, 1, *[0] * (len(replicas.COLUMNS) - 1), True)], f"run int, {cells}, quiet boolean")

    monkeypatch.setattr(workloads, "graph_from", lambda s, d, name: s.createDataFrame(PAIRS, "src long, dst long"))
    monkeypatch.setattr(workloads.replicas, "adapt_many", seen)
    registry.queries()[name](spark, "").collect()
    assert asked == [(None, runs)]


def test_beyond_one_task_the_loop_is_distributed(small, monkeypatch):
    monkeypatch.setattr(workloads.replicas, "ONE_TASK_EDGES", 0)
    rows = registry.queries()["w4_convergence"](small, "").orderBy("iteration").collect()
    assert [(r.moved, r["cut"]) for r in rows] == brute(PAIRS, CFG) and all(r.quiet for r in rows)
