"""Runs in one task: what they take, and that arrays kept up to date stay those counted afresh."""

import random

import numpy as np
import pytest

from graphdrift.config import MigrationConfig
from graphdrift.operators import initial, replicas
from graphdrift.operators.graph import vertices_of


def cube(side):
    v = np.arange(side**3)
    steps = ((v % side, 1), (v // side % side, side), (v // side**2, side * side))
    src = [v[c < side - 1] for c, _ in steps]
    return v, np.concatenate(src), np.concatenate([a + d for a, (_, d) in zip(src, steps)])


@pytest.mark.parametrize("cfg", [MigrationConfig(k=5), MigrationConfig(k=5, count_self=True), MigrationConfig(k=5, candidate_rule="any", slack=1.02)])
def test_counts_are_kept(cfg, monkeypatch):
    monkeypatch.setattr(replicas, "BLOCK", 50)
    vid, src, dst = cube(9)
    one = replicas.Replica(src, dst, vid, vid % 5, cfg)
    for _ in range(6):
        one.step()
        assert (one.near == one.counts()).all()
        assert one.cut == (one.part[src] != one.part[dst]).sum() == one.rows[-1][5]


def test_bytes_an_edge():
    vid, src, dst = cube(40)
    one = replicas.Replica(src, dst, vid, vid % 9, MigrationConfig())
    held = sum(x.nbytes for x in vars(one).values() if isinstance(x, np.ndarray))
    assert held < 8 * len(src) + 60 * len(vid)
    assert replicas.ONE_TASK_EDGES * 16 < 1e9


def test_a_chunked_stream_in_a_task_is_that_of_rounds(spark, monkeypatch):
    random.seed(4)
    pairs = sorted({tuple(sorted(random.sample(range(30), 2))) for _ in range(70)})
    edges = spark.createDataFrame(pairs, "src long, dst long")
    v = vertices_of(edges)
    jobs = []
    spark.conf.set("spark.sql.shuffle.partitions", "2")
    for rule, chunk, cap in (("dgr", 11, None), ("mnn", 16, 5)):
        place = lambda: sorted(map(tuple, initial.stream_chunked(edges, v, 3, rule, chunk, cap).collect()))  # noqa: B023, E731
        monkeypatch.setattr(initial, "streams", lambda e: True)
        spark.sparkContext.setJobGroup(f"task-{rule}-{chunk}", "")
        one = place()
        jobs.append(len(spark.sparkContext.statusTracker().getJobIdsForGroup(f"task-{rule}-{chunk}")))
        monkeypatch.setattr(initial, "streams", lambda e: False)
        spark.sparkContext.setJobGroup("rounds", "")
        assert one == place(), (rule, chunk, cap)
    spark.conf.set("spark.sql.shuffle.partitions", "8")
    assert max(jobs) < 15  # however many chunks there are


def test_sums_follow_the_movers():
    """What an iteration reports is kept up to date from the movers, not summed over all vertices."""
    rng = np.random.default_rng(5)
    src, dst = rng.integers(0, 4000, (2, 12000))
    vid = np.arange(4000)
    for deferred in (False, True):
        run = replicas.Replica(src, dst, vid, vid % 7, MigrationConfig(k=7, deferred=deferred))
        for _ in range(25):
            run.step()
            assert run.loads.tolist() == np.bincount(run.part, minlength=7).tolist()
            assert (run.told, run.kept) == (run.others.sum(), run.own.sum()) and (run.near == run.counts()).all()


def test_runs_by_rules_send_edges_alone(spark, monkeypatch):
    """A task finds the ids at its edges' ends: no frame of vertices is made or sent."""
    pairs = [(7, 2**40), (7, 9), (9, 30), (-4, 30)]
    edges = spark.createDataFrame(pairs, "src long, dst long")
    sent, packed = [], replicas.packed
    monkeypatch.setattr(replicas, "packed", lambda rows, tasks, kind: sent.append(kind) or packed(rows, tasks, kind))
    cfg = MigrationConfig(k=3)
    start = initial.assign_hash(vertices_of(edges), 3, True, cfg.seed)
    got, want = (replicas.adapt_many(edges, {0: s}, {0: cfg}, 3)[1].drop("step_ms").orderBy("iteration").collect() for s in ("hsh_mixed", start))
    assert got == want and sent == [replicas.EDGE, replicas.EDGE, 0]
    for gap in (1, 1000):
        ends = np.array([5, 3, 3, 9, 5]) * gap
        assert replicas.ids_of(ends.astype(np.uint64)).tolist() == [3 * gap, 5 * gap, 9 * gap]
