"""Streams of vertices by one task: the sequential rules, also above the bound of the chunked form."""

import random

import pytest

from graphdrift.config import MigrationConfig
from graphdrift.operators import initial, replicas
from graphdrift.operators.graph import vertices_of
from graphdrift.plans import workloads


def one_by_one(pairs, vids, k, rule, cap):
    near_to, place, load = {v: [] for v in vids}, {}, [0] * k
    for a, b in pairs:
        near_to.setdefault(a, []).append(b)
        near_to.setdefault(b, []).append(a)
    for v in vids:
        near = [sum(place.get(x) == i for x in near_to[v]) for i in range(k)]
        score = {"dgr": lambda i: near[i] * (cap - load[i]), "mnn": lambda i: near[i] - load[i], "mnn_literal": lambda i: -near[i]}[rule]  # noqa: B023
        room = [i for i in range(k) if load[i] < cap] or range(k)
        place[v] = max(room, key=lambda i: (score(i), -load[i], -i))  # noqa: B023
        load[place[v]] += 1
    return sorted(place.items())


@pytest.mark.parametrize("rule", ["dgr", "mnn", "mnn_literal"])
def test_a_stream_above_the_chunked_bound_is_exact(spark, monkeypatch, rule):
    random.seed(6)
    pairs = sorted({tuple(sorted(random.sample(range(-20, 400, 3), 2))) for _ in range(300)})
    edges = spark.createDataFrame(pairs, "src long, dst long")
    v = vertices_of(edges)
    vids = sorted({x for p in pairs for x in p})
    monkeypatch.setattr(initial, "STRETCH", 13)
    monkeypatch.setattr(replicas, "STREAM_EDGES", 0)
    got = workloads.start_of(edges, v, MigrationConfig(k=4), rule)
    assert sorted(map(tuple, got.collect())) == one_by_one(pairs, vids, 4, rule, -(-len(vids) // 4))
    some = vids[::2] + [9999]  # ends outside the stream are no neighbours, and a lone vertex is placed too
    got = initial.stream_exact(edges, spark.createDataFrame([(x,) for x in some], "vid long"), 4, rule, cap=5)
    inside = [p for p in pairs if p[0] in some and p[1] in some]
    assert sorted(map(tuple, got.collect())) == one_by_one(inside, some, 4, rule, 5)
    assert initial.stream_exact(edges.limit(0), v.limit(0), 4, rule).count() == 0
