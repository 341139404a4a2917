"""Queries that take all ids, not a low range of them."""

from collections import Counter

import pytest

from graphdrift.plans import registry


def stream(pairs, k, rule):
    """Each vertex in id order, by the rule's score; full parts are closed."""
    ids = sorted({v for p in pairs for v in p})
    cap, place = -(-len(ids) // k), {}
    for v in ids:
        load = [sum(p == i for p in place.values()) for i in range(k)]
        near = Counter(place[x] for a, b in pairs for x in ((b,) if a == v else (a,) if b == v else ()) if x in place)
        score = {"dgr": lambda i: near[i] * (cap - load[i]), "mnn": lambda i: near[i] - load[i], "mnn_literal": lambda i: -near[i]}[rule]
        place[v] = min(range(k), key=lambda i: (load[i] >= cap, -score(i), load[i], i))
    return place


@pytest.mark.parametrize("rule", ["dgr", "mnn", "mnn_literal"])
def test_stream_rules_place_every_vertex(spark, monkeypatch, rule):
    pairs = sorted({(min(a, b), max(a, b)) for i in range(90) for a, b in ((i, (7 * i + 3) % 90), (i, (i * i + 1) % 90)) if a != b})
    monkeypatch.setattr(registry, "graph_from", lambda s, d, name: s.createDataFrame(pairs, "src long, dst long"))
    got = {r.vid: r.part for r in registry.queries()[f"assign_{rule}"](spark, "").collect()}
    assert max(got) > 60 and got == stream(pairs, 3, rule)


def test_ranges_reach_the_largest_key(spark, tmp_path):
    keys = [0, 5, 62, 63, 64, 6399, 6400, 6462, 6463, 100_000]
    spark.createDataFrame([(x,) for x in keys], "o_orderkey long").write.parquet(f"{tmp_path}/orders.parquet")
    got = {r.lo: r.n for r in registry.queries()["op_range_join"](spark, str(tmp_path)).collect()}
    assert got == Counter(x - x % 64 for x in keys if x % 64 < 63)
