"""Cliques of every week's window, whatever the dates."""

import datetime

from graphdrift.plans import registry, workloads


def test_cliques_of_each_week(spark, monkeypatch):
    spark.conf.set("spark.sql.shuffle.partitions", "2")
    first, second = datetime.datetime(2031, 3, 4, 9), datetime.datetime(2031, 3, 12, 9)
    calls = [(first, a, b) for a, b in ((9, 10), (10, 100), (100, 9), (100, 7))] + [(second, a, b) for a, b in ((9, 10), (7, 8), (8, 9), (7, 9))]
    monkeypatch.setattr(workloads, "interactions", lambda s, d: s.createDataFrame(calls, "ts timestamp, src long, dst long").coalesce(1))
    rows = registry.queries()["w7_cliques"](spark, "").collect()
    spark.conf.set("spark.sql.shuffle.partitions", "8")
    got = {(str(r.week_end)[:10], r.vid): (r["size"], r.members) for r in rows}
    assert got == {
        ("2031-03-10", 7): (2, "7,100"), ("2031-03-10", 9): (3, "9,10,100"), ("2031-03-10", 10): (2, "10,100"), ("2031-03-10", 100): (1, "100"),
        ("2031-03-17", 7): (3, "7,8,9"), ("2031-03-17", 8): (2, "8,9"), ("2031-03-17", 9): (2, "9,10"), ("2031-03-17", 10): (1, "10"),
    }
