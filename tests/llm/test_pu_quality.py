import os
import zlib

import numpy as np
import pytest

from graphdrift.llm import pu_quality as m

SF = "/root/testdata/sf0.1"


def test_prior_and_risk():
    rng = np.random.default_rng(0)
    p, u = rng.normal(2, 1, (3000, 3)), np.vstack([rng.normal(2, 1, (4200, 3)), rng.normal(-2, 1, (1800, 3))])
    model = m.fit(p, u, np.zeros((0, 3)))
    assert abs(model.prior - 0.7) < 0.08
    good, bad = model.score(rng.normal(2, 1, (1000, 3))), model.score(rng.normal(-2, 1, (1000, 3)))
    assert (good > 0.5).mean() > 0.97 and (bad > 0.5).mean() < 0.05
    assert m.risk(np.array([9.0]), np.array([-9.0]), 0.5)[1] < 0  # what the bound at zero is for
    assert m.fit(np.zeros((0, 3)), u, u) is None


def test_long_text_features():
    t = b"ab c\n" * 50
    assert np.allclose(m.features([t, b"", t], block=64), m.features([t, b"", t]))


@pytest.mark.skipif(not os.path.isdir(SF), reason="needs the test tables")
def test_held_out_accuracy(spark):
    docs, labels = (spark.read.parquet(f"{SF}/{t}.parquet") for t in ("documents", "labels"))
    got = {r.doc_id: r for r in m.quality_scores(docs, labels).collect()}
    assert len(got) == docs.count()
    truth = {r.doc_id: r.quality for r in labels.collect()}
    held = [(got[i], y) for i, y in truth.items() if zlib.crc32(str(i).encode()) % 5 == 0]
    assert all(r.held_out for r, _ in held)
    right = np.mean([r.predicted == y for r, y in held])
    print("held-out accuracy", right, len(held))
    assert right > 0.97


def test_edges(spark):
    docs = spark.createDataFrame([(1, "good text here", 0.1), (None, None, 0.2), (2, "", 0.3)], "doc_id long, text string, score double")
    labels = spark.createDataFrame([(1, 1), (9, None), (None, 1)], "doc_id long, quality int")
    out = m.score_documents(docs, m.learn(docs, labels)).collect()
    assert len(out) == 3 and all(0 <= r.score <= 1 for r in out)
    assert m.score_documents(docs.limit(0), None).count() == 0


def test_texts_do_not_travel(spark):
    docs = spark.createDataFrame([(i, f"text {i}") for i in range(20)], "key long, text string")
    labels = spark.createDataFrame([(i, 1) for i in range(0, 20, 2)], "doc_id long, quality int")
    rest = m.unlabelled(docs, labels)
    assert sorted(r.key for r in rest.collect()) == list(range(1, 20, 2))
    plan = rest._jdf.queryExecution().optimizedPlan().toString()
    assert plan.index("Join") < plan.index("MapInArrow")  # features are made below the join
    assert "BroadcastHashJoin" not in rest._jdf.queryExecution().executedPlan().toString()
    assert m.unlabelled(docs.where("key % 2 = 0"), labels).count() == 10
