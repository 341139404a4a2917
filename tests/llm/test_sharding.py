import hashlib
import random
import zlib

from graphdrift.llm import sharding as m


def brute(rows, shards):
    key = lambda r: (hashlib.md5((r[1] or "").encode()).hexdigest(), hashlib.md5(("" if r[0] is None else str(r[0])).encode()).hexdigest())
    line = sorted(rows, key=key)
    total, at, out, slots = sum(len((t or "").encode()) + 1 for _, t in rows), 0, [], {}
    for i, t in line:
        size = len((t or "").encode()) + 1
        at += size
        shard = min(shards - 1, shards * (2 * at - size) // (2 * total))
        slot = slots.get(shard, 0)
        slots[shard] = slot + 1
        out.append((i, size, zlib.crc32((t or "").encode()), shard, slot))
    return sorted(out, key=str)


def test_equals_brute_force_and_is_even(spark):
    random.seed(2)
    rows = [(i, "w" * random.randint(0, 400) + "é" * random.randint(0, 50)) for i in range(400)]
    rows += [(1000 + i, "the same text") for i in range(300)] + [(None, None), (None, "x"), (5000, None), (7, "twice"), (7, "twice")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    for kw in ({}, {"least_ranges": 7, "per_range": 2, "overfull": 1.1}):
        got = m.shard_records(docs, 16, **kw).collect()
        # twins may change places, so only their slots as a set are told
        assert sorted(map(tuple, got), key=str) == brute(rows, 16)
    sizes = [0] * 16
    for r in got:
        sizes[r.shard] += r["size"]
    assert max(sizes) - min(sizes) <= 2 * max(r["size"] for r in got)
    for s in range(16):
        slots = sorted(r.slot for r in got if r.shard == s)
        assert slots == list(range(len(slots)))


def test_splitters():
    sample = [(str(k % 5), str(k)) for k in range(100)]
    bounds = m.boundaries(sample, 10)
    assert len(bounds) == 9 and bounds == sorted(bounds) and m.boundaries([], 4) == []


def test_edges(spark, tmp_path):
    docs = spark.createDataFrame([(1, "a", 9)], "doc_id long, text string, shard int")
    row = m.shard_documents(docs).collect()[0]
    assert (row.doc_id, row.law, row.slot, row.grown_shard) == (1, "bytes", 0, None)
    assert m.shard_documents(docs.limit(0)).count() == 0
    m.write_shards(docs.drop("shard"), str(tmp_path / "s"), 2)
    assert spark.read.parquet(str(tmp_path / "s")).count() == 1
