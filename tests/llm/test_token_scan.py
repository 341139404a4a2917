import random

import numpy as np

from graphdrift.llm import pieces
from graphdrift.llm import token_scan as m


def split(ids, eod):
    out, n = [], 0
    for x in ids:
        if x == eod:
            out.append((n, True))
            n = 0
        else:
            n += 1
    return out + ([(n, False)] if n else [])


def test_scan_equals_splitting(spark, tmp_path):
    random.seed(1)
    want, rows = [], []
    for f in range(12):
        rate = [0, 0.01, 0.1, 0.5, 1][f % 5]
        ids = [2 if random.random() < rate else random.randint(3, 90) for _ in range([0, 1, 64, 500, 999, 1000][f % 6])]
        want += [(f, k, n, t) for k, (n, t) in enumerate(split(ids, 2))]
        rows += [(f, b, np.array(ids[k : k + 10], "<u2").tobytes()) for b, k in enumerate(range(0, len(ids), 10))]
        (tmp_path / f"{f}.bin").write_bytes(np.array(ids, "<u2").tobytes())
    random.shuffle(rows)
    blocks = spark.createDataFrame([(f, b, bytearray(d)) for f, b, d in rows], "file long, block long, data binary").repartition(5)
    for group in (1, 3, 1000):
        assert sorted(map(tuple, m.document_lengths(blocks, group=group).collect())) == sorted(want)
    read = m.read_token_files(spark, str(tmp_path), block=7)
    ranged = m.read_token_files(spark, str(tmp_path), block=7, whole_bytes=100, span_blocks=3)
    assert sorted(map(tuple, ranged.collect())) == sorted(map(tuple, read.collect()))
    got = m.document_lengths(read).groupBy("file").agg(m.F.sort_array(m.F.collect_list(m.F.struct("ordinal", "n_tokens"))).alias("x")).collect()
    lists = sorted([tuple(y) for y in r.x] for r in got)
    files = {f for f, *_ in want}
    assert lists == sorted([(k, n) for g, k, n, _ in want if g == f] for f in files)


def test_counts(spark):
    table = pieces.ChunkTable(pieces.default_model())
    rows = [(k, "word " * (k * 13 % 40) + "é") for k in range(60)] + [(None, "a b"), (99, None), (99, ""), (7, "dup"), (7, "dup")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    got = sorted(((r.doc_id, r.n_tokens) for r in m.token_counts(docs).collect()), key=str)
    assert got == sorted(((i, len(table.sp.encode(t or ""))) for i, t in rows), key=str)
    assert m.token_counts(docs.limit(0)).count() == 0
