import random
import re

import numpy as np

from graphdrift.llm import superminhash as m

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def shingles(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    w = WORD.findall(low)
    if not w:
        return set()
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)}


def brute(rows, percent):
    sets = {i: shingles(t) for i, t in rows}
    up = {i: i for i in sets}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    ids = sorted(sets)
    for n, a in enumerate(ids):
        for b in ids[n + 1 :]:
            x, y = sets[a], sets[b]
            if x and y and 100 * len(x & y) >= percent * len(x | y):
                ra, rb = find(a), find(b)
                up[max(ra, rb)] = min(ra, rb)
    return {i: (len(sets[i]), find(i), find(i) == i) for i in ids}


def got(spark, rows, percent, **kw):
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    return {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in m.near_duplicates(docs, percent, **kw).collect()}


def test_signature_is_the_sequential_definition():
    rng = np.random.default_rng(3)
    for size in (1, 5, 300):
        values = rng.integers(0, 2**63, size, dtype=np.uint64)
        want = np.full(16, 1e9)
        for v in values:
            p = list(range(16))
            for j in range(16):
                r = int(m.scramble(np.array([v]) + np.uint64(j + 1) * m._ODD)[0])
                k = j + ((r & 0xFFFFFFFF) * (16 - j) >> 32)
                p[j], p[k] = p[k], p[j]
                want[p[j]] = min(want[p[j]], (j << 24) | (r >> 40))
        assert (m.superminhash(values, np.array([0, size]), 16) == want).all()
        assert (m.signatures([values], 16, block=7)[0] == want).all()


def test_estimate_follows_similarity():
    rng = np.random.default_rng(1)
    base = rng.integers(0, 2**63, 400, dtype=np.uint64)
    other = np.concatenate([base[:300], rng.integers(0, 2**63, 100, dtype=np.uint64)])
    s = m.signatures([base, other])
    assert abs((s[0] == s[1]).mean() - 0.6) < 0.15


def test_equals_brute_force(spark):
    random.seed(5)
    vocab = [f"w{i}" for i in range(400)]
    rows = [(0, None), (1, ""), (2, " \n "), (3, "one two"), (4, "ONE two"), (5, "one two three")]
    for _ in range(12):
        base = [random.choice(vocab) for _ in range(random.randint(20, 150))]
        for _ in range(random.randint(1, 14)):
            t = list(base)
            for _ in range(random.randint(0, 8)):
                t[random.randrange(len(t))] = random.choice(vocab)
            rows.append((len(rows), " ".join(t)))
    random.shuffle(rows)
    want = brute(rows, 85)
    assert got(spark, rows, 85) == want
    assert got(spark, rows, 85, block=3) == want
    assert got(spark, rows, 80) == brute(rows, 80)


def test_edges(spark):
    assert got(spark, [(1, "a b c d e f"), (2, None)], 85) == {1: (2, 1, True), 2: (0, 2, True)}
    docs = spark.createDataFrame([(7, "a b", 1), (7, "a b", 2), (None, "a b", 3)], "doc_id long, text string, n int")
    out = sorted(map(str, m.near_duplicates(docs).select("doc_id", "component_id", "kept").collect()))
    assert out == ["Row(doc_id=7, component_id=7, kept=True)"] * 2 + ["Row(doc_id=None, component_id=None, kept=True)"]
    assert m.near_duplicates(docs.limit(0)).count() == 0


def test_components(spark):
    links = [(i, i + 1) for i in range(40)] + [(100, 90), (95, 90), (7, 200)]
    df = spark.createDataFrame(links, "a long, b long").repartition(7)
    root = {r.node: r.root for r in m.components(df).collect()}
    assert all(root[i] == 0 for i in range(1, 41)) and root[200] == 0 and root[100] == root[95] == 90 and 0 not in root
