import hashlib
import random

from graphdrift.llm import merkle as m


def test_tree_and_likeness():
    a = "One two. Three four!\nSecond line here. More.\n\nNew section."
    assert m.fingerprint(a) == m.fingerprint(a) and m.likeness(m.fingerprint(a), m.fingerprint(a)) == 1
    b = a.replace("Three", "Other")
    fa, fb = m.fingerprint(a), m.fingerprint(b)
    assert fa[:32] != fb[:32] and 0.5 < m.likeness(fa, fb) < 1
    assert [a[x:y] for x, y in m.differing(a, b)] == [" Three four!"] and m.differing(a, a) == []
    assert m.likeness(m.fingerprint(""), m.fingerprint("")) == 1
    assert m.likeness(m.fingerprint("abc."), m.fingerprint("xyz.")) == 0
    # the same characters cut differently into lines are different texts
    assert m.fingerprint("a\nb")[:32] != m.fingerprint("a\n\nb")[:32] != m.fingerprint("a\nb\n")[:32]


def brute(rows):
    rows = sorted(((-(2**63) if i is None else i), t or "", i) for i, t in rows)
    out = []
    for k, (_, t, i) in enumerate(rows):
        n = rows[(k + 1) % len(rows)][1]
        e = t[: len(t) - len(t) // 2] + n[: len(t) // 2]
        f, g = m.fingerprint(t), m.fingerprint(e)
        out.append((i, len(t), hashlib.sha256(e.encode()).hexdigest(), f, g, m.likeness(f, g), m.likeness(f, m.fingerprint(n))))
    return sorted(out, key=str)


def test_query_equals_brute_force(spark):
    random.seed(4)
    rows = [(i * 3, " ".join(random.choice(["ab.", "cdé", "x!\n", "日本"]) for _ in range(random.randint(0, 60)))) for i in range(150)]
    rows += [(None, "null id."), (3000, None), (3001, ""), (7, "rep. rep."), (7, "rep. rep.")]
    random.shuffle(rows)
    for part in (rows, rows[:1], rows[:3]):
        docs = spark.createDataFrame(part, "doc_id long, text string").repartition(6)
        assert sorted(map(tuple, m.compare_next(docs).collect()), key=str) == brute(part)
    assert m.compare_next(docs.limit(0)).count() == 0
    assert m.fingerprints(docs).count() == 3
