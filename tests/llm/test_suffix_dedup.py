import hashlib
import random
from collections import Counter

from graphdrift.llm import common
from graphdrift.llm import suffix_dedup as m


def brute(texts, length):
    data = [(t or "").encode() for t in texts]
    seen = Counter(d[i : i + length] for d in data for i in range(len(d) - length + 1))
    out = []
    for d in data:
        gone = bytearray(len(d))
        for i in range(len(d) - length + 1):
            if seen[d[i : i + length]] > 1:
                gone[i : i + length] = b"\1" * length
        kept = bytes(b for b, g in zip(d, gone) if not g)
        spans = sum(g and not (i and gone[i - 1]) for i, g in enumerate(gone))
        out.append((len(d), sum(gone), spans, hashlib.sha256(kept).hexdigest()))
    return out


def corpus(seed, n, passages, top=900):
    random.seed(seed)
    word = lambda: "".join(random.choice("abcdeé") for _ in range(random.randint(1, 9)))
    vocab = [word() for _ in range(200)]
    prose = lambda k: " ".join(random.choice(vocab) for _ in range(k))
    shared = [prose(random.randint(5, 60)) for _ in range(passages)]
    texts = [None, "", "x", "a" * 1500, "ab" * 300, "ab" * 300 + "c", prose(30)]
    for _ in range(n):
        parts = [prose(random.randint(1, 80))]
        for _ in range(random.randint(0, 3)):
            parts += [random.choice(shared), prose(random.randint(0, 30))]
        texts.append(" ".join(parts)[:top])
    texts += texts[7:10]
    t = texts[12]
    return texts + [t[:100] + "Z" + t[101:], t[50:], t[:-30]]


def check(spark, texts, length, **kw):
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(5)
    out = m.remove_repeats(docs, length, keep=["doc_id"], **kw).collect()
    got = {r.doc_id: (r.n_bytes, r.n_bytes - len(r.kept_bytes), len(r.removed), hashlib.sha256(r.kept_bytes).hexdigest()) for r in out}
    assert [got[i] for i in range(len(texts))] == brute(texts, length)


def test_cover_reaches_all_pairs():
    assert m.OFFSET.max() < m.MODULUS


def test_order_is_the_suffix_order():
    import numpy as np

    random.seed(2)
    for alphabet in (b"ab", b"a", b"abcdefgh"):
        text = bytes(random.choice(alphabet) for _ in range(400)) * 3
        data = np.frombuffer(text + bytes(600), np.uint8)
        words = m._words(data)
        rank = m.cover_ranks(words, len(text), 400)
        order = m.suffix_order(words, np.arange(800), rank)
        full = text + bytes(600)
        got = [full[i : i + 400] for i in order]
        assert got == sorted(got)


def test_equals_brute_force(spark):
    check(spark, corpus(1, 60, 6), 100, gram=32)
    check(spark, corpus(2, 40, 4), 60, gram=20, block=200)
    check(spark, corpus(3, 40, 3), 60, gram=20, most_runs=2)


def test_equals_brute_force_at_400(spark):
    check(spark, corpus(4, 40, 5, top=2500), 400)


def test_rows_and_text(spark):
    t = "é" * 300
    docs = spark.createDataFrame([(1, t + "x", 5), (1, t + "x", 5), (None, "y" + t, 6)], "doc_id long, text string, removed int")
    out = m.remove_repeats(docs, 400, as_text=True).collect()
    assert len(out) == 3 and all(r.kept_bytes.decode() in ("", "y") for r in out)
    assert m.removal_digests(docs.limit(0)).count() == 0


def test_shorter_passages_beside(spark):
    texts = corpus(5, 50, 5)
    docs = spark.createDataFrame([(i, t, "own") for i, t in enumerate(texts)], "doc_id long, text string, spans string").repartition(4)
    out = m.remove_repeats(docs, 120, passage=60, gram=20, longer_gram=32).collect()
    assert {r.spans for r in out} == {"own"}
    got = {r.doc_id: r for r in out}
    assert [(r.n_bytes, r.n_bytes - len(r.kept_bytes), len(r.removed), hashlib.sha256(r.kept_bytes).hexdigest()) for r in (got[i] for i in range(len(texts)))] == brute(texts, 120)
    plain = {r.doc_id: r.kept_bytes.decode() for r in m.remove_repeats(docs, 60, as_text=True, gram=20).collect()}
    assert {i: r.passages_cut for i, r in got.items()} == plain
    digests = {r.doc_id: r for r in m.removal_digests(docs, 120, 60).collect()}
    assert all(digests[i].n_removed == r.n_bytes - len(r.kept_bytes) and digests[i].text == r.passages_cut for i, r in got.items())


def test_a_task_gives_its_memory_back():
    kept = []

    def hold(batches):
        for b in batches:
            rows = [bytes(2000) for _ in range(150_000)]
            kept.append(rows[-1])  # one object above all freed ones
            del rows
            yield b

    def resident():
        with open("/proc/self/statm") as f:
            return int(f.read().split()[1]) * 4096

    before = resident()
    assert list(common.trimmed(hold)([1])) == [1]
    assert resident() - before < 100e6


def test_ranks_are_those_of_bytes():
    import numpy as np

    rng = np.random.default_rng(3)
    for n in (0, 1, 2, 5000):
        text = rng.choice(np.frombuffer(b"ab\xff", np.uint8), n).tobytes()
        words = m._words(np.frombuffer(text + bytes(80), np.uint8))
        assert [int(w) for w in words[:50]] == [int.from_bytes((text + bytes(80))[k : k + 8], "big") for k in range(len(words[:50]))]
        at = np.arange(0, n, 3)
        strings = [(text + bytes(80))[k : k + 32] for k in at]
        place = {x: i for i, x in enumerate(sorted(set(strings)))}
        assert m._first_bytes(words, at).tolist() == [place[x] for x in strings]
        far = rng.integers(0, 1 << 63, n).astype(np.uint64)  # too wide to hold their places
        assert m._order(far, 64)[1].tolist() == sorted(far.tolist())
