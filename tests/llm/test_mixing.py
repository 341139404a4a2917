import hashlib
import math

from graphdrift.llm import mixing as m


def pour(children, budget):
    """(name, cap, weight) by rounds: fill, then hand the shortage to siblings with room."""
    share, open_, left = {}, list(children), budget
    while open_:
        level = left / sum(w for _, _, w in open_)
        full = [c for c in open_ if c[1] <= c[2] * level]
        if not full:
            share |= {n: min(c, math.floor(w * level)) for n, c, w in open_}
            break
        for n, c, _ in full:
            share[n] = c
            left -= c
        open_ = [c for c in open_ if c not in full]
    return share


def brute(rows, share, epochs, seed, dw, lw):
    leaves = {}
    for i, t, lang, source in rows:
        n = (len((t or "").encode()) + 3) // 4
        digits = "".join(c for c in (source or "")[::-1][: len(source or "") - len((source or "").rstrip("0123456789"))][::-1])
        d = "domain" + (str(int(digits) % 4) if digits else "0")
        leaves.setdefault((d, lang or "(none)", source or "(none)"), []).append((i, n))
    cap = {k: sum(n for _, n in v) * epochs for k, v in leaves.items()}
    total = sum(cap.values()) // epochs
    domains = sorted({k[0] for k in leaves})
    top = pour([(d, sum(c for k, c in cap.items() if k[0] == d), dw.get(d, 1)) for d in domains], min(int(total * share), sum(cap.values())))
    out = []
    for d in domains:
        langs = sorted({k[1] for k in leaves if k[0] == d})
        mid = pour([(x, sum(c for k, c in cap.items() if k[:2] == (d, x)), lw.get(x, 1)) for x in langs], top[d])
        for x in langs:
            low = pour([(k[2], c, 1) for k, c in sorted(cap.items()) if k[:2] == (d, x)], mid[x])
            for s, budget in low.items():
                run, turns = 0, []
                for e in range(epochs):
                    turns += sorted((e, hashlib.md5(f"{seed}:{e}:{'' if i is None else i}".encode()).hexdigest(), n, i) for i, n in leaves[d, x, s])
                for e, _, n, i in turns:
                    run += n
                    if run <= budget:
                        out.append((i, d, x, s, e, n, budget))
    return sorted(out, key=str)


def rows_of(n):
    return [(k, "x" * (k * 37 % 90), ["en", "de", "fr", None][k % 7 % 4], f"src{k % 3 if k % 2 else k % 11}") for k in range(n)] + [(None, None, None, None), (5000, "", "en", "odd"), (3, "x" * 21, "fr", "src1")]


def test_equals_brute_force(spark):
    rows = rows_of(600)
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").repartition(4)
    for share, epochs in ((0.5, 2), (0.9, 1), (1.7, 2), (0.05, 3)):
        got = m.mix(docs, share, epochs, digits=1).select("doc_id", *m.LEVELS, "mix_epoch", "mix_tokens", "leaf_budget").collect()
        assert sorted(map(tuple, got), key=str) == brute(rows, share, epochs, 7, m.DOMAIN_WEIGHTS, m.LANG_WEIGHTS)


def test_shortage_goes_to_siblings_first(spark):
    rows = [(k, "x" * 400, "en", f"src{s}") for s, n in ((0, 2), (4, 50), (1, 50)) for k in range(s * 100, s * 100 + n)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    leaf = {r.mix_source: r.leaf_budget for r in m.mix(docs, 0.5, 1, domain_weights={}, lang_weights={}).select("mix_source", "leaf_budget").distinct().collect()}
    # domain0 (src0, src4) and domain1 (src1) get half each; src0 holds 200 and src4 takes what it leaves
    assert leaf == {"src0": 200, "src4": 2350, "src1": 2550}


def test_edges(spark):
    docs = spark.createDataFrame(rows_of(5), "doc_id long, text string, lang string, source string")
    assert m.mix(docs.limit(0)).count() == 0
    assert m.mix(docs.withColumn("extra", m.F.lit(1)), 1.0, 1).columns[:5] == ["doc_id", "text", "lang", "source", "extra"]
    assert m.mix(docs, 1.0, 1).count() == 8
    plan = m.mix(docs)._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan
