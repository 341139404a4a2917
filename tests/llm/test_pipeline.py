"""Each stage of the corpus pipeline, and all in a row, against brute force; names that clash; edge cases of every operator."""

import hashlib
import importlib.util
import os
import random

import numpy as np
import pytest
import test_mixing
import test_superminhash
from graphdrift.llm import merkle, mixing, pieces, pu_quality, sharding, suffix_dedup, superminhash, token_scan, transcripts, webp

spec = importlib.util.spec_from_file_location("corpus_pipeline", os.path.join(os.path.dirname(__file__), "../../corpus_pipeline.py"))
pipe = importlib.util.module_from_spec(spec)
spec.loader.exec_module(pipe)

#: Columns that bear names which the operators use themselves.
CLASH = "score double, predicted int, held_out int, stop int, e int, run int, spans string, rid long, n_bytes int, removed int, kept_bytes int, mix_tokens int, mix_domain string, kept string, row_ int, at int, fingerprint string, component_id int, piece_ids string, seq int, __text string"


def corpus():
    random.seed(11)
    words = ["".join(random.choice("abcdefghilmnoprstu") for _ in range(random.randint(2, 9))) for _ in range(300)]
    prose = lambda n: " ".join(random.choice(words) for _ in range(n)).capitalize() + "."
    shared = [prose(60) for _ in range(3)]
    rows = []
    for i in range(60):
        text = prose(random.randint(20, 140))
        if i % 6 == 1:
            text += " " + shared[i % 3] + " " + prose(30)
        if i % 10 == 4:
            text = "x1 " * random.randint(30, 90)
        rows.append((i, text, ["en", "de", None][i % 3], f"src{i % 5}"))
    rows += [(60, rows[0][1], "en", "src0"), (61, rows[2][1] + " end", "en", "src1"), (62, None, "en", "src1"), (63, "", None, None), (None, "no id here " * 9, "de", "src2"), (5, rows[5][1], "de", "src0"), (5, prose(50), "de", "src0"), (64, prose(4000), "en", "src3")]
    return rows


def brute_near(rows):
    """One row of a group stays; rows without an id stay; rows that repeat an id are one group."""
    one = {}
    for r in rows:
        if r[0] is not None:
            one.setdefault(r[0], []).append(r)
    sets = {(i, k): test_superminhash.shingles(r[1]) for i, v in one.items() for k, r in enumerate(v)}
    up = {i: i for i in one}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    keys = sorted(sets)
    for n, a in enumerate(keys):
        for b in keys[n + 1 :]:
            x, y = sets[a], sets[b]
            if x and y and 100 * len(x & y) >= 80 * len(x | y):
                ra, rb = find(a[0]), find(b[0])
                up[max(ra, rb)] = min(ra, rb)
    return {i for i in one if find(i) == i}


def brute_passages(texts, length=240):
    data = [(t or "").encode() for t in texts]
    seen = {}
    for d in data:
        for i in range(len(d) - length + 1):
            seen[d[i : i + length]] = seen.get(d[i : i + length], 0) + 1
    out = []
    for d in data:
        gone = bytearray(len(d))
        for i in range(len(d) - length + 1):
            if seen[d[i : i + length]] > 1:
                gone[i : i + length] = b"\1" * length
        out.append(bytes(b for b, g in zip(d, gone) if not g).decode())
    return out


@pytest.fixture(scope="module")
def table(spark, tmp_path_factory):
    folder = tmp_path_factory.mktemp("sf")
    clash = [f.split()[1] for f in CLASH.split(", ")]
    rows = [(*r, len(r[1] or ""), *[k if c in ("int", "long") else float(k) if c == "double" else f"own{k}" for c in clash]) for k, r in enumerate(corpus())]
    docs = spark.createDataFrame(rows, f"doc_id long, text string, lang string, source string, n_chars long, {CLASH}")
    docs.repartition(3).write.parquet(f"{folder}/documents.parquet")
    labels = [(i, int(i % 10 != 4), 0) for i in range(60) if i % 4]
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")
    return str(folder)


def key(rows):
    return sorted((tuple(r) for r in rows), key=str)


def test_stages_and_run(spark, table):
    docs = spark.read.parquet(f"{table}/documents.parquet")
    extra = [c for c in docs.columns if c not in ("doc_id", "text", "lang", "source", "n_chars")]
    whole = {r.row_: r for r in docs.collect()}  # row_ tells the rows apart

    def carried(frame):
        rows = frame.collect()
        assert frame.columns == docs.columns
        assert all(r[c] == whole[r.row_][c] for r in rows for c in [*extra, "doc_id", "lang", "source"])
        return rows

    # quality: the learned model, one text at a time
    model = pu_quality.learn(docs, spark.read.parquet(f"{table}/labels.parquet"))
    good = lambda t: model.score(pu_quality.features([(t or "").encode()]).astype(np.float64))[0] >= 0.3
    kept = carried(pipe.quality_stage(spark, docs, table))
    assert key(kept) == key(r for r in whole.values() if good(r.text)) and 0 < len(kept) < len(whole)

    stage = lambda rows: spark.createDataFrame(rows, docs.schema).repartition(3)
    near = carried(pipe.near_duplicate_stage(spark, stage(kept), table))
    stay = brute_near([tuple(r)[:4] for r in kept])
    named = [r for r in near if r.doc_id is not None]
    assert sorted(r.doc_id for r in named) == sorted(stay) and all(tuple(r) in set(map(tuple, kept)) for r in near)
    assert sum(r.doc_id is None for r in near) == sum(r.doc_id is None for r in kept)

    cut = carried(pipe.passage_stage(spark, stage(near), table))
    want = brute_passages([r.text for r in near])
    assert sorted((r.row_, r.text, r.n_chars) for r in cut) == sorted((r.row_, t, len(t)) for r, t in zip(near, want))
    assert any(len(t) < len(r.text or "") for r, t in zip(near, want))

    mixed = carried(pipe.mixture_stage(spark, stage(cut), table))
    want = test_mixing.brute([(r.doc_id, r.text, r.lang, r.source) for r in cut], pipe.MIX_SHARE, 1, 7, mixing.DOMAIN_WEIGHTS, mixing.LANG_WEIGHTS)
    assert sorted((r.doc_id for r in mixed), key=str) == sorted((w[0] for w in want), key=str) and len(mixed) < len(cut)

    sp = pieces.Segmenter(pieces.default_model()).sp
    coded = pipe.piece_stage(spark, stage(mixed), table).collect()
    digest = lambda x: hashlib.sha256(x.encode()).hexdigest()
    told = [(r.doc_id, r.lang, r.source, len(sp.encode(r.text or "")), digest(",".join(map(str, sp.encode(r.text or "")))), digest(sp.decode(sp.encode(r.text or "")))) for r in mixed]
    assert key(coded) == key(told)

    assert key(pipe.run(spark, table).collect()) == key(told)


OPERATORS = {
    "op1": lambda d: mixing.mix(d),
    "op2": webp.media_digests,
    "op3": lambda d: suffix_dedup.remove_repeats(d, 100, gram=32, passage=60),
    "op4": lambda d: pu_quality.score_documents(d, None),
    "op5": lambda d: superminhash.near_duplicates(d),
    "op6": merkle.compare_next,
    "op6b": merkle.fingerprints,
    "op7": sharding.shard_documents,
    "op8": token_scan.token_counts,
    "op10": pieces.encode_documents,
}


@pytest.mark.parametrize("name", OPERATORS)
def test_clashes_nulls_repeats_and_empty_tables(spark, table, name):
    docs = spark.read.parquet(f"{table}/documents.parquet")
    out = OPERATORS[name](docs)
    n = out.count()
    if name == "op1":
        assert 0 < n <= 2 * docs.count()
    else:
        assert n == docs.count()
    if name in ("op1", "op3", "op4", "op6b", "op10"):  # other columns pass through
        named = {c.lower() for c in out.columns}
        assert all(c.lower() in named for c in docs.columns) and len(named) == len(out.columns)
        own = "input_" if name != "op6b" else "input_fingerprint"
        assert any(c.startswith(own) for c in out.columns)
        got = {r.row_: r for r in out.collect()}
        for r in docs.collect():
            for c in docs.columns:
                if r.row_ in got:
                    assert got[r.row_][f"input_{c}" if f"input_{c}" in out.columns else c] == r[c]
    assert OPERATORS[name](docs.limit(0)).count() == 0


def test_transcripts_clashes_and_long_conversations(spark):
    rows = [(1, t, ["user", "assistant"][t % 2], f"line {t} " + "word " * (t % 9)) for t in range(3000)] + [(None, None, None, None), (2, 0, "system", ""), (2, 0, "system", ""), (3, 1, "user", "x" * 200_000)]
    docs = spark.createDataFrame([(*r, "own", 1, 2) for r in rows], "conv_id long, turn long, role string, text string, raw string, seq int, m int").repartition(7)
    out = transcripts.recovered_roles(docs)
    assert out.count() == len(rows)
    raw = transcripts.ordered_turns(transcripts.raw_conversations(docs), partitions=8)
    model = transcripts.train(raw)
    got = [r for r in transcripts.parse_turns(raw, model).collect() if r.conv_id == 1]
    got.sort(key=lambda r: r.turn)
    lines = [x for r in got for x in r.raw.split("\n")]
    best = model.path([transcripts.symbol_of(x) for x in lines], transcripts.START)
    roles = [transcripts.ROLES.index(x) for r in got for x in r.roles]
    assert [s // 2 for s in best] == roles
    assert transcripts.recovered_roles(docs.limit(0)).count() == 0
