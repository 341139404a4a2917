import hashlib

import numpy as np

from hypothesis import given, settings
from hypothesis import strategies as st

from graphdrift.llm import pieces

TABLE = pieces.ChunkTable(pieces.default_model())


def ids_of(text):
    """By chunks, each segmented on its own; the task's table must agree."""
    ids = [i for chunks in pieces.chunks_of(text, 7) for part in TABLE.segment(chunks) for i in part] if text else []
    assert np.frombuffer(TABLE.encode_all([text])[0], "<i4").tolist() == ids
    return ids, TABLE.decode(ids)


@settings(max_examples=300, deadline=None)
@given(st.text(alphabet=st.one_of(st.sampled_from(" ▁\n\t<s>abé日😀▁ \x00"), st.characters(exclude_categories=["Cs"])), max_size=60))
def test_equals_library(text):
    ids, plain = ids_of(text)
    assert ids == TABLE.sp.encode(text)
    assert plain == TABLE.sp.decode(ids) == TABLE.decode(ids)


def test_edges():
    for text in ["", " ", "  ", "▁", "a", " a ", "x" * 5000, "ab " * 20000, "\n\n  z"]:
        ids, plain = ids_of(text)
        assert ids == TABLE.sp.encode(text) and plain == TABLE.sp.decode(ids)


def test_each_distinct_chunk_is_segmented_once(spark):
    rows = [(i, " ".join(f"w{(i * j) % 11}" for j in range(40)) + " x" * (i % 3)) for i in range(60)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    packed = pieces.common.packed(docs, ["doc_id"], text=pieces.common.text_of())
    blocks, path = pieces.common.stored(pieces._numbered(packed, 500))
    lists = blocks.where("at is null")
    dealt = pieces._dealt(lists, 8).collect()
    held = {}
    for r in dealt:
        words, at = pieces._bytes(r.data), 0
        for n in pieces._array(r.sizes):
            held.setdefault(words[at : at + n], set()).add(r.bucket)
            at += n
    assert all(len(b) == 1 for b in held.values()) and len(held) == len({c for _, t in rows for x in pieces.chunks_of(t) for c in x})
    assert lists.count() > 4
    got = {r.doc_id: r for r in pieces.encode_documents(docs, block=500, bucket_chunks=3).collect()}
    assert all(got[i].piece_ids == TABLE.sp.encode(t) and got[i].piece_text == t for i, t in rows)


def test_long_texts_and_clashes(spark):
    rows = [(1, "é" * 70_000 + " " + "ab " * 400_000, 5, "own"), (2, None, 6, None), (2, " ", 7, "z")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, at int, kept string")
    got = pieces.encode_documents(docs).orderBy("at").collect()
    assert [(r.doc_id, r.at, r.kept) for r in got] == [(1, 5, "own"), (2, 6, None), (2, 7, "z")]
    assert [r.piece_ids for r in got] == [TABLE.sp.encode(t or "") for _, t, *_ in rows]


def test_query_rows(spark):
    rows = [(1, "hello world", "x"), (2, None, "y"), (3, "", None), (1, "hello world", "x"), (None, "é ▁ z", "q")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, piece_ids string")
    got = pieces.encode_documents(docs).collect()
    assert len(got) == 5 and {r.input_piece_ids for r in got} == {"x", "y", None, "q"}
    for r in got:
        assert r.piece_ids == TABLE.sp.encode(r.text or "")
    digests = {r.doc_id: r for r in pieces.piece_digests(docs).collect()}
    assert digests[2].ids_sha256 == hashlib.sha256(b"").hexdigest() and digests[2].n_tokens == 0
    want = ",".join(map(str, TABLE.sp.encode("hello world")))
    assert digests[1].ids_sha256 == hashlib.sha256(want.encode()).hexdigest()
    assert pieces.piece_digests(docs.limit(0)).count() == 0
    pieces.release(spark)
    back = pieces.decode_ids(pieces.encode_documents(docs).withColumnRenamed("piece_text", "was"))
    assert all(r.was == r.piece_text for r in back.collect())
