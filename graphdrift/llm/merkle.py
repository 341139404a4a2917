"""Merkle fingerprints of texts: segments, paragraphs, sections, root.

A paragraph is a line; a section is a run of paragraphs up to a blank line or, in
texts without blank lines, up to a paragraph whose digest says so (a rule on
content, so an insertion doesn't shift later sections). Paragraphs fall into
sentence-like segments, the leaves. Every digest covers its children's, so equal
roots mean equal texts and unequal ones are followed down only where branches
differ.

The fingerprint string is the root and the short digests of the leaves, nested as
sections ``|``, paragraphs ``/`` and segments of eight hex digits; likeness is
twice the common leaves over all leaves of both.

Defined results: null text is empty, with one empty leaf; equal texts have equal
fingerprints; two empty texts are alike by 1; rows are ordered by id (nulls
first), then text, and the last row's next is the first; a lone row is its own
next; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphdrift.llm import common

_SEGMENT = re.compile(r"[^.!?]{1,160}[.!?]*|[.!?]+")
_SECTION_EVERY = 8


def _hash(data: bytes) -> bytes:
    return hashlib.blake2b(data, digest_size=16).digest()


def tree(text: str) -> tuple[bytes, list[tuple[bytes, list[tuple[bytes, list[tuple[bytes, int]]]]]]]:
    """Root and sections; a section is (digest, paragraphs), a paragraph (digest, leaves), a leaf (digest, characters)."""
    blank = "\n\n" in text
    sections, now = [], []
    for line in text.split("\n"):
        parts = _SEGMENT.findall(line) or [""]
        leaves = [(_hash(s.encode("utf-8", "surrogatepass")), len(s)) for s in parts]
        digest = _hash(b"p" + b"".join(x for x, _ in leaves))
        now.append((digest, leaves))
        if (not line) if blank else digest[0] % _SECTION_EVERY == 0:
            sections.append((_hash(b"s" + b"".join(x for x, _ in now)), now))
            now = []
    if now:
        sections.append((_hash(b"s" + b"".join(x for x, _ in now)), now))
    return _hash(b"r" + b"".join(x for x, _ in sections)), sections


def as_string(found) -> str:
    """The fingerprint string of a tree."""
    root, sections = found
    return root.hex() + ":" + "|".join("/".join("".join([leaf.hex()[:8] for leaf, _ in leaves]) for _, leaves in paragraphs) for _, paragraphs in sections)


def fingerprint(text: str) -> str:
    return as_string(tree(text))


def leaves_of(fingerprint: str) -> Counter:
    """Multiset of the leaves in a fingerprint string."""
    body = fingerprint.partition(":")[2].replace("|", "").replace("/", "")
    return Counter([body[k : k + 8] for k in range(0, len(body), 8)])


def likeness(a: str, b: str) -> float:
    """0 to 1; 1 for equal roots."""
    if a[:32] == b[:32]:
        return 1.0
    return _overlap(leaves_of(a), leaves_of(b))


def _overlap(x: Counter, y: Counter) -> float:
    if len(y) < len(x):
        x, y = y, x
    shared = sum(min(n, y[k]) for k, n in x.items() if k in y)
    return min(2 * shared / max(1, x.total() + y.total()), 1 - 1e-9)


def differing(a: str, b: str) -> list[tuple[int, int]]:
    """Character ranges of ``a``'s leaves that have no equal branch in ``b``: branches found equal are not entered."""
    (root_a, sections_a), (root_b, sections_b) = tree(a), tree(b)
    if root_a == root_b:
        return []
    other = Counter(d for d, _ in sections_b)
    in_paragraphs = Counter(d for _, ps in sections_b for d, _ in ps)
    in_leaves = Counter(d for _, ps in sections_b for _, ls in ps for d, _ in ls)
    at, out = 0, []
    for s, paragraphs in sections_a:
        same = other[s] > 0
        for p, leaves in paragraphs:
            alike = same or in_paragraphs[p] > 0
            for leaf, n in leaves:
                if not alike and not in_leaves[leaf]:
                    if out and out[-1][1] == at:
                        out[-1] = (out[-1][0], at + n)
                    else:
                        out.append((at, at + n))
                at += n
            at += 1
    return out


def edited(text: str, following: str) -> str:
    """The text with its last half replaced by the first half of the next, as far as it reaches."""
    half = len(text) // 2
    return text[: len(text) - half] + following[:half]


def fingerprints(docs: DataFrame) -> DataFrame:
    """Columns of ``docs`` (one named fingerprint as input_fingerprint) and fingerprint."""
    common.tune(docs.sparkSession)

    @F.pandas_udf("string")
    def mark(texts: pd.Series) -> pd.Series:
        return texts.map(fingerprint)

    return common.unpacked(common.packed(docs, docs.columns, fingerprint=mark(common.text_of())), docs.columns, fingerprint=F.col("fingerprint"))


def with_next(docs: DataFrame, least_ranges: int = 128, range_bytes: int = 1 << 27, most_ranges: int = 8192) -> tuple[DataFrame, int]:
    """Rows dealt into id ranges, and in each range, last, the first row of the range after it.

    One exchange of the texts; the rows that cross a border number as many as the
    ranges (at most ``most_ranges``).
    """
    order = F.coalesce(F.col("doc_id").cast("long"), F.lit(-(2**63)))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), order.alias("place"), common.text_of().alias("text"))
    total = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    ranges = int(min(most_ranges, max(least_ranges, total // range_bytes)))
    shares = [k / ranges for k in range(1, ranges)]
    bounds = sorted(set(rows.agg(F.percentile_approx("place", shares, 20 * ranges)).first()[0] or []))

    @F.pandas_udf("int")
    def find(place: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(np.array(bounds, np.int64), place.to_numpy(), side="left").astype(np.int32))

    firsts = sorted((r["range"], r["place"]) for r in rows.select("place").withColumn("range", find("place")).groupBy("range").agg(F.min("place").alias("place")).collect())
    if not firsts:
        return rows.select("doc_id", "place", "text", F.lit(0).alias("range"), F.lit(0).alias("guest")), 1
    spark = docs.sparkSession
    border = spark.createDataFrame([(place, firsts[k - 1][0]) for k, (_, place) in enumerate(firsts)], "place long, range int")
    guests = rows.join(F.broadcast(border), "place").groupBy("range").agg(F.min("text").alias("text"))
    dealt = rows.withColumn("range", find("place")).select("doc_id", "place", "text", "range", F.lit(0).alias("guest"))
    guests = guests.select(F.lit(None).cast("long").alias("doc_id"), F.lit(0).cast("long").alias("place"), "text", "range", F.lit(1).alias("guest"))
    both = dealt.unionAll(guests)
    return both.repartitionById(len(bounds) + 1, F.col("range")).sortWithinPartitions("range", "guest", "place", "text"), len(bounds) + 1


def compare_next(docs: DataFrame) -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next."""
    common.tune(docs.sparkSession)
    rows, _ = with_next(docs)
    names = ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"]
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for batch in batches:
            out = []
            for doc_id, text, where, guest in zip(*(batch.column(k).to_pylist() for k in range(4))):
                mark = fingerprint(text)
                leaves = leaves_of(mark)
                if held is not None and held[4] == where:
                    own, own_text, own_mark, own_leaves, _ = held
                    new = edited(own_text, text)
                    new_mark = fingerprint(new)
                    near = [1.0 if own_mark[:32] == m[:32] else _overlap(own_leaves, x) for m, x in ((new_mark, leaves_of(new_mark)), (mark, leaves))]
                    out.append((own, len(own_text), hashlib.sha256(new.encode("utf-8", "surrogatepass")).hexdigest(), own_mark, new_mark, *near))
                held = None if guest else (doc_id, text, mark, leaves, where)
            if out:
                yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in out], kind) for k, kind in enumerate(kinds)], names=names)

    return rows.select("doc_id", "text", "range", "guest").mapInArrow(run, "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")
