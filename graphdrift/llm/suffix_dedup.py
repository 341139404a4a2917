"""Removal of byte strings of a given length that start at more than one place.

All suffixes of a corpus can't travel, so the corpus first says which of them can
have an equal: the starts of a text are cut into runs that share a minimal k-gram
hash within their window (a property of the window's own bytes, so equal windows
lie in runs with equal hashes). A run's hash is its suffix bucket. Runs are
grouped by (bucket, digest of the run's bytes):

* a bucket with one run, seen once, holds no repeated window;
* a run seen twice or more is repeated throughout;
* what is left are buckets with different runs. Their distinct runs' bytes are
  brought together, and the suffixes of a few buckets at a time are sorted: by
  their first 32 bytes, long ties by the ranks of a difference-cover sample (mod
  31, six residues, ranked beforehand by doubling). For any two suffixes some
  offset below 31 leads both into the sample, so one look-up decides. Neighbours
  in the order whose common prefix reaches the window length are repeated.

Memory is bounded by the block of buckets that a task sorts. A bucket of more
runs than ``most_runs`` is dealt out window by window instead (128-bit hashes,
counted before the exchange), which is exact as well.

Defined results: null text is empty; a text shorter than the window loses nothing;
repeated rows are places of their own, so a repeated text of the window's length
or more goes as a whole; bytes are judged on the input; an empty table gives an
empty result; other columns pass through, one with an added column's name as
``input_<name>``. Rows are told apart by a 64-bit hash of (doc_id, text) and length.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from graphdrift.llm import common
from graphdrift.llm.superminhash import scramble

MODULUS, COVER = 31, (1, 5, 11, 24, 25, 27)
_BASE = 0xD6E8FEB86659FD93
_BASE_INV = pow(_BASE, -1, 1 << 64)


def _offsets() -> np.ndarray:
    """The least offset that takes both residues into the cover."""
    member = [r in COVER for r in range(MODULUS)]
    return np.array([[next(d for d in range(MODULUS) if member[(a + d) % MODULUS] and member[(b + d) % MODULUS]) for b in range(MODULUS)] for a in range(MODULUS)])


OFFSET = _offsets()


class Roller:
    """Hashes of all k-grams of a byte array (polynomial mod 2^64, scrambled)."""

    def __init__(self) -> None:
        self.up = self.down = np.ones(1, np.uint64)

    def __call__(self, data: np.ndarray, k: int) -> np.ndarray:
        n = len(data)
        if n < k:
            return np.empty(0, np.uint64)
        if len(self.up) < n + 1:
            for name, base in (("up", _BASE), ("down", _BASE_INV)):
                powers = np.full(n + 1, base, np.uint64)
                powers[0] = 1
                setattr(self, name, np.cumprod(powers, dtype=np.uint64))
        total = np.zeros(n + 1, np.uint64)
        np.cumsum((data.astype(np.uint64) + np.uint64(1)) * self.up[:n], out=total[1:])
        return scramble((total[k:] - total[:-k]) * self.down[: n - k + 1])


def window_minima(values: np.ndarray, width: int) -> np.ndarray:
    """The least of each ``width`` neighbours, from running minima of blocks."""
    n = len(values)
    if n < width:
        return np.empty(0, values.dtype)
    padded = np.full(-(-n // width) * width, np.iinfo(values.dtype).max, values.dtype)
    padded[:n] = values
    grid = padded.reshape(-1, width)
    left = np.minimum.accumulate(grid, axis=1).reshape(-1)
    right = np.minimum.accumulate(grid[:, ::-1], axis=1)[:, ::-1].reshape(-1)
    return np.minimum(right[: n - width + 1], left[width - 1 : n])


def runs_of(texts: list[bytes], length: int, gram: int, roll: Roller):
    """Runs of starts for texts laid end to end: text number, key, digest, first start, starts, repeats inside."""
    sizes = np.array([len(t) for t in texts], np.int64)
    ends = np.cumsum(sizes)
    data = np.frombuffer(b"".join(texts), np.uint8)
    grams = roll(data, gram)
    least = window_minima(grams, length - gram + 1)
    valid = np.zeros(len(least) + 1, bool)
    for e, n in zip(ends[sizes >= length], sizes[sizes >= length]):
        valid[e - n : e - length + 1] = True
    valid[len(least) :] = False
    on = valid[:-1]
    first = on.copy()
    first[1:] &= ~(on[:-1] & (least[1:] == least[:-1]))
    begins = np.flatnonzero(first)
    stop = on.copy()
    stop[:-1] &= ~(on[1:] & (least[1:] == least[:-1]))
    lasts = np.flatnonzero(stop)
    keys = least[begins]
    owner = np.searchsorted(ends, begins, side="right")
    whole = data.tobytes()
    digest = np.empty(len(begins), np.uint64)
    inner = np.zeros(len(begins), bool)
    width = length - gram + 1
    for r, (a, b) in enumerate(zip(begins.tolist(), lasts.tolist())):
        digest[r] = int.from_bytes(hashlib.blake2b(whole[a : b + length], digest_size=8).digest(), "little")
        inner[r] = b > a and np.count_nonzero(grams[a : b + width] == keys[r]) > 1
    return owner, keys, digest, begins - (ends - sizes)[owner], lasts - begins + 1, inner


def _words(data: np.ndarray) -> np.ndarray:
    """Big-endian 8-byte words at every position."""
    out = data
    for half, wider in ((1, np.uint16), (2, np.uint32), (4, np.uint64)):
        last, out = out[half:], out[:-half].astype(wider)
        out <<= wider(8 * half)
        out |= last
    return out


def _order(key: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Places and values of numbers of so many bits, ascending. Sorting values with their places in them is faster than sorting places."""
    n = len(key)
    room = np.uint64(n.bit_length())
    if bits + int(room) > 64:
        order = np.argsort(key)
        return order, key[order]
    packed = key << room
    packed |= np.arange(n, dtype=np.uint64)
    packed.sort()
    return (packed & ((np.uint64(1) << room) - np.uint64(1))).astype(np.int64), packed >> room


def _dense(key: np.ndarray, bits: int = 64) -> np.ndarray:
    """Dense ranks of numbers of so many bits."""
    order, key = _order(key, bits)
    rank = np.zeros(len(order), np.uint64)
    rank[order[1:]] = np.cumsum(key[1:] != key[:-1])
    return rank


def _paired(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Dense ranks of pairs of numbers of up to the array's length, the first foremost."""
    bits = len(a).bit_length()
    return _dense(a << np.uint64(bits) | b, 2 * bits)


def _first_bytes(words: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Dense ranks of the 32 bytes at each position."""
    a, b, c, d = (_dense(words[at + 8 * k]) for k in range(4))
    return _paired(_paired(a, b), _paired(c, d))


def cover_ranks(words: np.ndarray, size: int, depth: int) -> np.ndarray:
    """Ranks, at sample positions, of their next ``depth`` bytes at least; 0 elsewhere."""
    at = np.flatnonzero(np.resize(np.isin(np.arange(MODULUS), COVER), size))
    rank = np.zeros(len(words), np.uint64)
    one = np.uint64(1)
    rank[at] = _first_bytes(words, at) + one
    reach = MODULUS
    while reach < depth:
        after = rank[np.minimum(at + reach, len(words) - 1)]
        rank[at] = _paired(rank[at], after) + one
        reach *= 2
    return rank


def suffix_order(words: np.ndarray, starts: np.ndarray, rank: np.ndarray) -> np.ndarray:
    """Starts in the order of their suffixes."""
    first = _first_bytes(words, starts)
    turn, first = _order(first, len(first).bit_length())
    order = starts[turn]
    fresh = np.ones(len(order), bool)
    fresh[1:] = first[1:] != first[:-1]
    heads = np.flatnonzero(fresh)
    sizes = np.diff(np.append(heads, len(order)))
    # ties of one size class at a time through a merge-exchange network
    bits = 1
    while len(sizes) and (1 << (bits - 1)) < sizes.max():
        chosen = (sizes > 1 << (bits - 1)) & (sizes <= 1 << bits)
        if chosen.any():
            n = sizes[chosen]
            local = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            room, base = np.repeat(n, n), np.repeat(heads[chosen], n)
            p = top = 1 << (bits - 1)
            while p:
                q, r, d = top, 0, p
                while True:
                    pick = ((local & p) == r) & (local + d < room)
                    low = base[pick] + local[pick]
                    a, b = order[low], order[low + d]
                    off = OFFSET[a % MODULUS, b % MODULUS]
                    swap = rank[a + off] > rank[b + off]
                    order[low[swap]], order[low[swap] + d] = b[swap], a[swap]
                    if q == p:
                        break
                    d, q, r = q - p, q >> 1, p
                p >>= 1
        bits += 1
    return order


def repeated_starts(parts: list[bytes], counts: list[int], length: int) -> list[np.ndarray]:
    """For each string: which of its first ``count`` windows equal another window of the block."""
    text = b"".join(parts)
    data = np.frombuffer(text + bytes(length + 64), np.uint8)
    words = _words(data)
    begins = np.cumsum([0] + [len(p) for p in parts])[:-1]
    starts = np.concatenate([np.arange(b, b + c) for b, c in zip(begins, counts)])
    rank = cover_ranks(words, len(text), length)
    order = suffix_order(words, starts, rank)
    a, b = order[:-1], order[1:]
    live = np.arange(len(a))
    for k in range(0, length, 8):
        if not len(live):
            break
        at = min(k, length - 8)
        live = live[words[a[live] + at] == words[b[live] + at]]
    hit = np.zeros(len(data), bool)
    hit[a[live]] = hit[b[live]] = True
    return [hit[x : x + c] for x, c in zip(begins, counts)]


def _spans(hit: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    edge = np.diff(np.concatenate([[0], hit.astype(np.int8), [0]]))
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)


def _extract(texts: DataFrame, length: int, gram: int) -> DataFrame:
    """rid and its runs: bucket key, digest, (first start << 32 | starts << 1 | repeats inside)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        roll = Roller()
        for batch in batches:
            texts = common.byte_list(batch.column(1))
            at = 0
            while at < len(texts):
                end, held = at, 0
                while end < len(texts) and (end == at or held + len(texts[end]) <= 1 << 19):
                    held += len(texts[end])
                    end += 1
                owner, keys, digest, first, count, inner = runs_of(texts[at:end], length, gram, roll)
                cuts = np.searchsorted(owner, np.arange(end - at + 1)).astype(np.int32)
                where = (first << 32) | (count << 1) | inner
                lists = [pa.ListArray.from_arrays(pa.array(cuts), pa.array(x)) for x in (keys.view(np.int64), digest.view(np.int64), where.astype(np.int64))]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, end - at), *lists], names=["rid", "keys", "digests", "places"])
                at = end

    return texts.select("rid", "text").mapInArrow(common.trimmed(run), "rid long, keys array<long>, digests array<long>, places array<long>")


def _combined(runs: DataFrame) -> DataFrame:
    """key, digest, c, rid, place, inner: the runs of a task, equal ones counted before anything travels."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list[np.ndarray]] = []
        for batch in batches:
            lists = [batch.column(k) for k in (1, 2, 3)]
            sizes = np.diff(lists[0].offsets.to_numpy())
            held.append([*[x.flatten().to_numpy() for x in lists], np.repeat(batch.column(0).to_numpy(), sizes)])
        if not held:
            return
        key, digest, place, rid = (np.concatenate(x) for x in zip(*held))
        order = np.lexsort((place, rid, digest, key))
        key, digest, place, rid = key[order], digest[order], place[order], rid[order]
        first = np.ones(len(key), bool)
        first[1:] = (key[1:] != key[:-1]) | (digest[1:] != digest[:-1])
        at = np.flatnonzero(first)
        if not len(at):
            return
        count = np.diff(np.append(at, len(key)))
        inner = np.maximum.reduceat(place & 1, at)
        for k in range(0, len(at), 100_000):
            x = at[k : k + 100_000]
            columns = [key[x], digest[x], count[k : k + 100_000], rid[x], place[x], inner[k : k + 100_000]]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=["key", "digest", "c", "rid", "place", "inner"])

    return runs.select("rid", "keys", "digests", "places").mapInArrow(common.trimmed(run), "key long, digest long, c long, rid long, place long, inner long")


def _cut_out(asked: DataFrame, length: int, longer: int | None) -> DataFrame:
    """kind, key, c, rid, first, starts, data. ``asked``: text, rid, runs (place, key, c, need).

    Kind 0 are the bytes of the runs needed by the sort. Kind 1, with ``longer``, are
    the stretches of at least that many bytes that the text's runs cover together.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for t, rid, runs in zip(common.byte_list(batch.column(0)), batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                spans = []
                for x in runs:
                    first, starts = x["place"] >> 32, (x["place"] & 0xFFFFFFFF) >> 1
                    if x["need"]:
                        rows.append((0, x["key"], x["c"], rid, first, starts, t[first : first + starts - 1 + length]))
                    spans.append({"a": first, "b": first + starts - 1 + length})
                if longer:
                    spans.sort(key=lambda s: s["a"])
                    rows += [(1, 0, 0, rid, a, 0, t[a:b]) for a, b in merged(spans) if b - a >= longer]
            kinds = [pa.int32(), *[pa.int64()] * 5, pa.binary()]
            for k in range(0, len(rows), 4096):
                yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in rows[k : k + 4096]], kind) for i, kind in enumerate(kinds)], names=["kind", "key", "c", "rid", "first", "starts", "data"])

    return asked.select("text", "rid", "runs").mapInArrow(common.trimmed(run), "kind int, key long, c long, rid long, first long, starts long, data binary")


def _sorted_buckets(strings: DataFrame, length: int, block: int) -> DataFrame:
    """rid, a, b: byte spans found repeated among the runs of each bucket."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list = []
        size, now = 0, None

        def flush() -> pa.RecordBatch:
            out = []
            for x, hit in zip(held, repeated_starts([h[4] for h in held], [h[3] for h in held], length)):
                if x[0] == 1 and hit.any():
                    out += [(x[1], x[2] + a, x[2] + b - 1 + length) for a, b in zip(*map(np.ndarray.tolist, _spans(hit)))]
            return pa.RecordBatch.from_arrays([pa.array([o[k] for o in out], pa.int64()) for k in range(3)], names=["rid", "a", "b"])

        for batch in batches:
            key, c, rid, first, starts, data = (batch.column(k).to_pylist() for k in range(6))
            for i in range(batch.num_rows):
                if size > block and key[i] != now:
                    yield flush()
                    held, size = [], 0
                    common.give_back()
                now = key[i]
                held.append((c[i], rid[i], first[i], starts[i], data[i]))
                size += len(data[i])
        if held:
            yield flush()

    return strings.repartition("key").sortWithinPartitions("key").mapInArrow(common.trimmed(run), "rid long, a long, b long")


def _dealt_windows(strings: DataFrame, length: int) -> DataFrame:
    """The same spans for the runs of very large buckets, by counting 128-bit window hashes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            key, c, rid, first, starts, data = (batch.column(k).to_pylist() for k in range(6))
            for i in range(batch.num_rows):
                hashes = [hashlib.blake2b(data[i][k : k + length], digest_size=16).digest() for k in range(starts[i])]
                yield pa.RecordBatch.from_arrays([pa.array(hashes, pa.binary()), pa.array([rid[i]] * starts[i], pa.int64()), pa.array(range(first[i], first[i] + starts[i]), pa.int64()), pa.array([c[i]] * starts[i], pa.int64())], names=["h", "rid", "a", "c"])

    windows = strings.mapInArrow(common.trimmed(run), "h binary, rid long, a long, c long")
    again = windows.groupBy("h").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("h")
    return windows.where("c = 1").join(again, "h", "left_semi").select("rid", "a", (F.col("a") + length).alias("b"))


def repeated_spans(texts: DataFrame, length: int = 400, gram: int = 128, block: int = 1 << 20, most_runs: int = 20_000, longer: int | None = None, longer_gram: int = 128) -> tuple[DataFrame, DataFrame | None]:
    """rid, spans (array of a, b, not yet merged) of texts with repeated windows. ``texts``: rid, text.

    With ``longer`` also the spans of that greater length. A repeated window of it
    consists of repeated windows of ``length``, so only stretches that these can cover
    are searched, as texts of their own; their bytes leave with the runs' bytes.
    """
    runs = common.cut(_extract(texts, length, min(gram, length)))
    groups = _combined(runs).repartition("key").groupBy("key", "digest").agg(F.sum("c").alias("c"), F.min("rid").alias("rep"), F.max("inner").alias("inner"), F.min_by("place", "rid").alias("rep_place"))
    of_key = Window.partitionBy("key")
    told = groups.withColumn("nd", F.count(F.lit(1)).over(of_key)).withColumn("most", F.max("c").over(of_key)).withColumn("any_inner", F.max("inner").over(of_key))
    told = common.cut(told.where("nd > 1 or most > 1 or any_inner > 0").select("key", "digest", "c", "rep", "rep_place", "nd", "any_inner"))
    common.release(texts.sparkSession)
    flat = runs.select("rid", F.explode(F.arrays_zip("keys", "digests", "places")).alias("r")).select("rid", F.col("r.keys").alias("key"), F.col("r.digests").alias("digest"), F.col("r.places").alias("place"))
    need = F.expr("(nd > 1 or any_inner > 0) and rid = rep and place = rep_place")
    members = flat.join(told.select("key", "digest", "c", "rep", "rep_place", "nd", "any_inner"), ["key", "digest"]).select("rid", "place", "key", "c", need.alias("need"))
    if not longer:  # the bytes of the runs to be sorted are all that is asked for
        members = members.where("c > 1 or need")
    lists = common.cut(members.groupBy("rid").agg(F.collect_set(F.struct("place", "key", "c", "need")).alias("runs")))
    whole = lists.select("rid", F.explode("runs").alias("r")).where("r.c > 1").select("rid", F.shiftright("r.place", 32).alias("a"), (F.shiftright("r.place", 32) + F.shiftright(F.col("r.place").bitwiseAND(F.lit(0xFFFFFFFF)), 1) - 1 + length).alias("b"))
    asked = lists if longer else lists.where(F.exists("runs", lambda r: r["need"]))
    pieces, path = common.stored(_cut_out(texts.join(asked, "rid"), length, longer))
    strings = pieces.where("kind = 0").drop("kind")
    large = told.where(F.col("nd") > most_runs).select("key").distinct()
    if large.limit(1).count():
        parted = _sorted_buckets(strings.join(large, "key", "left_anti"), length, block).unionAll(_dealt_windows(strings.join(large, "key", "left_semi"), length))
    else:
        parted = _sorted_buckets(strings, length, block)
    found = common.cut(whole.unionAll(parted).groupBy("rid").agg(F.array_sort(F.collect_list(F.struct("a", "b"))).alias("spans")))
    common.forget(runs, told, lists)
    common.release(texts.sparkSession)
    far = None
    if longer:
        stretch = pieces.where("kind = 1").select(F.xxhash64("rid", "first").alias("sid"), "rid", "first", "data")
        inside, _ = repeated_spans(stretch.select(F.col("sid").alias("rid"), F.col("data").alias("text")), longer, longer_gram, block, most_runs)
        back = inside.join(stretch.select(F.col("sid"), F.col("rid").alias("own"), "first").distinct(), F.col("rid") == F.col("sid"))
        shifted = back.select(F.col("own").alias("rid"), F.explode("spans").alias("s"), "first").select("rid", (F.col("s.a") + F.col("first")).alias("a"), (F.col("s.b") + F.col("first")).alias("b"))
        far = common.cut(shifted.groupBy("rid").agg(F.array_sort(F.collect_list(F.struct("a", "b"))).alias("spans")))
        common.forget(inside)
    common.delete(texts.sparkSession, path)
    return found, far


def merged(spans: list[dict]) -> list[tuple[int, int]]:
    """Overlapping or touching spans, in order of a, as maximal runs."""
    out: list[list[int]] = []
    for s in spans:
        a, b = s["a"], s["b"]
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


def whole_characters(data: bytes, a: int, b: int) -> tuple[int, int]:
    """The part of [a, b) that cuts no UTF-8 character."""
    while a < b and data[a] & 0xC0 == 0x80:
        a += 1
    while b > a and b < len(data) and data[b] & 0xC0 == 0x80:
        b -= 1
    return a, b


def without(data: bytes, spans: list[dict] | None, as_text: bool) -> tuple[bytes, list[dict]]:
    """The bytes outside the spans, and the removed runs."""
    cuts = merged(spans or [])
    if as_text:
        cuts = [x for a, b in cuts if (x := whole_characters(data, a, b))[0] < x[1]]
    at, parts = 0, []
    for a, b in cuts:
        parts.append(data[at:a])
        at = b
    parts.append(data[at:])
    return b"".join(parts), [{"a": a, "b": b} for a, b in cuts]


def remove_repeats(docs: DataFrame, length: int = 400, keep: list[str] | None = None, as_text: bool = False, passage: int | None = None, **kw) -> DataFrame:
    """Kept columns of ``docs`` and n_bytes, removed (maximal runs: a, b) and kept_bytes.

    ``as_text`` leaves a character that a removed run cuts whole, so that the kept
    bytes are UTF-8. ``passage``, a length below the other, adds passages_cut: the text
    without the strings of that length that repeat.
    """
    common.tune(docs.sparkSession)
    keep = docs.columns if keep is None else keep
    key = F.xxhash64(F.col("doc_id").cast("string") if "doc_id" in docs.columns else F.lit(0), common.text_of(), F.octet_length(common.text_of()))
    texts = docs.select(key.alias("rid"), common.text_of().alias("text"))
    short, spans = repeated_spans(texts, passage, longer=length, **kw) if passage else (None, repeated_spans(texts, length, **kw)[0])
    frame = common.packed(docs, keep, rid=key, text=common.text_of()).join(spans, "rid", "left")
    if passage:
        frame = frame.join(short.withColumnRenamed("spans", "short"), "rid", "left")
    frame = frame.select("kept", "text", "spans", *(["short"] if passage else []))
    added = "n_bytes long, removed array<struct<a:long,b:long>>, kept_bytes binary" + ", passages_cut string" * bool(passage)
    schema = T.StructType([frame.schema["kept"], *T.StructType.fromDDL(added).fields])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = common.byte_list(batch.column(1))
            pairs = [without(t, s, as_text) for t, s in zip(texts, batch.column(2).to_pylist())]
            removed = pa.array([p[1] for p in pairs], pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64())])))
            more = [pa.array([len(t) for t in texts], pa.int64()), removed, pa.array([p[0] for p in pairs], pa.binary())]
            if passage:
                more.append(pa.array([without(t, s, True)[0].decode() for t, s in zip(texts, batch.column(3).to_pylist())], pa.string()))
            yield pa.RecordBatch.from_arrays([batch.column(0), *more], names=schema.names)

    out = frame.mapInArrow(common.trimmed(run), schema)
    return common.unpacked(out, keep, **{c: F.col(c) for c in schema.names[1:]})


#: Bytes of a string that counts as a passage: about 40 words of prose.
PASSAGE, PASSAGE_GRAM = 240, 48


def removal_digests(docs: DataFrame, length: int = 400, passage: int = PASSAGE) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256, and text: what is left without passages of ``passage`` bytes.

    Passages of over 50 words can be shorter than ``length`` bytes; ``text`` lacks those too.
    """
    out = remove_repeats(docs, length, keep=["doc_id"], passage=passage, gram=PASSAGE_GRAM)
    return out.select(
        "doc_id",
        "n_bytes",
        (F.col("n_bytes") - F.octet_length("kept_bytes")).alias("n_removed"),
        F.size("removed").cast("long").alias("n_spans"),
        F.sha2("kept_bytes", 256).alias("kept_sha256"),
        F.col("passages_cut").alias("text"),
    )
