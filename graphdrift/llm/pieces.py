"""SentencePiece BPE encoding and decoding through a table of distinct chunks.

The model's pieces carry the whitespace mark only at their front, so no merge can
join characters across the boundary between an unmarked character and a mark.
A text therefore falls into independent chunks (a run of marks and what follows
it). The loader verifies the property on the given model and refuses models
(user-defined pieces, marks inside pieces, normalisation tables) for which chunks
would not be independent.

1. Texts are gathered into blocks. A block numbers its distinct chunks, and a text
   becomes the list of its chunks' numbers, in order of position.
2. The blocks' chunks are dealt into buckets by a hash of their bytes, so that every
   distinct chunk of the table comes to one bucket, is segmented there once, and
   answers all blocks that hold it. Segmentation merges all chunks of a bucket side by
   side, the best and leftmost pair of each chunk a round.
3. The answers go back to their blocks, where a text's ids are its chunks' ids put
   in a row by position.

What travels are chunks and ids, compressed by block and bucket. Texts don't, nor do
their numbers: they are written once, bucketed by block, and the answers come to them.
That table stays until ``release`` (the result reads it).

Defined results: null text is empty; an empty text has no ids and decodes to the
empty string; texts of any length, ties and repeated rows are encoded row by row;
an empty table gives an empty result; other columns pass through, one with an added
column's name as ``input_<name>``.
"""

from __future__ import annotations

import heapq
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from graphdrift.llm import common

MARK = "▁"
_CHUNK = re.compile(f"{MARK}+[^{MARK}]*")
#: Characters up to which chunks are merged side by side; longer ones go through a heap.
LONG = 48


def default_model() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def chunks_of(text: str, slice_: int = 1 << 20) -> Iterator[list[str]]:
    """The chunks of a text in order, a slice of it at a time."""
    text = MARK + text.replace(" ", MARK)
    at = 0
    while at < len(text):
        end = at + slice_
        if end < len(text):
            end = text.find(MARK, end)
            while end > 0 and text[end - 1] == MARK:  # not inside a run of marks
                end = text.find(MARK, end + 1)
        if end < 0 or end >= len(text):
            end = len(text)
        yield _CHUNK.findall(text, at, end)
        at = end


class Segmenter:
    """Pieces, their scores and merges; segmentation of chunks and surface text of ids."""

    def __init__(self, model: str):
        import sentencepiece

        self.sp = sp = sentencepiece.SentencePieceProcessor(model_file=model)
        self.ids: dict[str, int] = {}
        self.bytes = [0] * 256
        self.surface: list[str | int] = []
        for i in range(sp.get_piece_size()):
            piece = sp.id_to_piece(i)
            if sp.is_control(i):
                self.surface.append("")
            elif sp.is_byte(i):
                self.surface.append(int(piece[3:-1], 16))
                self.bytes[self.surface[-1]] = i
            elif sp.is_unknown(i):
                self.surface.append(" ⁇ ")
            else:
                if MARK in piece.lstrip(MARK):
                    raise ValueError(f"piece {piece!r} crosses a whitespace mark")
                self.surface.append(piece.replace(MARK, " "))
                self.ids[piece] = i
        probe = "ﬁ　x"
        if sp.decode(sp.encode(probe)) != probe or sp.decode(sp.encode("  a  b ")) != "  a  b " or not all(self.bytes):
            raise ValueError("the model normalises text or lacks byte pieces; chunks would not be independent")
        self.score = np.array([sp.get_score(i) for i in range(sp.get_piece_size())])
        # every way to put a piece together from two others, as a sorted table
        pairs = [(self.ids[p[:k]], self.ids[p[k:]], i) for p, i in self.ids.items() for k in range(1, len(p)) if p[:k] in self.ids and p[k:] in self.ids]
        keys = np.array([(a << 32) | b for a, b, _ in pairs], np.int64)
        order = np.argsort(keys)
        self.keys, self.made = keys[order], np.array([c for *_, c in pairs], np.int64)[order]
        self.symbol = -1 - np.arange(0x110000)  # by code point; negative: no piece
        for c, i in self.ids.items():
            if len(c) == 1:
                self.symbol[ord(c)] = i

    def _merged(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """The piece that each pair of symbols makes, or -1. Symbols that are no piece are negative."""
        key = (left << 32) | right
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.where((self.keys[at] == key) & (left >= 0) & (right >= 0), self.made[at], -1)

    def segment(self, chunks: list[str]) -> list[list[int]]:
        """Ids of every chunk."""
        out: list[list[int]] = [[]] * len(chunks)
        short = [i for i, c in enumerate(chunks) if len(c) <= LONG]
        for k in range(0, len(short), 20_000):
            part = short[k : k + 20_000]
            for i, ids in zip(part, self._side_by_side([chunks[i] for i in part])):
                out[i] = ids
        for i, c in enumerate(chunks):
            if len(c) > LONG:
                out[i] = self._one(c)
        return out

    def _side_by_side(self, chunks: list[str]) -> list[list[int]]:
        sizes = np.array([len(c) for c in chunks])
        flat = self.symbol[np.frombuffer("".join(chunks).encode("utf-32-le"), np.uint32)]
        owner = np.repeat(np.arange(len(chunks)), sizes)
        done_symbols, done_owner = [], []
        while len(flat):
            made = np.full(len(flat), -1)
            made[:-1] = np.where(owner[1:] == owner[:-1], self._merged(flat[:-1], flat[1:]), -1)
            value = np.where(made >= 0, self.score[made], -np.inf)
            heads = np.flatnonzero(np.concatenate([[True], owner[1:] != owner[:-1]]))
            best = np.maximum.reduceat(value, heads)
            lengths = np.diff(np.append(heads, len(flat)))
            top = np.repeat(best, lengths)
            where = np.where((value == top) & (made >= 0), np.arange(len(flat)), len(flat))
            first = np.minimum.reduceat(where, heads)
            live = first < len(flat)
            keep = np.repeat(live, lengths)
            done_symbols.append(flat[~keep])
            done_owner.append(owner[~keep])
            at = first[live]
            flat[at] = made[at]
            keep[at + 1] = False
            flat, owner = flat[keep], owner[keep]
        symbols, owner = np.concatenate(done_symbols), np.concatenate(done_owner)
        order = np.argsort(owner, kind="stable")
        symbols = symbols[order].tolist()
        ends = np.cumsum(np.bincount(owner, minlength=len(chunks))).tolist()
        return [self._spelt(symbols[a:b]) for a, b in zip([0, *ends[:-1]], ends)]

    def _spelt(self, symbols: list[int]) -> list[int]:
        """Symbols with characters that are no piece as bytes."""
        if min(symbols) >= 0:
            return symbols
        out = []
        for s in symbols:
            if s >= 0:
                out.append(s)
            else:
                out += [self.bytes[b] for b in chr(-1 - s).encode()]
        return out

    def _one(self, chunk: str) -> list[int]:
        """Ids of one chunk of any length, by a heap of pairs."""
        parts: list[str] = list(chunk)
        before, after = list(range(-1, len(parts) - 1)), [*range(1, len(parts)), -1]
        heap: list[tuple[float, int, int, str]] = []

        def offer(a: int, b: int) -> None:
            if a >= 0 and b >= 0:
                i = self.ids.get(parts[a] + parts[b])
                if i is not None:
                    heapq.heappush(heap, (-self.score[i], a, b, parts[a] + parts[b]))

        for k in range(1, len(parts)):
            offer(k - 1, k)
        while heap:
            _, a, b, whole = heapq.heappop(heap)
            if not parts[a] or not parts[b] or after[a] != b or parts[a] + parts[b] != whole:
                continue
            parts[a], parts[b] = whole, ""
            after[a] = after[b]
            if after[a] >= 0:
                before[after[a]] = a
            offer(before[a], a)
            offer(a, after[a])
        return self._spelt([self.ids.get(p, -1 - ord(p)) if len(p) == 1 else self.ids[p] for p in parts if p])

    def plain(self, ids) -> str:
        """Surface text of ids, byte pieces joined into characters."""
        out, run = [], bytearray()
        for i in ids:
            s = self.surface[i]
            if isinstance(s, int):
                run.append(s)
                continue
            if run:
                out.append(run.decode("utf-8", "replace"))
                run.clear()
            out.append(s)
        if run:
            out.append(run.decode("utf-8", "replace"))
        return "".join(out)

    def decode(self, ids) -> str:
        """Text of a whole id sequence: the mark put before the text goes."""
        return self.plain(ids).removeprefix(" ")


class ChunkTable(Segmenter):
    """A task's own table, for uses that need ids at once (flat token files).

    It holds up to ``most`` chunks and is emptied beyond; chunks above ``longest``
    characters aren't held. The library segments what a task's table lacks.
    """

    def __init__(self, model: str, most: int = 300_000, longest: int = 64):
        super().__init__(model)
        self.most, self.longest = most, longest
        self.known: dict[str, bytes] = {}

    def encode_all(self, texts: list[str]) -> list[bytes]:
        """Packed ids (int32) of each text."""
        out = []
        for text in texts:
            parts = []
            for chunks in chunks_of(text) if text else ():
                new = list({c for c in chunks if c not in self.known})
                if len(self.known) + len(new) > self.most:
                    self.known.clear()
                    new = list(set(chunks))
                # the library puts a mark before any text but the empty one
                coded = self.sp.encode([c[1:].replace(MARK, " ") for c in new], num_threads=1)
                told = {c: np.asarray(ids if c != MARK else [self.ids[MARK]], "<i4").tobytes() for c, ids in zip(new, coded)}
                self.known |= {c: x for c, x in told.items() if len(c) <= self.longest}
                parts += [self.known.get(c) or told[c] for c in chunks]
            out.append(b"".join(parts))
        return out


class _Numbers(dict):
    """Numbers of a block's chunks by first sight."""

    def __missing__(self, chunk: str) -> int:
        n = self[chunk] = len(self)
        return n


def _squeeze(x: np.ndarray | bytes) -> bytes:
    """Compressed bytes, or numbers below 2^32 plane by plane."""
    if isinstance(x, np.ndarray):
        x = np.ascontiguousarray(x.astype("<u4").view(np.uint8).reshape(-1, 4).T).tobytes()
    return zstandard.ZstdCompressor(level=3).compress(x)


def _bytes(data: bytes) -> bytes:
    return zstandard.ZstdDecompressor().decompress(data)


def _array(data: bytes) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(_bytes(data), np.uint8).reshape(4, -1).T).view("<u4").reshape(-1)


def _cut_up(sizes: np.ndarray, data: bytes) -> list[bytes]:
    ends = np.cumsum(sizes).tolist()
    return [data[a:b] for a, b in zip([0, *ends[:-1]], ends)]


#: Beside the kept columns: a text's row has ``at``, a block's chunks are ``sizes`` and ``data``.
_ROW = "part int, seq int, at binary, sizes binary, data binary"


def _numbered(frame: DataFrame, block: int) -> DataFrame:
    """Texts as chunk numbers by block, and each block's chunks. ``frame``: kept, text."""
    schema = T.StructType([T.StructField("kept", frame.schema["kept"].dataType), *T.StructType.fromDDL(_ROW).fields])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, seq, held, numbers = TaskContext.get().partitionId(), 0, 0, _Numbers()
        none = None
        kinds = [pa.int32(), pa.int32(), *[pa.binary()] * 3]

        def chunks() -> pa.RecordBatch:
            words = [c.encode() for c in numbers]
            cells = [part, seq, None, _squeeze(np.array([len(w) for w in words], "<u4")), _squeeze(b"".join(words))]
            return pa.RecordBatch.from_arrays([none, *[pa.array([c], f) for c, f in zip(cells, kinds)]], names=schema.names)

        for batch in batches:
            none = pa.nulls(1, batch.column(0).type)
            rows: list[tuple[int, int, bytes]] = []
            begun = 0
            for i, text in enumerate(batch.column(1).to_pylist()):
                at = [x for c in chunks_of(text) for x in map(numbers.__getitem__, c)] if text else []
                rows.append((part, seq, _squeeze(np.array(at, "<u4"))))
                held += len(text)
                if held >= block or i == batch.num_rows - 1:
                    columns = [pa.array([r[k] for r in rows], kinds[k]) for k in range(3)]
                    yield pa.RecordBatch.from_arrays([batch.column(0).slice(begun, len(rows)), *columns, *[pa.nulls(len(rows), pa.binary())] * 2], names=schema.names)
                    begun, rows = i + 1, []
                if held >= block:
                    yield chunks()
                    seq, held, numbers = seq + 1, 0, _Numbers()
        if numbers:
            yield chunks()

    return frame.mapInArrow(common.trimmed(run), schema)


def _dealt(lists: DataFrame, buckets: int) -> DataFrame:
    """Each block's chunks by bucket: bucket, part, seq, steps (of their numbers), sizes, data."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, seq, sizes, data in zip(*(batch.column(k).to_pylist() for k in range(4))):
                sizes = _array(sizes)
                words = _cut_up(sizes, _bytes(data))
                bucket = np.fromiter(map(zlib.crc32, words), np.uint32, len(words)) % buckets
                order = np.argsort(bucket, kind="stable")
                rows = []
                for x in np.split(order, np.flatnonzero(np.diff(bucket[order])) + 1) if len(order) else ():
                    rows.append((int(bucket[x[0]]), part, seq, _squeeze(np.diff(x, prepend=0)), _squeeze(sizes[x]), _squeeze(b"".join([words[i] for i in x.tolist()]))))
                kinds = [pa.int32()] * 3 + [pa.binary()] * 3
                yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], kind) for k, kind in enumerate(kinds)], names=["bucket", "part", "seq", "steps", "sizes", "data"])

    return lists.select("part", "seq", "sizes", "data").mapInArrow(common.trimmed(run), "bucket int, part int, seq int, steps binary, sizes binary, data binary")


def _answers(dealt: DataFrame, model: str) -> DataFrame:
    """part, seq, steps, counts, ids of each block's chunks by bucket. Each distinct chunk is segmented once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = Segmenter(model)
        known: dict[bytes, list[int]] = {}
        now = None
        for batch in batches:
            for bucket, part, seq, steps, sizes, data in zip(*(batch.column(k).to_pylist() for k in range(6))):
                if bucket != now:
                    now = bucket
                    known.clear()
                words = _cut_up(_array(sizes), _bytes(data))
                new = [w for w in words if w not in known]
                known |= zip(new, table.segment([w.decode() for w in new]))
                found = [known[w] for w in words]
                cells = [part, seq, steps, _squeeze(np.array([len(f) for f in found], "<u4")), _squeeze(np.array([i for f in found for i in f], "<u4"))]
                kinds = [pa.int32(), pa.int32(), *[pa.binary()] * 3]
                yield pa.RecordBatch.from_arrays([pa.array([c], kind) for c, kind in zip(cells, kinds)], names=["part", "seq", "steps", "counts", "ids"])

    near = dealt.repartition("bucket").sortWithinPartitions("bucket")
    return near.mapInArrow(common.trimmed(run), "part int, seq int, steps binary, counts binary, ids binary")


def _joined(texts: DataFrame, answers: DataFrame, model: str, schema: T.StructType) -> DataFrame:
    """Texts' ids and surface by position, block by block. ``texts``: part, seq, kept, at; ``answers``: part, seq, steps, counts, ids."""
    tables: dict[str, Segmenter] = {}

    def run(texts: pa.Table, told: pa.Table) -> pa.Table:
        if model not in tables:
            tables[model] = Segmenter(model)
        table = tables[model]
        texts, parts = texts.combine_chunks(), [tuple(map(_array, x)) for x in zip(*(told.column(k).to_pylist() for k in ("steps", "counts", "ids")))]
        numbers = [np.cumsum(p[0]) for p in parts]
        size = 1 + max((int(n[-1]) for n in numbers), default=-1)
        count, start, base = np.zeros(size, np.int64), np.zeros(size, np.int64), 0
        words = [""] * size
        for n, (_, c, ids) in zip(numbers, parts):
            count[n] = c
            ends = np.cumsum(c.astype(np.int64))
            start[n] = base + ends - c
            base += len(ids)
            ids, ends = ids.tolist(), ends.tolist()
            for k, a, b in zip(n.tolist(), [0, *ends[:-1]], ends):
                words[k] = table.plain(ids[a:b])
        flat = np.concatenate([p[2] for p in parts]).astype(np.int32) if parts else np.zeros(0, np.int32)
        lists, plain = [], []
        for at in texts.column("at").to_pylist():
            order = _array(at)
            n = count[order]
            total = int(n.sum())
            lists.append(flat[np.repeat(start[order] - (np.cumsum(n) - n), n) + np.arange(total)] if total else flat[:0])
            plain.append("".join([words[k] for k in order.tolist()])[1:])
        ends = np.cumsum([0, *[len(x) for x in lists]]).astype(np.int32)
        found = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(lists), pa.int32()))
        kept = texts.column("kept")
        return pa.table([kept, found, pa.array(plain, pa.string())], names=schema.names)

    return texts.groupBy("part", "seq").cogroup(answers.groupBy("part", "seq")).applyInArrow(run, schema)


_tables: list[str] = []


def release(spark) -> None:
    """Drop the tables that results of ``encode_documents`` read; for when those are written."""
    while _tables:
        common.drop(spark, _tables.pop())


def encode_documents(docs: DataFrame, text: str = "text", keep: list[str] | None = None, model: str | None = None, ids: str = "piece_ids", decoded: str = "piece_text", block: int = 1 << 24, bucket_chunks: int = 200_000) -> DataFrame:
    """Add ``ids`` (array of int) and ``decoded`` (their text) to the kept columns of ``docs``.

    A block has about ``block`` characters, and a task of the segmentation buckets with
    about ``bucket_chunks`` chunks each, however large the table.
    """
    common.tune(docs.sparkSession)
    spark = docs.sparkSession
    model = model or default_model()
    keep = docs.columns if keep is None else keep
    tasks = int(spark.conf.get("spark.sql.shuffle.partitions"))
    # the numbering is written down, so that every later reader sees the same blocks
    blocks, name = common.bucketed(_numbered(common.packed(docs, keep, text=common.text_of(text)), block), tasks, "part", "seq")
    _tables.append(name)
    lists = blocks.where("at is null").select("part", "seq", "sizes", "data")
    size = lists.agg(F.sum(F.octet_length("data"))).first()[0] or 0  # three bytes a chunk or more when compressed
    told = _answers(_dealt(lists, max(tasks, size // (3 * bucket_chunks) + 1)), model)
    texts = blocks.where("at is not null").select("part", "seq", "kept", "at")
    fields = [T.StructField("kept", blocks.schema["kept"].dataType), T.StructField("ids", T.ArrayType(T.IntegerType())), T.StructField("plain", T.StringType())]
    out = _joined(texts, told, model, T.StructType(fields))
    return common.unpacked(out, keep, **{ids: F.col("ids"), decoded: F.col("plain")})


def decode_ids(frame: DataFrame, ids: str = "piece_ids", decoded: str = "piece_text", model: str | None = None) -> DataFrame:
    """Add the text of an id column; null ids give null."""
    common.tune(frame.sparkSession)
    model = model or default_model()
    keep = frame.columns
    rows = common.packed(frame, keep, ids=F.col(f"`{ids}`"))
    schema = T.StructType([rows.schema["kept"], T.StructField("plain", T.StringType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = Segmenter(model)
        for batch in batches:
            texts = [None if x is None else table.decode(x) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], names=schema.names)

    return common.unpacked(rows.mapInArrow(common.trimmed(run), schema), keep, **{decoded: F.col("plain")})


def piece_digests(docs: DataFrame, model: str | None = None) -> DataFrame:
    """doc_id, n_tokens, ids_sha256 and decoded_sha256 of every row."""
    coded = encode_documents(docs, keep=["doc_id"], model=model)
    return coded.select(
        "doc_id",
        F.size("piece_ids").cast("long").alias("n_tokens"),
        F.sha2(F.concat_ws(",", F.col("piece_ids").cast("array<string>")).cast("binary"), 256).alias("ids_sha256"),
        F.sha2(F.col("piece_text").cast("binary"), 256).alias("decoded_sha256"),
    )
