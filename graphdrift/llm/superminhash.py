"""Near-duplicate groups by SuperMinHash signatures, bands, verification and union-find.

1. Every text becomes its set of distinct word shingles (64-bit hashes). Rows with
   equal sets form a class (128-bit digest), so copies are never paired.
2. A class gets a SuperMinHash signature: each element deals one random
   permutation of the slots, its j-th slot receiving j + a random fraction, and a
   slot keeps its least value. Elements are dealt side by side, one permutation
   step at a time; once every slot of a text is filled no later step can lower a
   value and the text stops early.
3. Bands of the signature are hashed; classes that share a band are candidates. A
   bucket of any size is not paired out: its most central class (the one whose
   own buckets are the fullest) is the centre, and every other member is verified
   against it on full sets.
4. Verified links are grouped by union-find (within tasks, then by rounds of
   star contraction over the whole set of links).
5. What the centres leave open are members around one centre that still carry
   different labels. They are compared exactly among themselves, in blocks of
   bounded size, by counting common shingles; members whose shingles are found
   nowhere else in the block to too large a share are passed over, since no link
   is possible for them. Only links leave the block.

Defined results: null text is empty; a text without words has an empty set and is
linked with nothing; one with fewer words than a shingle is one element; rows that
repeat an id with different texts count as linked; a row without an id takes no
part in links (its component is null and it is kept); an empty table gives an
empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphdrift.llm import common

SLOTS, BANDS = 128, 32
#: Members of a centre that one task compares with it.
SPOKES = 256
_ODD = np.uint64(0x9E3779B97F4A7C15)
_MIX1, _MIX2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def scramble(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (bijective)."""
    x = (x ^ (x >> np.uint64(30))) * _MIX1
    x = (x ^ (x >> np.uint64(27))) * _MIX2
    return x ^ (x >> np.uint64(31))


class Words(dict):
    """64-bit hashes of words seen by a task; emptied when it holds too many."""

    def __missing__(self, word: bytes) -> int:
        if len(self) > 500_000:
            self.clear()
        h = int.from_bytes(hashlib.blake2b(word, digest_size=8).digest(), "little")
        if len(word) <= 64:
            self[word] = h
        return h


def shingle_set(text: bytes, width: int, words: Words) -> np.ndarray:
    """Sorted distinct shingle hashes. bytes.lower and bytes.split treat just A-Z, space and 9-13."""
    found = text.lower().split()
    n = len(found)
    if not n:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(words.__getitem__, found), np.uint64, n)
    span = min(n, width)
    out = h[: n - span + 1].copy()
    for k in range(1, span):
        out = out * _ODD + scramble(h[k : n - span + 1 + k])
    return np.unique(scramble(out + np.uint64(span)))


def superminhash(values: np.ndarray, starts: np.ndarray, slots: int = SLOTS) -> np.ndarray:
    """Signatures (uint32, steps in the high bits) of sets laid end to end; no set may be empty."""
    sets = len(starts) - 1
    out = np.full((sets, slots), np.iinfo(np.uint32).max, np.uint32)
    flat, owner = out.reshape(-1), np.repeat(np.arange(sets), np.diff(starts))
    order = np.tile(np.arange(slots, dtype=np.uint8 if slots <= 256 else np.uint16), (len(values), 1))
    live = np.arange(len(values))
    for j in range(slots):
        if not len(live):
            break
        r = scramble(values[live] + np.uint64((j + 1) * int(_ODD) & 0xFFFFFFFFFFFFFFFF))
        k = j + (((r & np.uint64(0xFFFFFFFF)) * np.uint64(slots - j)) >> np.uint64(32)).astype(np.int64)
        slot = order[live, k]
        order[live, k] = order[live, j]
        order[live, j] = slot
        value = (np.uint64(j) << np.uint64(24)) | (r >> np.uint64(40))
        np.minimum.at(flat, owner[live] * slots + slot, value.astype(np.uint32))
        if j < 4 or j % 4 == 3:
            done = out.max(axis=1) < ((j + 1) << 24)
            live = live[~done[owner[live]]]
    return out


def signatures(sets: list[np.ndarray], slots: int = SLOTS, block: int = 150_000) -> np.ndarray:
    """Signatures of non-empty sets, at most ``block`` elements at once; parts of a large set merge by minimum."""
    parts = [(i, s[k : k + block]) for i, s in enumerate(sets) for k in range(0, len(s), block)]
    out = np.full((len(sets), slots), np.iinfo(np.uint32).max, np.uint32)
    at = 0
    while at < len(parts):
        end, held = at, 0
        while end < len(parts) and (end == at or held + len(parts[end][1]) <= block):
            held += len(parts[end][1])
            end += 1
        starts = np.zeros(end - at + 1, np.int64)
        np.cumsum([len(p) for _, p in parts[at:end]], out=starts[1:])
        got = superminhash(np.concatenate([p for _, p in parts[at:end]]), starts, slots)
        np.minimum.at(out, np.array([i for i, _ in parts[at:end]]), got)
        at = end
    return out


def band_hashes(signature: np.ndarray, bands: int = BANDS) -> np.ndarray:
    """One 64-bit hash for each band of each signature."""
    rows = signature.astype(np.uint64).reshape(len(signature), bands, -1)
    h = np.broadcast_to(np.arange(bands, dtype=np.uint64) * _MIX1, rows.shape[:2]).copy()
    for k in range(rows.shape[2]):
        h = scramble(h * _ODD + rows[:, :, k])
    return h.view(np.int64)


def _profiles(docs: DataFrame, width: int, slots: int, bands: int) -> DataFrame:
    """doc_id, n, digest (128 bits of the set), bands."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = Words()
        for batch in batches:
            sets = [shingle_set(t, width, words) for t in common.byte_list(batch.column(1))]
            full = [i for i, s in enumerate(sets) if len(s)]
            hashes: list = [None] * len(sets)
            if full:
                for i, row in zip(full, band_hashes(signatures([sets[i] for i in full], slots), bands)):
                    hashes[i] = row
            digests = [hashlib.blake2b(s.tobytes(), digest_size=16).digest() for s in sets]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(s) for s in sets], pa.int64()), pa.array(digests, pa.binary()), pa.array(hashes, pa.list_(pa.int64()))], names=["doc_id", "n", "digest", "bands"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), common.text_of().alias("text")).mapInArrow(common.trimmed(run), "doc_id long, n long, digest binary, bands array<long>")


def _sets(docs: DataFrame, width: int) -> DataFrame:
    """node, elements of the given documents."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = Words()
        for batch in batches:
            sets = [shingle_set(t, width, words).view(np.int64) for t in common.byte_list(batch.column(1))]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sets, pa.list_(pa.int64()))], names=["node", "elements"])

    return docs.select("doc_id", "text").mapInArrow(common.trimmed(run), "node long, elements array<long>")


def forest(links: DataFrame) -> DataFrame:
    """Union-find inside each task: links become (node, root) with root < node."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        up: dict[int, int] = {}

        def find(x: int) -> int:
            root = x
            while (p := up.get(root, root)) != root:
                root = p
            while (p := up.get(x, x)) != root:
                up[x] = root
                x = p
            return root

        for batch in batches:
            for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                ra, rb = find(a), find(b)
                if ra != rb:
                    up[max(ra, rb)] = min(ra, rb)
        nodes = [x for x in up if find(x) != x]
        for k in range(0, len(nodes), 10_000):
            part = nodes[k : k + 10_000]
            yield pa.RecordBatch.from_arrays([pa.array(part, pa.int64()), pa.array([find(x) for x in part], pa.int64())], names=["node", "root"])

    return links.mapInArrow(common.trimmed(run), "node long, root long")


def components(links: DataFrame) -> DataFrame:
    """(node, root) for every node that has a link and isn't its component's least node."""
    edges = common.cut(forest(links).distinct())
    seen = None
    while True:
        state = edges.agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("node", "root").cast("decimal(20,0)")).alias("h")).first()
        if state == seen or not state["n"]:
            return edges
        seen = state
        both = edges.unionAll(edges.select(F.col("root").alias("node"), F.col("node").alias("root")))
        least = both.groupBy("node").agg(F.min("root").alias("m")).select("node", F.least("node", "m").alias("m"))
        large = both.join(least, "node").where("root > node").select(F.col("root").alias("node"), F.col("m").alias("root")).distinct()
        m = large.groupBy("node").agg(F.min("root").alias("m"))
        small = large.join(m, "node").select(F.explode(F.array(F.struct(F.col("root").alias("node"), F.col("m").alias("root")), F.struct(F.col("node"), F.col("m").alias("root")))).alias("e"))
        edges = common.cut(small.select("e.*").where("node <> root").distinct())


def linked_pairs(block: list[tuple[int, int, np.ndarray]], percent: int) -> list[tuple[int, int]]:
    """Links between members with different labels. A member: node, label, elements."""
    if len({x[1] for x in block}) < 2:
        return []
    lengths = np.array([len(x[2]) for x in block])
    ids, inverse, held = np.unique(np.concatenate([x[2] for x in block]), return_inverse=True, return_counts=True)
    starts = np.concatenate([[0], np.cumsum(lengths)[:-1]])
    common_part = np.add.reduceat((held[inverse] > 1).astype(np.int64), starts)
    hopeful = np.flatnonzero(100 * common_part >= percent * lengths)
    # the most frequent label needs no turn of its own as a probe: every open pair has a member outside it
    label = np.unique([x[1] for x in block], return_inverse=True)[1]
    if len(hopeful) < 2:
        return []
    most = np.bincount(label[hopeful]).argmax()
    keep = np.concatenate([inverse[s : s + n] for s, n in zip(starts[hopeful], lengths[hopeful])])
    cuts = np.concatenate([[0], np.cumsum(lengths[hopeful])[:-1]])
    mark, found = np.zeros(len(ids), np.int64), []
    for p, i in enumerate(hopeful):
        if label[i] == most:
            continue
        own = keep[cuts[p] : cuts[p] + lengths[i]]
        mark[own] = 1
        shared = np.add.reduceat(mark[keep], cuts)
        mark[own] = 0
        hit = (100 * shared >= percent * (lengths[i] + lengths[hopeful] - shared)) & (label[hopeful] != label[i])
        found += [(block[i][0], block[q][0]) for q in hopeful[hit]]
    return found


def _block_links(rows: DataFrame, percent: int) -> DataFrame:
    """Links inside blocks; ``rows``: centre, block, node, label, elements. A block's rows stand together."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, block = None, []

        def flush() -> pa.RecordBatch:
            pairs = linked_pairs(block, percent)
            return pa.RecordBatch.from_arrays([pa.array([p[k] for p in pairs], pa.int64()) for k in (0, 1)], names=["node", "other"])

        for batch in batches:
            centre, part, node, label = (batch.column(k).to_pylist() for k in range(4))
            lists = batch.column(4)
            ends, flat = lists.offsets.to_numpy(), lists.values.to_numpy()
            for i in range(batch.num_rows):
                if (centre[i], part[i]) != now:
                    if block:
                        yield flush()
                    now, block = (centre[i], part[i]), []
                block.append((node[i], label[i], flat[ends[i] : ends[i + 1]].copy()))
        if block:
            yield flush()

    cols = ["centre", "block", "node", "label", "elements"]
    return rows.select(*cols).repartition("centre", "block").sortWithinPartitions("centre", "block").mapInArrow(common.trimmed(run), "node long, other long")


def near_duplicates(docs: DataFrame, percent: int = 80, width: int = 5, slots: int = SLOTS, bands: int = BANDS, block: int = 2000) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every row; links have 100 * common >= percent * united."""
    common.tune(docs.sparkSession)
    seen = common.cut(_profiles(docs, width, slots, bands))
    named = seen.where("n > 0 and doc_id is not null")
    classes = common.cut(named.groupBy("digest").agg(F.min(F.struct("doc_id", "n", "bands")).alias("r")).select("digest", F.col("r.doc_id").alias("node"), "r.n", "r.bands"))
    rows = classes.select("node", F.explode("bands").alias("key"))
    full = rows.groupBy("key").agg(F.count(F.lit(1)).alias("held")).where("held > 1")
    members = common.cut(rows.join(full, "key"))
    score = members.groupBy("node").agg(F.sum("held").alias("score"))
    members = members.join(score, "node")
    centres = members.groupBy("key").agg(F.max(F.struct("score", F.negative("node").alias("minus"))).alias("c")).select("key", F.negative("c.minus").alias("centre"))
    pairs = common.cut(members.select("key", "node").join(centres, "key").where("node <> centre").select("node", "centre").distinct())
    wanted = pairs.select("node").unionAll(pairs.select(F.col("centre").alias("node"))).distinct()
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), common.text_of().alias("text"))
    sets = common.cut(_sets(texts.join(wanted, texts.doc_id == wanted.node, "left_semi"), width).dropDuplicates(["node"]))
    # a centre of many members is given out again for every SPOKES of them, so that no task gets them all
    salts = pairs.groupBy("centre").agg(F.expr(f"(count(1) - 1) div {SPOKES} + 1").alias("salts"))
    cores = sets.select(F.col("node").alias("centre"), F.col("elements").alias("core")).join(salts, "centre").select("centre", "core", F.explode(F.sequence(F.lit(0), F.col("salts").cast("int") - 1)).alias("salt"))
    dealt = pairs.join(salts, "centre").select("node", "centre", F.pmod(F.xxhash64("node"), F.col("salts")).cast("int").alias("salt"))
    probe = dealt.join(sets, "node").join(cores, ["centre", "salt"])
    both = F.size(F.array_intersect("elements", "core"))
    checked = probe.select("node", "centre", both.alias("both"), (F.size("elements") + F.size("core")).alias("sum"))
    checked = common.cut(checked.select("node", "centre", F.expr(f"100 * both >= {percent} * (sum - both)").alias("linked")))
    links = checked.where("linked").select("node", F.col("centre").alias("other"))
    # classes whose first rows bear the same id are one node by definition; what stays open:
    roots = components(links)
    spokes = checked.select("centre", "node").unionAll(checked.select("centre", F.col("centre").alias("node"))).distinct()
    labelled = spokes.join(roots, "node", "left").select("centre", "node", F.coalesce("root", "node").alias("label"))
    groups = labelled.groupBy("centre").agg(F.count(F.lit(1)).alias("g"), F.min("label").alias("a"), F.max("label").alias("b")).where("g > 2 and a <> b").select("centre", "g")
    open_rows = labelled.join(groups, "centre").withColumn("parts", F.expr(f"cast((g + {block - 1}) div {block} as int)")).withColumn("own", F.pmod(F.xxhash64("node"), F.col("parts")).cast("int"))
    # a large group goes out as pairs of its chunks, each pair a block
    blocks = F.explode(F.transform(F.sequence(F.lit(0), F.col("parts") - 1), lambda q: (F.least(F.col("own"), q).cast("long") * F.col("parts") + F.greatest(F.col("own"), q))))
    open_rows = open_rows.select("centre", "node", "label", blocks.alias("block"))
    more = common.cut(_block_links(open_rows.join(sets, "node"), percent).distinct())
    if more.limit(1).count():
        roots = components(links.unionAll(more))
    label = classes.select("digest", "node").join(roots, "node", "left").select("digest", F.coalesce("root", "node").alias("component"))
    # a row of a class bears its class's component; rows without words stand alone
    out = seen.where("n > 0").select("doc_id", "n", "digest").join(label, "digest", "left").select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNotNull(), F.col("component")).alias("component_id"))
    out = out.unionAll(seen.where("n = 0").select("doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("component_id")))
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))
