"""Roles of a raw transcript's lines by a hidden Markov model, and its canonical form.

States are a role together with whether a line opens a turn or goes on with it. A
line emits one symbol made of its speaker marker (if any), its length class and
whether it ends as a question. Start, transition and emission chances are counted
(with one added to each) on conversations whose roles are known. Viterbi's best
path gives the roles.

A conversation of any length is decoded in blocks: maxima over paths are matrix
products under (max, +), so each block becomes a 7 x 6 matrix of best scores from
every state before it to every state at its end, and so does all that a task holds of
a conversation. A pass over the tasks' matrices fixes the states between tasks, one
over each task's blocks those at block borders, and each block then finds its own part
of the path. Rows are dealt out by ranges of (conversation, position), which split
a long conversation as well.

Defined results: null text is one empty line; a row without an id belongs to the
conversation of null ids; rows are ordered by turn (nulls first), then text, and
repeated rows are turns of their own; an empty table gives an empty result; other
columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphdrift.llm import common

ROLES = ["system", "user", "assistant"]
STATES = 2 * len(ROLES)  # role * 2 + (0 opens a turn, 1 goes on)
START = STATES
LENGTHS = (0, 20, 60, 120, 240, 480)
SYMBOLS = (len(ROLES) + 1) * (len(LENGTHS) + 1) * 2
BLOCK_ROWS = 256

_NAMES = {"system": 0, "instructions": 0, "user": 1, "human": 1, "q": 1, "assistant": 2, "bot": 2, "ai": 2, "a": 2}
_MARKER = re.compile(r"^\s*(?:#{1,4}\s*|\[|<\|?|\*\*)?(" + "|".join(sorted(_NAMES, key=len, reverse=True)) + r")(?:\]|\|?>|\*\*)?\s*(?::|\]|>|$|(?<=[\]>*])\s)\s*", re.IGNORECASE)
STYLES = ["{Role}: ", "### {Role}\n", "[{role}] ", "<|{role}|> ", "**{Role}**: "]


def marker_of(line: str) -> tuple[int, str]:
    """Role that a line's marker names (or the number of roles), and the line without it."""
    m = _MARKER.match(line)
    return (_NAMES[m[1].lower()], line[m.end() :]) if m else (len(ROLES), line)


def symbol_of(line: str) -> int:
    role, rest = marker_of(line)
    size = sum(len(rest) > x for x in LENGTHS)
    return (role * (len(LENGTHS) + 1) + size) * 2 + rest.rstrip().endswith("?")


def raw_turn(conv_id: int | None, turn: int | None, role: str | None, text: str | None) -> str:
    """A turn as a raw transcript has it: the marker's style varies by conversation, and one marker in six is missing."""
    n = 0 if conv_id is None else conv_id
    t = 0 if turn is None else turn
    if (n * 31 + t * 17) % 6 == 5 and t:
        return text or ""
    name = role or "user"
    return STYLES[n % len(STYLES)].format(role=name, Role=name.capitalize()) + (text or "")


class Hmm:
    """Logarithms of start/transition (7 x 6) and emission (6 x symbols) chances."""

    def __init__(self, moves: np.ndarray, shown: np.ndarray):
        moves, shown = moves + 1.0, shown + 1.0
        # a turn's first line can't go on with another role's turn
        for a in range(STATES + 1):
            for b in range(STATES):
                if b % 2 and (a == START or a // 2 != b // 2):
                    moves[a, b] = 1e-6
        self.moves = np.log(moves / moves.sum(axis=1, keepdims=True))
        self.shown = np.log(shown / shown.sum(axis=1, keepdims=True))

    def matrix(self, symbols: list[int]) -> np.ndarray:
        """Best scores from each state before the lines to each state at their end."""
        best = self.moves + self.shown[:, symbols[0]]
        inner = self.moves[:STATES]
        for s in symbols[1:]:
            best = (best[:, :, None] + inner[None]).max(axis=1) + self.shown[:, s]
        return best

    def path(self, symbols: list[int], entry: int, exit_: int | None = None) -> list[int]:
        """Best states of the lines, given the state before them and (if told) the last."""
        score = self.moves[entry] + self.shown[:, symbols[0]]
        inner, back = self.moves[:STATES], []
        for s in symbols[1:]:
            every = score[:, None] + inner
            back.append(every.argmax(axis=0))
            score = every.max(axis=0) + self.shown[:, s]
        at = int(score.argmax()) if exit_ is None else exit_
        out = [at]
        for b in reversed(back):
            at = int(b[at])
            out.append(at)
        return out[::-1]


def ordered_turns(conversations: DataFrame, text: str = "raw", partitions: int | None = None) -> DataFrame:
    """Rows dealt by ranges of (conversation, turn) and sorted, in the shared folder."""
    spark = conversations.sparkSession
    n = partitions or int(spark.conf.get("spark.sql.shuffle.partitions"))
    tie = F.md5(F.coalesce(F.col(text), F.lit("")).cast("binary"))
    rows = conversations.withColumn("tie", tie).repartitionByRange(n, "conv_id", "turn", "tie").sortWithinPartitions("conv_id", "turn", "tie")
    return common.cut(rows.drop("tie"))


def _counts(rows: DataFrame) -> DataFrame:
    """a, b, n: moves (a, b) and, with a from 100, emissions (a - 100, symbol). Held-out conversations don't count."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        moves, shown, now, last, role_before = np.zeros((STATES + 1, STATES), np.int64), np.zeros((STATES, SYMBOLS), np.int64), object(), START, None
        for batch in batches:
            for conv, role, raw in zip(*(batch.column(k).to_pylist() for k in range(3))):
                if conv != now:
                    now, last, role_before = conv, START, None
                if role not in ROLES:
                    continue
                for k, line in enumerate((raw or "").split("\n")):
                    state = ROLES.index(role) * 2 + (k > 0)
                    moves[last, state] += 1
                    shown[state, symbol_of(line)] += 1
                    last = state
        grid = [(a, b, int(n)) for (a, b), n in np.ndenumerate(moves) if n] + [(100 + a, b, int(n)) for (a, b), n in np.ndenumerate(shown) if n]
        if grid:
            yield pa.RecordBatch.from_arrays([pa.array([g[k] for g in grid], pa.int64()) for k in range(3)], names=["a", "b", "n"])

    known = rows.where(F.pmod(F.crc32(F.coalesce(F.col("conv_id").cast("string"), F.lit("")).cast("binary")), F.lit(5)) != 0)
    return known.select("conv_id", "role", "raw").mapInArrow(run, "a long, b long, n long").groupBy("a", "b").agg(F.sum("n").alias("n"))


def train(rows: DataFrame) -> Hmm:
    """Count the model's chances on known roles; the counts number no more than the model's cells."""
    moves, shown = np.zeros((STATES + 1, STATES)), np.zeros((STATES, SYMBOLS))
    for r in _counts(rows).collect():
        if r["a"] < 100:
            moves[r["a"], r["b"]] = r["n"]
        else:
            shown[r["a"] - 100, r["b"]] = r["n"]
    return Hmm(moves, shown)


def _segments(batches: Iterator[pa.RecordBatch], columns: int) -> Iterator[list[tuple]]:
    """Consecutive rows of one conversation, at most BLOCK_ROWS of them."""
    held: list[tuple] = []
    for batch in batches:
        for row in zip(*(batch.column(k).to_pylist() for k in range(columns))):
            if held and (row[0] != held[0][0] or len(held) >= BLOCK_ROWS):
                yield held
                held = []
            held.append(row)
    if held:
        yield held


def parse_turns(rows: DataFrame, model: Hmm) -> DataFrame:
    """Roles of ordered raw turns: conv_id, turn, n_lines, roles (a line each), rendered (canonical lines).

    ``rows``: conv_id, turn, raw, as ordered_turns gives them. A rendered line
    opens with <|role|> where a turn begins and closes with <|end|> where the next
    one does; the lines in order are the canonical transcript.
    """
    common.tune(rows.sparkSession)
    rows = rows.select("conv_id", "turn", "raw")

    def matrices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """A row a segment, and one with seq -1 for all of a conversation's segments in the task."""
        part, chunk, whole, now = TaskContext.get().partitionId(), -1, None, None

        def row(conv: int | None, seq: int, m: np.ndarray) -> pa.RecordBatch:
            cells = [pa.array([x], pa.int64()) for x in (conv, part, chunk, seq)]
            return pa.RecordBatch.from_arrays([*cells, pa.array([m.reshape(-1)], pa.list_(pa.float64()))], names=["conv_id", "part", "chunk", "seq", "m"])

        for seq, seg in enumerate(_segments(batches, 3)):
            if chunk < 0 or seg[0][0] != now:
                if chunk >= 0:
                    yield row(now, -1, whole)
                chunk, now, whole = chunk + 1, seg[0][0], None
            m = model.matrix([symbol_of(x) for row in seg for x in (row[2] or "").split("\n")])
            whole = m if whole is None else (whole[:, :, None] + m[None, :STATES]).max(axis=1)
            yield row(now, seq, m)
        if chunk >= 0:
            yield row(now, -1, whole)

    def settle(mats: list, entry: int, exit_: int | None) -> list[tuple[int, int]]:
        """(entry, exit) of each matrix on the best path from ``entry`` (to ``exit_``, if told)."""
        score, back = np.full(STATES + 1, -np.inf), []
        score[entry] = 0
        for m in mats:
            every = score[:, None] + np.array(m).reshape(STATES + 1, STATES)
            back.append(every.argmax(axis=0).astype(np.int8))
            score = np.append(every.max(axis=0), -np.inf)
        at, out = int(score[:STATES].argmax()) if exit_ is None else exit_, []
        for b in reversed(back):
            out.append((int(b[at]), at))
            at = out[-1][0]
        return out[::-1]

    def grouped(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[list[tuple]]:
        """Consecutive rows whose first ``keys`` cells agree."""
        group: list[tuple] = []
        for batch in batches:
            for row in zip(*(batch.column(k).to_pylist() for k in range(batch.num_columns))):
                if group and row[:keys] != group[0][:keys]:
                    yield group
                    group = []
                group.append(row)
        if group:
            yield group

    def emit(rows: list[tuple], names: list[str]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], pa.int64()) for k in range(len(names))], names=names)

    def across(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in grouped(batches, 1):  # a row a task that holds some of the conversation
            found = settle([g[3] for g in group], START, None)
            yield emit([(g[1], g[2], *f) for g, f in zip(group, found)], ["part", "chunk", "entry", "exit"])

    def inside(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in grouped(batches, 2):  # the segments of one conversation in one task
            found = settle([g[5] for g in group], group[0][3], group[0][4])
            yield emit([(g[0], g[2], *f) for g, f in zip(group, found)], ["part", "seq", "entry", "exit"])

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for turns, entry, exit_ in zip(*(batch.column(k).to_pylist() for k in range(3))):
                lines = [(i, x) for i, t in enumerate(turns) for x in (t["raw"] or "").split("\n")]
                states = model.path([symbol_of(x) for _, x in lines], entry, exit_)
                roles: list[list[str]] = [[] for _ in turns]
                shown: list[list[str]] = [[] for _ in turns]
                last = entry
                for (i, x), s in zip(lines, states):
                    opens = s % 2 == 0 or last == START
                    roles[i].append(ROLES[s // 2])
                    shown[i].append(("" if last == START or not opens else "<|end|>\n") + (f"<|{ROLES[s // 2]}|>\n" if opens else "") + marker_of(x)[1])
                    last = s
                columns = [pa.array([t["conv_id"] for t in turns], pa.int64()), pa.array([t["turn"] for t in turns], pa.int64()), pa.array([t["raw"] for t in turns], pa.string()), pa.array([len(r) for r in roles], pa.int64()), pa.array(roles, pa.list_(pa.string())), pa.array(shown, pa.list_(pa.string()))]
                yield pa.RecordBatch.from_arrays(columns, names=["conv_id", "turn", "raw", "n_lines", "roles", "rendered"])

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = TaskContext.get().partitionId()
        kind = pa.list_(pa.struct([("conv_id", pa.int64()), ("turn", pa.int64()), ("raw", pa.string())]))
        for seq, seg in enumerate(_segments(batches, 3)):
            turns = [{"conv_id": c, "turn": t, "raw": r} for c, t, r in seg]
            yield pa.RecordBatch.from_arrays([pa.array([part], pa.int64()), pa.array([seq], pa.int64()), pa.array([turns], kind)], names=["part", "seq", "turns"])

    # two levels, so that no task meets more than a row a task of a long conversation, or more than one task's segments
    scored = common.cut(rows.mapInArrow(matrices, "conv_id long, part long, chunk long, seq long, m array<double>"))
    tops = scored.where("seq < 0").select("conv_id", "part", "chunk", "m").repartition("conv_id").sortWithinPartitions("conv_id", "part")
    ends = tops.mapInArrow(across, "part long, chunk long, entry long, exit long")
    low = scored.where("seq >= 0").select("part", "chunk", "seq", "m").join(ends, ["part", "chunk"]).select("part", "chunk", "seq", "entry", "exit", "m")
    fixed = low.repartition("part", "chunk").sortWithinPartitions("part", "chunk", "seq").mapInArrow(inside, "part long, seq long, entry long, exit long")
    blocks = rows.mapInArrow(packed, "part long, seq long, turns array<struct<conv_id:long,turn:long,raw:string>>")
    return blocks.join(fixed, ["part", "seq"]).select("turns", "entry", "exit").mapInArrow(decode, "conv_id long, turn long, raw string, n_lines long, roles array<string>, rendered array<string>")


def raw_conversations(conversations: DataFrame) -> DataFrame:
    """conv_id, turn, role, raw: turns as a raw transcript has them (see raw_turn)."""
    n, t = F.coalesce(F.col("conv_id").cast("long"), F.lit(0)), F.coalesce(F.col("turn").cast("long"), F.lit(0))
    name = F.coalesce(F.col("role"), F.lit("user"))
    style = F.pmod(n, F.lit(len(STYLES)))
    marker = F.lit("")
    for k, s in enumerate(STYLES):
        before, after = re.split(r"\{[Rr]ole\}", s)
        shown = F.initcap(name) if "{Role}" in s else name
        marker = F.when(style == k, F.concat(F.lit(before), shown, F.lit(after))).otherwise(marker)
    missing = (F.pmod(n * 31 + t * 17, F.lit(6)) == 5) & (t != 0)
    return conversations.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), "role", F.concat(F.when(missing, F.lit("")).otherwise(marker), common.text_of()).alias("raw"))


def recovered_roles(conversations: DataFrame) -> DataFrame:
    """conv_id, turn, role (recovered, of the turn's first line), n_lines, n_changes, rendered_sha256, raw_sha256."""
    common.tune(conversations.sparkSession)
    rows = ordered_turns(raw_conversations(conversations))
    out = parse_turns(rows, train(rows))
    changes = F.aggregate(F.sequence(F.lit(1), F.greatest(F.lit(1), F.size("roles") - 1)), F.lit(0), lambda n, k: n + F.coalesce((F.get("roles", k) != F.get("roles", k - 1)).cast("int"), F.lit(0)))
    return out.select("conv_id", "turn", F.get("roles", F.lit(0)).alias("role"), "n_lines", changes.cast("long").alias("n_changes"), F.sha2(F.concat_ws("\n", "rendered").cast("binary"), 256).alias("rendered_sha256"), F.sha2(F.coalesce("raw", F.lit("")).cast("binary"), 256).alias("raw_sha256"))
