"""Supersteps: adapt, compute, barrier, drain; vertex programs as Column builders."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphdrift.config import MigrationConfig
from graphdrift.functions.hashing import PICK, mix32, salt_of
from graphdrift.functions.lineage import cut, forget
from graphdrift.operators.apps import CELL, UNIT
from graphdrift.operators.changes import ChangeQueue, reassign
from graphdrift.operators.graph import symmetric, vertices_of
from graphdrift.operators.migrate import Adaptation
from graphdrift.operators.snapshot import restore_latest, save_snapshot


@dataclass
class VertexProgram:
    """init: value of a new vertex. message: what a vertex tells its neighbours, from ``value`` (null: nothing).
    combine: aggregate of ``payload``. update: new value from ``value`` and ``inbox`` (null: no message).
    degree: message and update may also use ``out``, the number of arcs that leave a vertex.
    merge: aggregate that joins what ``combine`` gave (the same one unless told)."""

    init: Column
    message: Column
    combine: Callable[[Column], Column]
    update: Column
    degree: bool = False
    merge: Callable[[Column], Column] | None = None


def local_and_remote(arcs: DataFrame, values: DataFrame, program: VertexProgram, run: Adaptation | None = None) -> DataFrame:
    """Messages along arcs with the places of both ends: src_part, dst_part, dst, payload. With ``run``, arcs are those of
    its ``outward``, where what vertices tell goes to the cached arcs instead of arcs to the vertices."""
    told = values.select(F.col("vid").alias("src"), F.col("part").alias("src_part"), program.message.alias("payload")).where("payload is not null")
    places = values.select(F.col("vid").alias("dst"), F.col("part").alias("dst_part"))
    sent = arcs.join(told, "src") if run is None else run.beside_arcs(arcs, told, "src")
    return sent.join(places, "dst").select("src_part", "dst_part", "dst", "payload")


def combine_messages(messages: DataFrame, program: VertexProgram) -> DataFrame:
    """One message for each (sending partition, vertex), and the number n of those in it; summed before the exchange."""
    return messages.groupBy("src_part", "dst_part", "dst").agg(program.combine(F.col("payload")).alias("payload"), F.count(F.lit(1)).alias("n"))


def run_program(
    edges: DataFrame, assignment: DataFrame, program: VertexProgram, cfg: MigrationConfig, supersteps: int, queue: ChangeQueue | None = None, on_superstep: Callable | None = None,
    arcs: DataFrame | None = None, snapshots: str | None = None, save_every: int = 1, run_id: str = "run",
) -> tuple[DataFrame, list[dict]]:
    """Values by vertex and one record a superstep: moves, cut and edges found, messages (all, remote, grouped), times by phase.

    Each superstep adapts once (if cfg.adaptive), then computes; at its end the queue is
    drained. ``arcs`` are the directed arcs that messages take (both directions of the
    edges unless told). With ``snapshots`` (a shared folder) state and values are saved
    every ``save_every`` supersteps, and a run that finds a committed snapshot of its
    ``run_id`` goes on from there.
    """
    spark = edges.sparkSession
    done, values = 0, None
    if snapshots:
        held, done = restore_latest(spark, snapshots, run_id)
        if held is not None:
            held = cut(held)
            assignment = held.select("vid", "part", "home", "settle")
            values = held.select("vid", "value")
    run = Adaptation.start(edges, assignment, cfg, done)
    values = cut(run.state.select("vid").withColumn("value", program.init)) if values is None else values
    log: list[dict] = []
    for t in range(done + 1, supersteps + 1):
        step = run.step() if cfg.adaptive else {"moved": 0, "decide_ms": 0, "migrate_ms": 0}
        began = time.time()
        along = run.outward if arcs is None else arcs
        placed = values.join(run.state.select("vid", F.col("home").alias("part")), "vid")
        if program.degree:
            out = along.groupBy(F.col("src").alias("vid")).agg(F.count(F.lit(1)).alias("out"))
            placed = placed.join(out, "vid", "left").withColumn("out", F.coalesce("out", F.lit(0)))
        grouped = cut(combine_messages(local_and_remote(along, placed, program, run if arcs is None else None), program))
        remote = F.col("src_part") != F.col("dst_part")
        counts = grouped.agg(
            F.coalesce(F.sum("n"), F.lit(0)).alias("messages"), F.coalesce(F.sum(F.when(remote, F.col("n"))), F.lit(0)).alias("remote"), F.count(F.lit(1)).alias("grouped"), F.count_if(remote).alias("remote_grouped")
        ).first()
        sent = time.time()
        inbox = grouped.groupBy(F.col("dst").alias("vid")).agg((program.merge or program.combine)(F.col("payload")).alias("inbox"))
        old, values = values, cut(placed.join(inbox, "vid", "left").select("vid", program.update.alias("value")))
        forget(grouped)
        if old is not None and t > done + 1:
            forget(old)
        times = {"decide_ms": step["decide_ms"], "migrate_ms": step["migrate_ms"], "message_ms": int(1000 * (sent - began)), "compute_ms": int(1000 * (time.time() - sent))}
        log.append({"superstep": t, "moved": step["moved"], **counts.asDict(), **times})
        if on_superstep:
            on_superstep(t, values)
        if queue is not None:
            new_edges, vertices, changed = queue.drain(t, edges, run.state.select("vid"))
            if changed:
                edges = cut(new_edges)
                state = reassign(run.state, cut(vertices), cfg.k, cfg.newcomer, cfg.seed, edges)
                before = run
                run = Adaptation.start(edges, state, cfg, before.iteration)
                run.history = before.history
                before.close()
                values = cut(run.state.select("vid").join(values, "vid", "left").select("vid", F.coalesce("value", program.init).alias("value")))
        if snapshots and t % save_every == 0:
            save_snapshot(run.state.select("vid", "part", "home", "settle").join(values, "vid"), snapshots, t, run_id)
    run.close()
    return values, log


def influence_program(p: float = 0.5) -> VertexProgram:
    """What followers pass on, in fixed point: the sum over followers of (1 + p influence) / out-degree."""
    share = F.floor((F.lit(UNIT) + F.lit(p) * F.col("value")) / F.col("out")).cast("long")
    return VertexProgram(F.lit(0).cast("long"), share, F.sum, F.coalesce("inbox", F.lit(0)).cast("long"), degree=True)


def reach_program(seed: int = 0) -> VertexProgram:
    """Neighbourhood sketches: each vertex sets one bit (bit i with chance 2^-(i+1)) and takes over its neighbours' bits.

    The superstep after which no vertex gains a bit estimates the diameter from below;
    the lowest unset bit b of a vertex tells of about 2^b / 0.77351 vertices within reach.
    """
    h = mix32("vid", salt_of(seed, PICK, 7)).bitwiseOR(F.lit(1 << 30))
    bit = h.bitwiseAND(-h)  # the lowest set bit
    return VertexProgram(bit, F.col("value"), F.bit_or, F.col("value").bitwiseOR(F.coalesce("inbox", F.lit(0).cast("long"))))


def tissue_program(dt: float = 0.1, diffusion: float = 0.1, epsilon: float = 0.08, a: float = 0.7, b: float = 0.8, current: float = 0.5) -> VertexProgram:
    """Excitable cells (see apps.tissue), value (u, w) in fixed point, all live and at rest but for every seventh."""
    v, w = F.col("value.u") / CELL, F.col("value.w") / CELL
    pull = (F.coalesce("inbox", F.lit(0)) - F.col("out") * F.col("value.u")) / CELL
    new_u = F.round((v + dt * (v - v * v * v / 3 - w + current + diffusion * pull)) * CELL).cast("long")
    new_w = F.round((w + dt * epsilon * (v + a - b * w)) * CELL).cast("long")
    init = F.struct(F.when(F.col("vid") % 7 == 0, F.lit(CELL)).otherwise(F.lit(0)).cast("long").alias("u"), F.lit(0).cast("long").alias("w"))
    return VertexProgram(init, F.col("value.u"), F.sum, F.struct(new_u.alias("u"), new_w.alias("w")), degree=True)


def min_label_program() -> VertexProgram:
    """Least id spreading: components after enough supersteps."""
    return VertexProgram(F.col("vid"), F.col("value"), F.min, F.least("value", F.coalesce("inbox", "value")))


def degree_program() -> VertexProgram:
    """Counts neighbours once."""
    return VertexProgram(F.lit(0).cast("long"), F.lit(1).cast("long"), F.sum, F.coalesce("inbox", F.lit(0).cast("long")))


__all__ = ["VertexProgram", "combine_messages", "degree_program", "local_and_remote", "min_label_program", "run_program", "symmetric", "vertices_of"]
