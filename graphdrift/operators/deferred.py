"""Deferred moves: forecasts of room, and what happens to messages under each way of delivery."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphdrift.config import MigrationConfig
from graphdrift.functions.lineage import cut, forget
from graphdrift.operators.migrate import Adaptation


def forecast_room(room: DataFrame, moves: DataFrame) -> DataFrame:
    """part, remaining of the next iteration from announced moves: room + leaving - arriving."""
    out = moves.groupBy(F.col("from_part").alias("part")).agg(F.count(F.lit(1)).alias("leaving"))
    in_ = moves.groupBy(F.col("to_part").alias("part")).agg(F.count(F.lit(1)).alias("arriving"))
    change = out.join(in_, "part", "full").select("part", (F.coalesce("leaving", F.lit(0)) - F.coalesce("arriving", F.lit(0))).alias("d"))
    return room.join(change, "part", "left").select("part", (F.col("remaining") + F.coalesce("d", F.lit(0))).alias("remaining"))


def deliveries(edges: DataFrame, start: DataFrame, cfg: MigrationConfig, steps: int) -> DataFrame:
    """mode, superstep, sent, lost, forwarded, rewritten: every vertex messages every neighbour while moves happen.

    A message leaves for the place that its sender knows as the superstep begins and
    arrives after it, at the place's worker; it is stray if the addressee's physical
    place is another by then. Immediate moves (mode ``immediate``) lose stray messages,
    unless the old place sends them on (``forward``) or the senders' queues are
    rewritten as the move is announced (``rewrite``). ``deferred`` is run with deferred
    moves: the addressee is where its last announcement but one said, so none should stray.
    """
    rows = []
    for late in (False, True):
        run = Adaptation.start(edges, start, cfg.but(deferred=late))
        for t in range(1, steps + 1):
            known = cut(run.state.select(F.col("vid").alias("dst"), "part"))
            run.step()
            there = run.state.select(F.col("vid").alias("dst"), "home")
            told = run.sym.join(known, "dst").join(there, "dst").agg(F.count(F.lit(1)).alias("sent"), F.count_if(F.col("part") != F.col("home")).alias("stray")).first()
            forget(known)
            sent, stray = told["sent"], told["stray"]
            rows += [("deferred", t, sent, stray, 0, 0)] if late else [("immediate", t, sent, stray, 0, 0), ("forward", t, sent, 0, stray, 0), ("rewrite", t, sent, 0, 0, stray)]
        run.close()
    return edges.sparkSession.createDataFrame(rows, "mode string, superstep int, sent long, lost long, forwarded long, rewritten long")


def physical(state: DataFrame) -> DataFrame:
    """vid, part by physical place."""
    return state.select("vid", F.col("home").alias("part"))
