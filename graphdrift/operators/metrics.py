"""Cost and quality measures over edges, assignments, messages and histories."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphdrift.operators.graph import localise, symmetric, vertices_of


def cut_edges(edges: DataFrame, assignment: DataFrame) -> DataFrame:
    """cut, edges: one row."""
    local = localise(edges, assignment)
    return local.agg(F.coalesce(F.sum((F.col("src_part") != F.col("dst_part")).cast("long")), F.lit(0)).alias("cut"), F.count(F.lit(1)).alias("edges"))


def cut_ratio(edges: DataFrame, assignment: DataFrame) -> DataFrame:
    """cut, edges, ratio."""
    return cut_edges(edges, assignment).withColumn("ratio", F.when(F.col("edges") > 0, F.col("cut") / F.col("edges")))


def cut_matrix(edges: DataFrame, assignment: DataFrame) -> DataFrame:
    """a, b, edges: edges between partitions a <= b (a = b: not cut)."""
    local = localise(edges, assignment)
    return local.groupBy(F.least("src_part", "dst_part").alias("a"), F.greatest("src_part", "dst_part").alias("b")).agg(F.count(F.lit(1)).alias("edges"))


def cut_rollup(edges: DataFrame, assignment: DataFrame) -> DataFrame:
    """Cut edges by pair, by first partition, and in all (grouping tells the level)."""
    m = cut_matrix(edges, assignment).where("a <> b")
    return m.rollup("a", "b").agg(F.sum("edges").alias("edges"), F.grouping_id().cast("int").alias("level"))


def cut_pivot(edges: DataFrame, assignment: DataFrame, k: int) -> DataFrame:
    """The matrix with one column a partition."""
    m = cut_matrix(edges, assignment)
    return m.groupBy("a").pivot("b", list(range(k))).agg(F.sum("edges")).na.fill(0)


def balance(assignment: DataFrame, k: int, cap: int | None = None) -> DataFrame:
    """n, max_load, min_load, max_over_mean, over (partitions above ``cap``)."""
    dim = assignment.sparkSession.range(k).select(F.col("id").cast("int").alias("part"))
    load = dim.join(assignment.groupBy("part").agg(F.count(F.lit(1)).alias("l")), "part", "left").select(F.coalesce("l", F.lit(0)).alias("l"))
    return load.agg(F.sum("l").alias("n"), F.max("l").alias("max_load"), F.min("l").alias("min_load"), (F.max("l") * k / F.sum("l")).alias("max_over_mean"), F.sum((F.col("l") > (2**62 if cap is None else cap)).cast("long")).alias("over"))


def message_cost(edges: DataFrame, assignment: DataFrame) -> DataFrame:
    """Messages of a superstep in which every vertex tells every neighbour: all, local, remote, grouped remote."""
    local = localise(symmetric(edges), assignment)
    remote = F.col("src_part") != F.col("dst_part")
    grouped = local.where(remote).select("src_part", "dst").distinct().agg(F.count(F.lit(1)).alias("grouped"))
    counts = local.agg(F.count(F.lit(1)).alias("messages"), F.count_if(~remote).alias("local"), F.count_if(remote).alias("remote"))
    return counts.join(grouped).withColumn("remote_share", F.col("remote") / F.col("messages"))


def degree_profile(edges: DataFrame) -> DataFrame:
    """degree, vertices."""
    degree = symmetric(edges).groupBy("src").agg(F.count(F.lit(1)).alias("degree"))
    return degree.groupBy("degree").agg(F.count(F.lit(1)).alias("vertices"))


def accumulated(history: DataFrame) -> DataFrame:
    """History with running moves, their share, and the share of the cut's gain. One row an iteration."""
    w = Window.orderBy("iteration")
    run = F.sum("moved").over(w.rowsBetween(Window.unboundedPreceding, 0))
    all_ = Window.partitionBy()
    out = history.withColumn("run", run).withColumn("share", F.col("run") / F.sum("moved").over(all_))
    return out.withColumn("gain", F.first("cut").over(w.rowsBetween(Window.unboundedPreceding, 0)) - F.col("cut"))


def iterations_to(history: DataFrame, share: float) -> DataFrame:
    """iteration: the first at which that share of all moves is done."""
    return accumulated(history).where(F.col("share") >= share).agg(F.min("iteration").alias("iteration"))


def cut_gain(edges: DataFrame, before: DataFrame, after: DataFrame) -> DataFrame:
    """before, after, gain, relative: cut edges under two placements, what was gained, and its share of the first."""
    a, b = cut_edges(edges, before).select(F.col("cut").alias("before")), cut_edges(edges, after).select(F.col("cut").alias("after"))
    gain = F.col("before") - F.col("after")
    return a.join(b).select("before", "after", gain.alias("gain"), F.when(F.col("before") > 0, gain / F.col("before")).alias("relative"))


def converged_at(history: DataFrame) -> DataFrame:
    """iteration: that of the last move (0: none)."""
    return history.agg(F.coalesce(F.max(F.when(F.col("moved") > 0, F.col("iteration"))), F.lit(0)).cast("int").alias("iteration"))


def summarise_runs(runs: DataFrame, value: str, *by: str) -> DataFrame:
    """Mean and standard deviation of repetitions."""
    return runs.groupBy(*by).agg(F.avg(value).alias("mean"), F.stddev_samp(value).alias("std"), F.count(F.lit(1)).alias("runs"))


def break_even(adaptive: DataFrame, static: DataFrame) -> DataFrame:
    """iteration: the first at which the adaptive run's total time is below the static one's."""
    w = Window.orderBy("iteration").rowsBetween(Window.unboundedPreceding, 0)
    a = adaptive.select("iteration", F.sum("step_ms").over(w).alias("a"))
    b = static.select("iteration", F.sum("step_ms").over(w).alias("b"))
    return a.join(b, "iteration").where("a < b").agg(F.min("iteration").alias("iteration"))


def speedup(adaptive: DataFrame, static: DataFrame) -> DataFrame:
    """static over adaptive total time."""
    return adaptive.agg(F.sum("step_ms").alias("a")).join(static.agg(F.sum("step_ms").alias("b"))).select((F.col("b") / F.col("a")).alias("speedup"))


def wasted_moves(trail: DataFrame) -> DataFrame:
    """wasted: moves that go straight back. ``trail``: vid, iteration, from_part, to_part."""
    w = Window.partitionBy("vid").orderBy("iteration")
    back = (F.lag("from_part").over(w) == F.col("to_part")) & (F.lag("to_part").over(w) == F.col("from_part"))
    return trail.select(F.coalesce(back, F.lit(False)).alias("back")).agg(F.count_if("back").alias("wasted"), F.count(F.lit(1)).alias("moves"))


def overhead_fit(history: DataFrame) -> DataFrame:
    """Do migrations predict the time of an iteration?"""
    both, moves, times = F.covar_pop("moved", "step_ms"), F.stddev_pop("moved"), F.stddev_pop("step_ms")
    slope = F.try_divide(both, moves * moves)
    return history.agg(F.try_divide(both, moves * times).alias("corr"), slope.alias("slope"), (F.avg("step_ms") - slope * F.avg("moved")).alias("intercept"))


def weekly_churn(interactions: DataFrame) -> DataFrame:
    """week, ties, added, deleted: ties present in a week, and changes against the week before."""
    ties = interactions.where("src <> dst").select(F.date_trunc("week", "ts").alias("week"), F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).distinct()
    before = ties.select((F.col("week") + F.expr("interval 7 days")).alias("week"), "src", "dst", F.lit(1).alias("had"))
    both = ties.withColumn("has", F.lit(1)).join(before, ["week", "src", "dst"], "full")
    weeks = ties.select("week").distinct()
    return both.join(F.broadcast(weeks), "week").groupBy("week").agg(F.count("has").alias("ties"), F.count_if(F.col("had").isNull()).alias("added"), F.count_if(F.col("has").isNull()).alias("deleted"))


def throughput(interactions: DataFrame, bucket: str = "10 minutes") -> DataFrame:
    """start, events of each time bucket."""
    return interactions.groupBy(F.window("ts", bucket).alias("w")).agg(F.count(F.lit(1)).alias("events")).select(F.col("w.start").alias("start"), "events")


def state_size(edges: DataFrame, state_bytes: int = 16) -> DataFrame:
    """vertices, edges, bytes (16 an arc and ``state_bytes`` a vertex)."""
    v = vertices_of(edges).agg(F.count(F.lit(1)).alias("vertices"))
    e = edges.agg(F.count(F.lit(1)).alias("edges"))
    return v.join(e).withColumn("bytes", F.col("vertices") * state_bytes + F.col("edges") * 32)


def coordination_rows(history: DataFrame, k: int) -> DataFrame:
    """iteration, rows: capacity rows (k) and move notices of each iteration."""
    return history.select("iteration", (F.col("moved") + k).alias("rows"))


def same_part_slice(assignment: DataFrame, side: int, z: int) -> DataFrame:
    """x, y, part of one plane of a cube of cells."""
    plane = assignment.where((F.col("vid") >= z * side * side) & (F.col("vid") < (z + 1) * side * side))
    return plane.select((F.col("vid") % side).cast("int").alias("x"), F.expr(f"cast((vid div {side}) % {side} as int)").alias("y"), "part")
