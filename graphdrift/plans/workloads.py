"""The experiment workloads on the given tables."""

from __future__ import annotations

import uuid
import warnings

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphdrift.config import MigrationConfig
from graphdrift.functions.lineage import checkpoint_dir, cut, forget
from graphdrift.operators import engine, metrics, replicas
from graphdrift.operators.apps import max_cliques
from graphdrift.operators.apps import diameter_sweep
from graphdrift.operators.changes import ChangeQueue, apply_changes, reassign
from graphdrift.operators.engine import min_label_program, run_program
from graphdrift.operators.graph import vertices_of
from graphdrift.operators.initial import assign_hash, assign_random, stream_chunked, stream_exact
from graphdrift.operators.migrate import Adaptation, adapt, convergence_iteration, quiet_for
from graphdrift.operators.ranks import global_rank
from graphdrift.sources import generators
from graphdrift.sources.graphs import canonical, cube_side, graph_from, interactions, mentions, table

HISTORY = ["iteration", "proposed", "damped", "refused", "moved", "cut", "edges", "max_load", "min_load"]
#: The bound on runs to quiescence is for safety alone; ``quiet`` of the result is false where it ended one.
MAX_ITER = 400
#: Starts that need nothing but ids.
RULES = ("hsh", "hsh_mixed", "rnd")


def union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def started(spark: SparkSession, sf_dir: str, name: str, cfg: MigrationConfig, kind: str = "hsh_mixed") -> tuple[DataFrame, DataFrame]:
    """Edges and initial placement of a graph."""
    edges = cut(graph_from(spark, sf_dir, name))
    return edges, start_of(edges, vertices_of(edges), cfg, kind)


def start_of(edges: DataFrame, v: DataFrame, cfg: MigrationConfig, kind: str) -> DataFrame:
    """The initial placement of that kind."""
    if kind in ("hsh", "hsh_mixed"):
        return assign_hash(v, cfg.k, kind == "hsh_mixed", cfg.seed)
    if kind == "rnd":
        return assign_random(v, cfg.k, cfg.seed)
    if replicas.fits(edges):
        return stream_exact(edges, v, cfg.k, kind)
    return stream_chunked(edges, v, cfg.k, kind, chunk=100_000)


def run_history(spark: SparkSession, sf_dir: str, name: str, cfg: MigrationConfig, steps: int | None, kind: str = "hsh_mixed") -> DataFrame:
    """The history of ``steps`` iterations; without a number, of all to quiescence, and whether they got there."""
    if steps is not None:
        return adapt(*started(spark, sf_dir, name, cfg, kind), cfg, steps)[1].select(*HISTORY)
    edges = replicas.hold(graph_from(spark, sf_dir, name))
    start = kind if kind in RULES else start_of(edges.frame(), vertices_of(edges.frame()), cfg, kind)
    return to_quiet(edges, start, cfg, None, states=False)[1].select(*HISTORY, "quiet")


def settled(history: DataFrame, cfg: MigrationConfig) -> DataFrame:
    """The history of one run with quiet: whether more than cfg.patience iterations without a move ended it."""
    last = history.agg((F.max("iteration") - F.coalesce(F.max(F.when(F.col("moved") > 0, F.col("iteration"))), F.lit(0)) > cfg.patience).alias("quiet"))
    return history.join(F.broadcast(last))


def unpacked(edges: DataFrame | replicas.Held) -> DataFrame:
    """src, dst for the distributed loop."""
    return cut(edges.frame()) if isinstance(edges, replicas.Held) else edges


def to_quiet(edges: DataFrame | replicas.Held, start: DataFrame | str, cfg: MigrationConfig, steps: int | None, states: bool = True) -> tuple[DataFrame | None, DataFrame]:
    """Final state (if asked for) and history (with quiet) of one run: as one task where the graph fits, else by the distributed loop. A history alone can begin by a rule."""
    cfg = cfg.but(max_iter=MAX_ITER)
    fits = replicas.fits(edges)
    if not fits:
        edges = unpacked(edges)
    if isinstance(start, str) and not fits:
        start = start_of(edges, vertices_of(edges), cfg, start)
    if fits:
        state, history = replicas.adapt_many(edges, start.select(F.lit(0).alias("run"), "vid", "part") if states else {0: start}, {0: cfg}, steps)
        if steps is None and not history.agg(F.max("quiet")).first()[0]:
            warnings.warn(f"not quiet after {MAX_ITER} iterations", stacklevel=2)
        return state.drop("run") if states else None, history.drop("run")
    state, history = adapt(edges, start, cfg, steps)
    return state, settled(history, cfg)


def many(edges: DataFrame | replicas.Held, starts: list[tuple[str, DataFrame | str]] | None, cfgs: dict[str, MigrationConfig], steps: int | None) -> DataFrame:
    """label and history of runs with different settings; ``starts`` by label, as placements or kinds (mixed hash unless told). Side by side where the graph fits in a task."""
    by = dict(starts or [])
    cfgs = {n: c.but(max_iter=MAX_ITER) for n, c in cfgs.items()}
    if not replicas.fits(edges):
        edges = unpacked(edges)
        v = cut(vertices_of(edges))
        begun = {n: start_of(edges, v, c, a) if isinstance(a, str) else a for n, c in cfgs.items() for a in [by.get(n, "hsh_mixed")]}
        return union([settled(adapt(edges, begun[n], c, steps)[1], c).select(F.lit(n).alias("label"), *HISTORY, "quiet") for n, c in cfgs.items()])
    history = replicas.adapt_many(edges, {i: by.get(n, "hsh_mixed") for i, n in enumerate(cfgs)}, dict(enumerate(cfgs.values())), steps)[1]
    names = F.array(*[F.lit(n) for n in cfgs])
    return history.select(names[F.col("run")].alias("label"), *HISTORY, "remote", "quiet")


def run_state(spark: SparkSession, sf_dir: str, name: str, cfg: MigrationConfig, steps: int | None, kind: str = "hsh_mixed") -> DataFrame:
    edges, start = started(spark, sf_dir, name, cfg, kind)
    return to_quiet(edges, start, cfg, steps)[0]


def s_sweep(spark: SparkSession, sf_dir: str, name: str = "lattice", values=(0.1, 0.25, 0.5, 0.75, 0.9, 1.0), steps: int | None = None, seeds=tuple(range(10))) -> DataFrame:
    """s, seed and the history of each run. (steps None: to quiescence, or to MAX_ITER iterations, where quiet is false.)"""
    if steps is not None:
        out = []
        for s in values:
            for seed in seeds:
                h = run_history(spark, sf_dir, name, MigrationConfig(s=s, seed=seed), steps)
                out.append(h.select(F.lit(round(100 * s)).alias("s_percent"), F.lit(seed).alias("seed"), *h.columns))
        return union(out)
    edges = replicas.hold(graph_from(spark, sf_dir, name))
    runs = many(edges, None, {f"{round(100 * s)}:{seed}": MigrationConfig(s=s, seed=seed) for s in values for seed in seeds}, None)
    part = F.split("label", ":")
    return runs.select(part[0].cast("int").alias("s_percent"), part[1].cast("int").alias("seed"), *HISTORY, "quiet")


def initial_quality(spark: SparkSession, sf_dir: str, graphs: list[str], kinds: list[str], steps: int | None, cfg: MigrationConfig | None = None, seeds=tuple(range(10))) -> DataFrame:
    """graph, start, before, after, edges: cuts before and after adapting; to quiescence (steps None) also seed, moves, the last move's iteration and quiet."""
    cfg = cfg or MigrationConfig()
    out = []
    for g in graphs:
        held = replicas.hold(graph_from(spark, sf_dir, g))
        edges = held.frame() if held.fits else unpacked(held)
        v = cut(vertices_of(edges)) if not held.fits or set(kinds) - set(RULES) else None
        # a stream in id order has no seed; all of them are one job's tasks
        streams = {kind: start_of(edges, v, cfg, kind) for kind in kinds if kind not in RULES}
        if streams:
            begun = cut(union([a.select(F.lit(kind).alias("kind"), "vid", "part") for kind, a in streams.items()]))
            streams = {kind: begun.where(F.col("kind") == kind).select("vid", "part") for kind in streams}
        starts, cfgs = [], {}
        for kind in kinds:
            for seed in seeds:
                label = f"{kind}:{seed}"
                cfgs[label] = cfg.but(seed=seed)
                starts.append((label, streams.get(kind, kind)))
        h = many(held if held.fits else edges, starts, cfgs, steps)
        if "remote" not in h.columns:
            begun = [(n, start_of(edges, v, cfgs[n], a) if isinstance(a, str) else a) for n, a in starts]
            first = spark.createDataFrame([(n, 2 * metrics.cut_edges(edges, a).first()["cut"]) for n, a in begun], "label string, remote long")
            h = h.join(F.broadcast(first), "label")
        part, last = F.split("label", ":"), F.coalesce(F.max(F.when(F.col("moved") > 0, F.col("iteration"))), F.lit(0))
        ends = h.groupBy("label").agg((F.min_by("remote", "iteration") / 2).cast("long").alias("before"), F.max_by("cut", "iteration").alias("after"), F.max("edges").alias("edges"), F.sum("moved").alias("moves"), last.alias("last_move"), F.first("quiet").alias("quiet"))
        out.append(ends.select(F.lit(g).alias("graph"), part[0].alias("start"), "before", "after", "edges", part[1].cast("int").alias("seed"), "moves", "last_move", "quiet"))
    found = union(out)
    return found if steps is None else found.drop("seed", "moves", "last_move", "quiet")


def sweep_spread(runs: DataFrame) -> DataFrame:
    """s_percent, value, mean, std, runs of the cut a run left, its moves and its last move, over the seeds of a sweep."""
    last = F.coalesce(F.max(F.when(F.col("moved") > 0, F.col("iteration"))), F.lit(0))
    ends = cut(runs.groupBy("s_percent", "seed").agg(F.max_by("cut", "iteration").alias("cut"), F.sum("moved").alias("moves"), last.alias("last_move")))
    return union([metrics.summarise_runs(ends, v, "s_percent").select("s_percent", F.lit(v).alias("value"), "mean", "std", "runs") for v in ("cut", "moves", "last_move")])


def ending(history: DataFrame, cfg: MigrationConfig) -> dict:
    """cut: what a run left; moves: all of them; last_move: its iteration (0: none); quiet."""
    rows = history.orderBy("iteration").collect()
    moved = [r["moved"] for r in rows]
    return {"cut": rows[-1]["cut"], "moves": sum(moved), "last_move": convergence_iteration(moved), "quiet": quiet_for(moved, cfg.patience)}


def ablation(spark: SparkSession, sf_dir: str, name: str, variants: dict[str, MigrationConfig], steps: int | None = None) -> DataFrame:
    """variant and its history; to quiescence (steps None) also quiet."""
    if steps is not None:
        return union([run_history(spark, sf_dir, name, cfg, steps).select(F.lit(v).alias("variant"), "*") for v, cfg in variants.items()])
    edges = replicas.hold(graph_from(spark, sf_dir, name))
    return many(edges, None, variants, None).select(F.col("label").alias("variant"), *HISTORY, "quiet")


ABLATIONS = {
    "base": MigrationConfig(),
    "no_quota": MigrationConfig(use_quota=False),
    "count_self": MigrationConfig(count_self=True),
    "lowest": MigrationConfig(tie_break="lowest"),
    "floor": MigrationConfig(quota_remainder="drop"),
    "tight": MigrationConfig(slack=1.02),
    "deferred": MigrationConfig(deferred=True),
    "by_hash": MigrationConfig(admission="hash"),
}


def call_ties(spark: SparkSession, sf_dir: str, days: int = 10) -> tuple[DataFrame, int]:
    """src, dst and first slice of the call stream's ties, and the number of slices of so many days."""
    calls = interactions(spark, sf_dir).where("src <> dst")
    ties = calls.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), F.expr(f"cast(datediff(ts, date'2024-01-01') div {days} as int)").alias("slice"))
    ties = cut(ties.groupBy("src", "dst").agg(F.min("slice").alias("slice")))
    last = ties.agg(F.max("slice")).first()[0]
    return ties, max(0, (-1 if last is None else last) + 1)


def grown(ties: DataFrame, slices: int, cfg: MigrationConfig, steps: int | None, onward: bool) -> list[tuple]:
    """(slice, cut, edges) of runs on the growing graph, in tasks that take its ties once."""
    ends = {r["slice"]: r for r in replicas.adapt_growing(ties.withColumn("slice", F.greatest("slice", F.lit(0))), slices, cfg.but(max_iter=MAX_ITER), steps, onward).collect()}
    if steps is None and not all(r["quiet"] for r in ends.values()):
        warnings.warn(f"not quiet after {MAX_ITER} iterations", stacklevel=2)
    return [(d, ends[d]["cut"], ends[d]["edges"]) if d in ends else (d, 0, 0) for d in range(slices)]


def drift(spark: SparkSession, sf_dir: str, strategy: str, k: int = 9, steps: int | None = None, days: int = 10) -> DataFrame:
    """slice, cut, edges: how a placement ages. hsh: hash; dtg: newcomers greedily on arrival; adp: hash and migration; scratch: all is placed anew each time."""
    cfg, placed, rows = MigrationConfig(k=k), None, []
    columns = "slice int, cut long, edges long"
    ties, slices = call_ties(spark, sf_dir, days)
    if slices and strategy in ("adp", "scratch") and replicas.fits(ties):
        return spark.createDataFrame(grown(ties, slices, cfg, steps, strategy == "adp"), columns)
    for d in range(slices):
        edges = ties.where(F.col("slice") <= d).select("src", "dst")
        v = vertices_of(edges)
        if placed is None:
            placed = assign_hash(v, k) if strategy != "dtg" else stream_chunked(edges, v, k, "dgr", chunk=200)
        else:
            placed = reassign(placed, v, k, "dgr" if strategy == "dtg" else "hash", 0, edges)
        placed = cut(placed)
        if strategy == "scratch":
            placed = to_quiet(edges, cut(assign_hash(v, k)), cfg, steps)[0].select("vid", "part")
        if strategy == "adp":
            placed = to_quiet(edges, placed, cfg, steps)[0].select("vid", "part")
        m = metrics.cut_edges(edges, placed).first()
        rows.append((d, m["cut"], m["edges"]))
    return spark.createDataFrame(rows, columns)


def bursts(spark: SparkSession, sf_dir: str, name: str = "cop", shares=(0.01, 0.02, 0.05, 0.10), phase: int = 50, adaptive: bool = True, k: int = 9) -> DataFrame:
    """phase, iteration, moved, cut, edges, step_ms, messages, remote, grouped, diameter: a forest-fire burst after each phase.

    The messages are those of the continuously running analysis (every vertex tells every
    neighbour). The diameter (a lower bound by two sweeps) changes with the graph, so once a phase.
    """
    cfg = MigrationConfig(k=k, adaptive=adaptive)
    edges = cut(graph_from(spark, sf_dir, name))
    state, out = assign_hash(vertices_of(edges), k), []
    for p, share in enumerate((0.0, *shares)):
        if share:
            n = state.count()
            burst = generators.forest_fire(edges, max(1, int(n * share)), seed=p)
            edges = cut(edges.unionAll(burst))  # newcomers' edges are new ones
            state = cut(reassign(state, vertices_of(edges), k))
        state, h = to_quiet(edges, state, cfg, phase)
        state = state.select("vid", "part")
        costs = [c for c in ("step_ms", "messages", "remote", "grouped") if c in h.columns]
        out.append(h.select(F.lit(p).alias("phase"), "iteration", "moved", "cut", "edges", *costs, F.lit(diameter_sweep(edges).first()["lower_bound"]).alias("diameter")))
    return union(out)


def use_case(spark: SparkSession, sf_dir: str, case: str, adaptive: bool, supersteps: int = 6, k: int = 9, times: bool = False) -> DataFrame:
    """One of the paper's use cases while it runs, adapting or static: a row a superstep with moves and messages, and with ``times`` its phases.

    mentions: influence along the mention arcs. bursts: neighbourhood sketches (the
    diameter's estimate) on customers, orders and parts. tissue: excitable cells on the lattice.
    """
    arcs = None
    if case == "mentions":
        arcs = cut(mentions(spark, sf_dir).select("src", "dst"))
        edges, program = cut(canonical(arcs)), engine.influence_program()
    elif case == "bursts":
        edges, program = cut(graph_from(spark, sf_dir, "cop")), engine.reach_program()
    else:
        edges, program = cut(graph_from(spark, sf_dir, "lattice")), engine.tissue_program()
    cfg = MigrationConfig(k=k, adaptive=adaptive)
    log = run_program(edges, assign_hash(vertices_of(edges), k), program, cfg, supersteps, arcs=arcs)[1]
    return log_frame(spark, "adaptive" if adaptive else "static", log, times)


COUNTS = ["moved", "messages", "remote", "grouped", "remote_grouped"]
TIMES = ["decide_ms", "migrate_ms", "message_ms", "compute_ms"]


def log_frame(spark: SparkSession, arm: str, log: list[dict], times: bool = False) -> DataFrame:
    """arm, superstep and the counts (and times) of an engine's log."""
    columns = [*COUNTS, *(TIMES if times else [])]
    return spark.createDataFrame([(arm, r["superstep"], *[int(r[c]) for c in columns]) for r in log], "arm string, superstep int, " + ", ".join(f"{c} long" for c in columns))


def arms(spark: SparkSession, sf_dir: str, case: str, supersteps: int = 3, times: bool = False) -> DataFrame:
    """Both arms of a use case."""
    return union([use_case(spark, sf_dir, case, a, supersteps, times=times) for a in (True, False)])


def arms_summary(spark: SparkSession, sf_dir: str, case: str, supersteps: int = 12) -> DataFrame:
    """arm, total_ms, messaging share, mean and deviation of a superstep's time, remote messages; speedup and break-even of adapting."""
    log = cut(arms(spark, sf_dir, case, supersteps, times=True))
    total = F.expr(" + ".join(TIMES))
    each = log.select("arm", F.col("superstep").alias("iteration"), "remote", "remote_grouped", "message_ms", total.alias("step_ms"))
    out = each.groupBy("arm").agg(F.sum("step_ms").alias("total_ms"), (F.sum("message_ms") / F.sum("step_ms")).alias("messaging_share"), F.avg("step_ms").alias("mean_ms"), F.stddev_samp("step_ms").alias("std_ms"), F.sum("remote").alias("remote"), F.max_by("remote_grouped", "iteration").alias("last_remote_grouped"))
    a, b = each.where("arm = 'adaptive'"), each.where("arm = 'static'")
    return out.join(metrics.speedup(a, b)).join(metrics.break_even(a, b).withColumnRenamed("iteration", "break_even"))


def mention_cuts(spark: SparkSession, sf_dir: str, steps: int | None, k: int = 9) -> DataFrame:
    """arm, cut, edges, ratio of the mentions' ties: placed by hash for good, and adapted."""
    edges = cut(canonical(mentions(spark, sf_dir)))
    start = cut(assign_hash(vertices_of(edges), k))
    after = to_quiet(edges, start, MigrationConfig(k=k), steps)[0]
    return union([metrics.cut_ratio(edges, a).select(F.lit(arm).alias("arm"), "*") for arm, a in (("adaptive", after), ("static", start))])


def recovered(spark: SparkSession, sf_dir: str, supersteps: int = 4, lost_after: int = 2, k: int = 9) -> DataFrame:
    """vid, value, part of influence on the mentions, by a run that ends after ``lost_after`` supersteps and another that goes on from its snapshot."""
    arcs = cut(mentions(spark, sf_dir).select("src", "dst"))
    edges = cut(canonical(arcs))
    cfg, folder = MigrationConfig(k=k), f"{checkpoint_dir(spark)}/snapshots-{uuid.uuid4().hex}"
    start = assign_hash(vertices_of(edges), k)
    run_program(edges, start, engine.influence_program(), cfg, lost_after, arcs=arcs, snapshots=folder)
    values, _ = run_program(edges, start, engine.influence_program(), cfg, supersteps, arcs=arcs, snapshots=folder)
    return values


def clique_weeks(spark: SparkSession, sf_dir: str, adaptive: bool, k: int = 9) -> DataFrame:
    """week, superstep, moved, cut, edges, cliques, largest: the call graph under one-week expiry, cliques every two supersteps.

    A week's new and expired ties wait in the change queue while the topology is frozen for
    the two supersteps of the clique search; the placement adapts in each of them.
    """
    ties = cut(window_edges(spark, sf_dir))
    weeks = [r[0] for r in ties.select("week_end").distinct().orderBy("week_end").collect()]
    cfg, queue, rows = MigrationConfig(k=k, adaptive=adaptive), ChangeQueue(spark, every_n=2), []
    edges, state, vertices, t = spark.createDataFrame([], "src long, dst long"), None, None, 0
    for n, week in enumerate(weeks):
        now = ties.where(F.col("week_end") == week).select("src", "dst")
        added = now.join(edges, ["src", "dst"], "left_anti").select(F.lit("add_edge").alias("op"), "src", "dst")
        gone = edges.join(now, ["src", "dst"], "left_anti").select(F.lit("del_edge").alias("op"), "src", "dst")
        changes = added.unionAll(gone)
        if vertices is not None:  # a subscriber without a tie leaves
            idle = vertices.join(vertices_of(now), "vid", "left_anti").select(F.lit("del_vertex").alias("op"), F.col("vid").alias("src"), F.lit(None).cast("long").alias("dst"))
            changes = changes.unionAll(idle)
        queue.push(cut(changes.select(F.lit(n).cast("long").alias("seq"), "op", "src", "dst", F.lit(0).alias("priority"), F.lit(week).alias("ts"))))
        new_edges, new_vertices, _ = queue.drain(t, edges, vertices if vertices is not None else spark.createDataFrame([], "vid long"))
        edges, vertices = cut(new_edges), cut(new_vertices)
        state = cut(assign_hash(vertices, k) if state is None else reassign(state, vertices, k))
        run = Adaptation.start(edges, state, cfg, t)
        for _ in range(2):
            t += 1
            moved = run.step()["moved"] if adaptive else 0
            found = max_cliques(edges, True).agg(F.count_if(F.col("size") > 2).alias("n"), F.max("size").alias("top")).first() if t % 2 == 0 else (0, None)
            rows.append((n, t, moved, run.measure(), edges.count(), found[0], found[1]))
        state = cut(run.state.select("vid", "part"))
        run.close()
    return spark.createDataFrame(rows, "week int, superstep int, moved long, cut long, edges long, cliques long, largest int")


def window_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """week_end, src, dst, last_seen: ties whose last call is at most a week old at each week's end."""
    calls = interactions(spark, sf_dir).where("src <> dst").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "ts", (F.date_trunc("week", "ts") + F.expr("interval 7 days")).alias("week_end"))
    # a call counts at the end of its own week only: older ends are before it, later ones over a week after
    return calls.groupBy("week_end", "src", "dst").agg(F.max("ts").alias("last_seen"))


def weekly_cuts(spark: SparkSession, sf_dir: str, adaptive: bool, k: int = 9, steps: int | None = None) -> DataFrame:
    """week, cut, edges of the windowed call graph under a static or adapting placement."""
    ties = cut(window_edges(spark, sf_dir))
    weeks = [r[0] for r in ties.select("week_end").distinct().orderBy("week_end").collect()]
    placed, rows = None, []
    for n, week in enumerate(weeks):
        edges = cut(ties.where(F.col("week_end") == week).select("src", "dst"))
        v = vertices_of(edges)
        placed = cut(assign_hash(v, k) if placed is None else reassign(placed, v, k))
        if adaptive:
            placed = to_quiet(edges, placed, MigrationConfig(k=k), steps)[0].select("vid", "part")
        m = metrics.cut_edges(edges, placed).first()
        rows.append((n, m["cut"], m["edges"]))
    return spark.createDataFrame(rows, "week int, cut long, edges long")


def weekly_cliques(spark: SparkSession, sf_dir: str) -> DataFrame:
    """week_end, vid, size, members: each window's cliques, listed at their lowest members, for all weeks at once.

    A week's vertices are numbered apart from other weeks' in the order of their ids, so one
    search over the disjoint union of all windows finds each window's cliques.
    """
    ties = window_edges(spark, sf_dir).select("week_end", "src", "dst")
    ends = ties.select("week_end", F.col("src").alias("v")).unionAll(ties.select("week_end", F.col("dst").alias("v"))).distinct()
    ids = cut(global_rank(ends, "week_end", "v", name="n"))
    at = lambda c: ids.select("week_end", F.col("v").alias(c), F.col("n").alias(f"{c}_n"))
    edges = cut(ties.join(at("src"), ["week_end", "src"]).join(at("dst"), ["week_end", "dst"]).select(F.col("src_n").alias("src"), F.col("dst_n").alias("dst")))
    found = max_cliques(edges, True).select(F.col("vid").alias("at"), "size", F.posexplode(F.split("members", ",")).alias("pos", "n"))
    named = found.withColumn("n", F.col("n").cast("long")).join(ids, "n")
    lists = named.groupBy("week_end", "at", "size").agg(F.array_sort(F.collect_list(F.struct("pos", "v"))).alias("m"))
    vid = ids.select(F.col("n").alias("at"), F.col("v").alias("vid"))
    return lists.join(vid, "at").select("week_end", "vid", "size", F.concat_ws(",", F.col("m.v").cast("array<string>")).alias("members"))


def last_week(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges of the window that ends on 15 January 2024, the second week of the given events."""
    ties = window_edges(spark, sf_dir)
    return ties.where("week_end = timestamp'2024-01-15 00:00:00'").select("src", "dst")


def heart(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Edges and cells of the tissue: excitation by order price, a corner inert."""
    orders = table(spark, sf_dir, "orders", "o_orderkey", "o_totalprice")
    side = cube_side(orders.count())
    vid = F.col("o_orderkey").cast("long")
    x, y, z = vid % side, F.expr(f"(o_orderkey div {side}) % {side}"), F.expr(f"o_orderkey div {side * side}")
    frame = orders.where(vid < side**3).select(vid.alias("vid"), ((F.col("o_totalprice").cast("double") % 1000) / 1000).alias("excitation"), (x + y + z < 3).alias("inert"))
    return graph_from(spark, sf_dir, "lattice"), frame


def expanded_heart(spark: SparkSession, sf_dir: str, adaptive: bool, k: int = 9, steps: int | None = None) -> DataFrame:
    """iteration, cut, edges, moved, quiet after 10 % new cells attach at the inert region's border."""
    cfg = MigrationConfig(k=k, adaptive=adaptive)
    edges, cells = heart(spark, sf_dir)
    edges = cut(edges)
    state = to_quiet(edges, assign_hash(vertices_of(edges), k), cfg, steps)[0].select("vid", "part")
    grown = generators.attach_border(edges, cells.where("inert").select("vid"), max(1, state.count() // 10))
    edges = cut(edges.unionAll(grown).distinct())
    state = cut(reassign(state, vertices_of(edges), k))
    return to_quiet(edges, state, cfg, steps)[1].select("iteration", "cut", "edges", "moved", "quiet")


def slices(spark: SparkSession, sf_dir: str, cfg: MigrationConfig, side: int, z: int, steps: int, share: bool) -> DataFrame:
    """iteration, x, y, part of one plane of the cube as it adapts; or iteration and the share of neighbours in the plane that are together."""
    run, out = Adaptation.start(*started(spark, sf_dir, "lattice", cfg), cfg), []
    for t in range(steps + 1):
        plane = cut(metrics.same_part_slice(run.state, side, z))
        if share:
            right, below = (plane.select((F.col("x") - dx).alias("x"), (F.col("y") - dy).alias("y"), F.col("part").alias("other")) for dx, dy in ((1, 0), (0, 1)))
            both = plane.join(right, ["x", "y"]).unionAll(plane.join(below, ["x", "y"]))
            plane = both.agg((F.count_if(F.col("part") == F.col("other")) / F.count(F.lit(1))).alias("share"))
        out.append(plane.select(F.lit(t).alias("iteration"), "*"))
        if t < steps:
            run.step()
    run.close()
    return union(out)


def newcomers(spark: SparkSession, sf_dir: str, strategies=("hash", "random", "dgr"), steps: int | None = None, k: int = 9) -> DataFrame:
    """strategy, cut_before, cut_after, edges, last_move, quiet: a tenth of the orders arrive late."""
    cfg = MigrationConfig(k=k)
    edges = cut(graph_from(spark, sf_dir, "cop"))
    late = (F.col("src") % 10 == 0) | (F.col("dst") % 10 == 0)
    old = cut(edges.where(~late))
    base = cut(to_quiet(old, assign_hash(vertices_of(old), k), cfg, steps)[0].select("vid", "part"))
    v, rows = cut(vertices_of(edges)), []
    placed = [(s, cut(reassign(base, v, k, s, 0, edges))) for s in strategies]
    runs = many(edges, placed, dict.fromkeys(strategies, cfg), steps)
    for s, start in placed:
        before = metrics.cut_edges(edges, start).first()
        after = ending(runs.where(F.col("label") == s), cfg)
        rows.append((s, before["cut"], after["cut"], before["edges"], after["last_move"], after["quiet"]))
    return spark.createDataFrame(rows, "strategy string, cut_before long, cut_after long, edges long, last_move int, quiet boolean")


def superstep_log(spark: SparkSession, sf_dir: str, adaptive: bool, supersteps: int = 3) -> DataFrame:
    """superstep and counts of a least-id program on the lattice."""
    edges = cut(graph_from(spark, sf_dir, "lattice"))
    cfg = MigrationConfig(adaptive=adaptive, deferred=True)
    log = run_program(edges, assign_hash(vertices_of(edges), cfg.k), min_label_program(), cfg, supersteps)[1]
    return log_frame(spark, "", log).drop("arm")


def stream_folder(spark: SparkSession, sf_dir: str) -> tuple[str, int, str]:
    """Folder of the event files, number of users, a fresh checkpoint folder."""
    users = table(spark, sf_dir, "events", "user_id").distinct().count()
    return f"{sf_dir}", users, f"{checkpoint_dir(spark)}/stream-{uuid.uuid4().hex}"


def event_changes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A change queue made from events: most add a tie, every ninth deletes one, every fiftieth a vertex."""
    e = interactions(spark, sf_dir)
    op = F.when(F.col("event_id") % 50 == 7, "del_vertex").when(F.col("event_id") % 9 == 4, "del_edge").otherwise("add_edge")
    return e.select(F.col("event_id").alias("seq"), op.alias("op"), "src", "dst", (F.col("event_id") % 3).cast("int").alias("priority"), "ts")


def changed_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    """src, dst after the changes over the succession graph."""
    edges = graph_from(spark, sf_dir, "succession")
    return apply_changes(edges, vertices_of(edges), event_changes(spark, sf_dir))[0]

