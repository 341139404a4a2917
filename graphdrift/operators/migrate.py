"""Greedy vertex migration: histogram, candidates, coins, room, quotas, admission, the loop.

The arcs stay cached by target, so only the assignment and the pre-aggregated
histogram travel: a vertex's neighbours are counted in one column a partition, summed
before the one exchange. An iteration has two actions. The first ranks the willing of
each pair of partitions up to its quota and brings back the last one admitted (at most
k(k-1) rows); the second says of every vertex whether it comes before that one, so no
vertex is joined with the moves. Loads (k numbers) come back with it and become the
next iteration's room. The iteration's number is a column of the state, and quotas and
bounds are tables of values, so the compiled plan of one iteration serves the next. The
state is cached, and checkpointed every few iterations.
"""

from __future__ import annotations

import time
import warnings
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphdrift import schemas
from graphdrift.config import MigrationConfig
from graphdrift.functions.hashing import ADMIT, COIN, TIE, mix32, mix32_text, salt_of, salt_text, threshold
from graphdrift.functions.lineage import cut, forget
from graphdrift.operators.graph import symmetric


def neighbour_histogram(sym: DataFrame, assignment: DataFrame, count_self: bool = False) -> DataFrame:
    """vid, part, cnt: how many neighbours of a vertex are in each partition."""
    hist = sym.join(assignment.select("vid", "part"), sym.dst == F.col("vid")).groupBy(F.col("src").alias("vid"), "part").agg(F.count(F.lit(1)).alias("cnt"))
    if count_self:
        own = assignment.select("vid", "part", F.lit(1).cast("long").alias("cnt"))
        hist = hist.unionAll(own).groupBy("vid", "part").agg(F.sum("cnt").alias("cnt"))
    return hist


def candidates(hist: DataFrame, rule: str = "majority") -> DataFrame:
    """vid, parts: the partitions with the most neighbours, or (any) with at least one."""
    if rule == "majority":
        top = hist.groupBy("vid").agg(F.max("cnt").alias("top"))
        hist = hist.join(top, "vid").where("cnt = top")
    return hist.groupBy("vid").agg(F.array_sort(F.collect_set("part")).alias("parts"))


def preferred(hist: DataFrame, assignment: DataFrame, tie_break: str = "hash", iteration: int = 0, seed: int = 0) -> DataFrame:
    """vid, from_part, to_part, gain, own, degree: where each vertex would rather be; its own part wins ties.

    An arg-max by one struct aggregate; no window, no sort.
    """
    tie = mix32("vid", salt_of(seed, TIE, iteration, F.col("part"))) if tie_break == "hash" else F.lit(0).cast("long")
    own = (F.col("part") == F.col("cur")).cast("int")
    rows = hist.join(assignment.select("vid", F.col("part").alias("cur")), "vid")
    best = rows.groupBy("vid", "cur").agg(
        F.max(F.struct("cnt", own.alias("own"), tie.alias("tie"), (-F.col("part")).alias("p"))).alias("b"),
        F.sum(F.col("cnt") * own).alias("own"),
        F.sum("cnt").alias("degree"),
    )
    return best.select("vid", F.col("cur").alias("from_part"), (-F.col("b.p")).alias("to_part"), (F.col("b.cnt") - F.col("own")).alias("gain"), "own", "degree")


def damped(proposals: DataFrame, s: float, iteration: int, seed: int = 0) -> DataFrame:
    """Proposals whose coin came up (chance ``s``); the coin is a function of (vid, iteration, seed)."""
    return proposals.where(coin(s, iteration, seed))


def coin(s: float, iteration: int, seed: int) -> Column:
    return F.expr(f"{mix32_text('vid', salt_text(seed, COIN, iteration))} < {threshold(s)}")


def capacity_plan(n: int, k: int, slack: float | None = 1.10, vector: tuple[int, ...] | None = None, loads: list[int] | None = None) -> list[int]:
    """Capacities: a given vector, none (n each), or the mean load with slack but no less than the largest load."""
    if vector is not None:
        return list(vector)
    if slack is None:
        return [n] * k
    return [max(-(-n * round(slack * 100) // (100 * k)), *(loads or [0]))] * k


def partition_room(assignment: DataFrame, caps: list[int]) -> DataFrame:
    """part, cap, load, remaining: k rows, empty partitions included."""
    spark = assignment.sparkSession
    dim = spark.createDataFrame(list(enumerate(caps)), "part int, cap long")
    load = assignment.groupBy("part").agg(F.count(F.lit(1)).alias("load"))
    out = dim.join(load, "part", "left").select("part", "cap", F.coalesce("load", F.lit(0)).alias("load"))
    return out.withColumn("remaining", F.greatest(F.lit(0), F.col("cap") - F.col("load")))


def quota_of(remaining: Column, from_part: Column, to_part: Column, k: int, remainder: str = "rotate", iteration: int = 0) -> Column:
    """Most moves from one partition to another this iteration: an equal share of the target's room.

    What does not divide is dropped, or handed to sources by turns; shares never sum to more than the room.
    """
    if k < 2:
        return F.lit(0).cast("long")
    base = F.floor(remaining / F.lit(k - 1)).cast("long")
    if remainder == "drop":
        return base
    turn = F.pmod(F.when(from_part < to_part, from_part).otherwise(from_part - 1) - F.lit(iteration), F.lit(k - 1))
    return base + (turn < remaining % (k - 1)).cast("long")


def pair_quotas(room: DataFrame, k: int, remainder: str = "rotate", iteration: int = 0) -> DataFrame:
    """from_part, to_part, quota for all k(k-1) pairs (for reports; the loop computes quotas in place)."""
    source = F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias("from_part")
    pairs = room.select(F.col("part").alias("to_part"), "remaining", source).where("from_part <> to_part")
    return pairs.select(F.col("from_part").cast("int").alias("from_part"), "to_part", quota_of(F.col("remaining"), F.col("from_part"), F.col("to_part"), k, remainder, iteration).alias("quota"))


def _order(admission: str, iteration: int, seed: int):
    h = F.expr(mix32_text("vid", salt_text(seed, ADMIT, iteration)))
    first = [F.desc("gain")] if admission == "gain" else []
    return Window.partitionBy("from_part", "to_part").orderBy(*first, h, "vid")


def admit(proposals: DataFrame, room: DataFrame | list[int], k: int, cfg: MigrationConfig, iteration: int, most: int | None = None) -> DataFrame:
    """Proposals within their pair's quota.

    ``room``: a frame of parts and their remaining places, or those as a list, whose
    largest quota is then the literal bound (``most``) that limits groups before the exchange.
    """
    listed = isinstance(room, list)
    ranked = proposals.withColumn("rn", F.row_number().over(_order(cfg.admission, iteration, cfg.seed)))
    if listed:
        most = max(room) // max(1, k - 1) + 1
        ranked = ranked.withColumn("remaining", F.expr(f"array({', '.join(f'{r}L' for r in room)})[to_part]"))
    if most is not None:
        ranked = ranked.where(F.col("rn") <= most)
    if not listed:
        ranked = ranked.join(F.broadcast(room.select(F.col("part").alias("to_part"), "remaining")), "to_part")
    fits = ranked.where(F.col("rn") <= quota_of(F.col("remaining"), F.col("from_part"), F.col("to_part"), k, cfg.quota_remainder, iteration))
    return fits.select("vid", "from_part", "to_part", "gain")


def apply_moves(assignment: DataFrame, moves: DataFrame) -> DataFrame:
    """All movers change place at once."""
    m = moves.select("vid", F.col("to_part").alias("__to"))
    return assignment.join(m, "vid", "left").withColumn("part", F.coalesce("__to", "part")).drop("__to")


def refresh_histogram(hist: DataFrame, moves: DataFrame, sym: DataFrame) -> DataFrame:
    """The histogram after moves, from the movers' arcs alone."""
    at = moves.join(sym, moves.vid == sym.src).select(F.col("dst").alias("n"), "from_part", "to_part")
    delta = at.select(F.col("n").alias("vid"), F.explode(F.array(F.struct(F.col("from_part").alias("part"), F.lit(-1).cast("long").alias("cnt")), F.struct(F.col("to_part").alias("part"), F.lit(1).cast("long").alias("cnt")))).alias("d")).select("vid", "d.part", "d.cnt")
    return hist.unionAll(delta).groupBy("vid", "part").agg(F.sum("cnt").alias("cnt")).where("cnt <> 0")


def full_state(assignment: DataFrame) -> DataFrame:
    """vid, part, home, settle: announced and physical place, and the iteration at whose end a pending move settles."""
    if "home" in assignment.columns:
        return assignment.select("vid", "part", "home", "settle")
    return assignment.select("vid", "part", F.col("part").alias("home"), F.lit(None).cast("int").alias("settle"))


#: Partitions up to which neighbours are counted in one column a partition.
WIDE = 64
#: Arcs of one vertex that one task may hold; a hub with more is split over several.
HUB_ARCS = 1_000_000


@dataclass
class Adaptation:
    """A running adaptation: cached arcs, the current state, loads, and the history so far."""

    spark: SparkSession
    sym: DataFrame
    state: DataFrame
    cfg: MigrationConfig
    caps: list[int]
    loads: list[int]
    iteration: int = 0
    history: list[dict] = field(default_factory=list)
    checkpoint: DataFrame | None = None
    hubs: DataFrame | None = None

    @classmethod
    def start(cls, edges: DataFrame, assignment: DataFrame, cfg: MigrationConfig, iteration: int = 0) -> Adaptation:
        spark, sym = edges.sparkSession, symmetric(edges)
        degrees = sym.groupBy(F.col("dst").alias("hub")).agg(F.expr(f"cast((count(1) - 1) div {HUB_ARCS} + 1 as int) pieces"))
        hubs = cut(degrees.where("pieces > 1"))  # a row or less for every HUB_ARCS arcs
        if hubs.limit(1).count():
            piece = F.pmod(F.xxhash64("src"), F.coalesce("pieces", F.lit(1))).cast("int")
            sym = sym.join(F.broadcast(hubs), F.col("dst") == F.col("hub"), "left").select("src", "dst", piece.alias("piece"))
        else:
            hubs, sym = None, sym.withColumn("piece", F.lit(0))
        # a fixed number of partitions, so that adaptive execution keeps what the join needs
        keys = ["dst"] if hubs is None else ["dst", "piece"]
        sym = sym.repartition(int(spark.conf.get("spark.sql.shuffle.partitions")), *keys).sortWithinPartitions(*keys).persist()
        state = cut(full_state(assignment).withColumn("t", F.lit(iteration).cast("long")))
        loads = [0] * cfg.k
        for r in state.groupBy("part").agg(F.count(F.lit(1)).alias("n")).collect():
            loads[r["part"]] = r["n"]
        caps = capacity_plan(sum(loads), cfg.k, cfg.slack if cfg.use_quota else None, cfg.caps, loads)
        return cls(spark, sym, state, cfg, caps, loads, iteration, hubs=hubs)

    def beside_arcs(self, arcs: DataFrame, rows: DataFrame, vid: str) -> DataFrame:
        """The cached arcs, as they lie, with the rows of the vertices that they are cached by; a hub's go to each piece of its arcs."""
        if self.hubs is None:  # a piece that is the same for all would drop out of the join's keys, and the arcs be shuffled
            return arcs.join(rows, vid)
        pieces = F.explode(F.sequence(F.lit(0), F.coalesce("pieces", F.lit(1)) - 1))
        rows = rows.join(F.broadcast(self.hubs), F.col(vid) == F.col("hub"), "left").select(*rows.columns, pieces.alias("piece"))
        return arcs.join(rows, [vid, "piece"])

    @property
    def outward(self) -> DataFrame:
        """The arcs as those that leave the vertex they are cached by: both directions are there."""
        return self.sym.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "piece")

    def _counted(self) -> DataFrame:
        """vid, part, home, settle, t, want, top, here, degree: each vertex's best partition, and its neighbours there, at home and in all.

        Arcs and the state are one union: a vertex's own row tells its place. Hubs shrink
        to a row a task before the exchange. Beyond WIDE partitions the histogram has a row
        a vertex and partition instead of a column.
        """
        cfg = self.cfg
        place = self.state.select(F.col("vid").alias("dst"), "part")
        arcs = self.beside_arcs(self.sym, place, "dst").selectExpr("src vid", "part", "1L n", "cast(null as int) home", "cast(null as int) settle", "cast(null as bigint) t")
        own = self.state.selectExpr("vid", "part", f"{int(cfg.count_self)}L n", "home", "settle", "t + 1 t")
        rows = arcs.unionAll(own)
        tie = mix32_text("vid", salt_text(cfg.seed, TIE, 0, "p", "t")) if cfg.tie_break == "hash" else "0L"
        size = "n" if cfg.candidate_rule == "majority" else "least(n, 1L)"
        # a vertex that has its own part among the best stays; ties are drawn for the others alone
        if cfg.k <= WIDE:
            counts = [F.expr(f"sum(if(part = {p}, n, 0L)) c{p}") for p in range(cfg.k)]
            one = rows.groupBy("vid").agg(*counts, F.expr("max(if(home is null, null, part)) part"), F.expr("max(home) home"), F.expr("max(settle) settle"), F.expr("max(t) t")).where("home is not null")
            columns = [f"c{p}" for p in range(cfg.k)]
            each = one.selectExpr("vid", "part", "home", "settle", "t", f"array({', '.join(columns)}) c", f"{' + '.join(columns)} degree")
            if cfg.candidate_rule != "majority":
                each = each.withColumn("w", F.expr("transform(c, n -> least(n, 1L))"))
            w = "c" if cfg.candidate_rule == "majority" else "w"
            others = f"-array_max(transform(filter(sequence(0, {cfg.k - 1}), p -> {w}[p] = array_max({w})), p -> struct({tie} as tie, -p as p))).p"
            return each.withColumn("want", F.expr(f"if({w}[part] = array_max({w}), part, {others})")).selectExpr("vid", "part", "home", "settle", "t", "want", "c[want] top", "c[part] here", "degree")
        hist = rows.groupBy("vid", "part").agg(F.sum("n").alias("n"), F.max("home").alias("home"), F.max("settle").alias("settle"), F.max("t").alias("t"))
        # the vertex's t is known to its own row alone, so ties are drawn once its parts are together
        each = hist.groupBy("vid").agg(F.expr(f"collect_list(struct(part p, {size} w, n)) h"), F.expr("max(if(home is null, null, part)) part"), F.expr("max(home) home"), F.expr("max(settle) settle"), F.expr("max(t) t"), F.expr("sum(n) degree"), F.expr("sum(if(home is null, 0L, n)) here")).where("home is not null")
        each = each.withColumn("b", F.expr(f"array_max(transform(h, x -> struct(x.w as w, x.p = part as o, {tie.replace('cast(p as bigint)', 'cast(x.p as bigint)')} as tie, -x.p as p, x.n as n)))"))
        return each.selectExpr("vid", "part", "home", "settle", "t", "-b.p want", "b.n top", "here", "degree")

    def proposals(self) -> DataFrame:
        """Every vertex with its state, the part it would rather be in, whether it asks for it, its coin, and its place in the queue."""
        cfg = self.cfg
        free = "(settle is null or settle < t)" if cfg.deferred else "true"
        head = f"{mix32_text('vid', salt_text(cfg.seed, COIN, 0, '0', 't'))} < {threshold(cfg.s if cfg.adaptive else 0.0)}"
        first = "here - top" if cfg.admission == "gain" else "0L"
        queue = f"struct({first} g, {mix32_text('vid', salt_text(cfg.seed, ADMIT, 0, '0', 't'))} h, vid v)"
        return self._counted().selectExpr("*", f"want <> part and {free} wanted").selectExpr("*", f"wanted and {head} acted", f"{queue} queue")

    def _last_admitted(self, wants: DataFrame) -> DataFrame | None:
        """part, want, last: the place in the queue of the last one that each pair's quota admits."""
        cfg, k, t = self.cfg, self.cfg.k, self.iteration
        room = [max(0, c - n) for c, n in zip(self.caps, self.loads)]
        quota = {}
        for i in range(k):
            for j in range(k):
                turn = ((i if i < j else i - 1) - t) % max(1, k - 1)
                n = room[j] // max(1, k - 1) + (cfg.quota_remainder == "rotate" and turn < room[j] % max(1, k - 1))
                if i != j and n:
                    quota[i, j] = n
        if not quota:
            return None
        pairs = self.spark.sql(f"select * from values {', '.join(f'({i}, {j}, {n}L)' for (i, j), n in quota.items())} as q(part, want, quota)")
        rank = F.row_number().over(Window.partitionBy("part", "want").orderBy("queue"))
        # the literal bound lets Spark limit groups before the exchange
        ranked = wants.where("acted").select("part", "want", "queue").withColumn("rn", rank).where(F.col("rn") <= max(quota.values()))
        last = ranked.join(F.broadcast(pairs), ["part", "want"]).where("rn <= quota").groupBy("part", "want").agg(F.max("queue").alias("q")).collect()
        if not last:
            return None
        rows = ", ".join(f"({r['part']}, {r['want']}, {r['q']['g']}L, {r['q']['h']}L, {r['q']['v']}L)" for r in last)
        return self.spark.sql(f"select part, want, struct(g, h, v) last from values {rows} as q(part, want, g, h, v)")

    def step(self) -> dict:
        """One iteration; returns its history row (``cut`` is that of the state it found)."""
        cfg, began = self.cfg, time.time()
        self.iteration = t = self.iteration + 1
        wants = self.proposals().persist()  # read by the admission and again by its outcome
        if cfg.use_quota:
            last = self._last_admitted(wants)
            told = wants.withColumn("moved", F.lit(False)) if last is None else wants.join(F.broadcast(last), ["part", "want"], "left").withColumn("moved", F.expr("acted and last is not null and queue <= last"))
        else:
            told = wants.withColumn("moved", F.col("acted"))
        decided = time.time()
        if cfg.deferred:
            home = "case when moved then home when settle <= t then part else home end"
            settle = "case when moved then t + 1 when settle > t then settle end"
        else:
            home, settle = "case when moved then want when settle <= t then part else home end", "cast(null as int)"
        new = told.selectExpr("vid", "if(moved, want, part) part", f"{home} home", f"cast({settle} as int) settle", "t", "moved", "wanted", "acted", "degree - here away", "degree")
        new = cut(new)
        wants.unpersist()
        count = lambda c: F.sum(F.col(c).cast("long")).alias(c)
        per_part = new.groupBy("part").agg(F.count(F.lit(1)).alias("n"), count("moved"), count("wanted"), count("acted"), count("away"), count("degree")).collect()
        self.state = new.select("vid", "part", "home", "settle", "t")
        if self.checkpoint is not None:
            forget(self.checkpoint)
        self.checkpoint = new
        self.loads = [0] * cfg.k
        for r in per_part:
            self.loads[r["part"]] = r["n"]
        total = {c: sum(r[c] for r in per_part) for c in ("moved", "wanted", "acted", "away", "degree")}
        extra = sum(self.loads) if cfg.count_self else 0
        row = {
            "iteration": t, "proposed": total["wanted"], "damped": total["wanted"] - total["acted"], "refused": total["acted"] - total["moved"], "moved": total["moved"],
            "cut_before": total["away"] // 2, "edges": (total["degree"] - extra) // 2, "max_load": max(self.loads), "min_load": min(self.loads),
            "decide_ms": int(1000 * (decided - began)), "migrate_ms": int(1000 * (time.time() - decided)), "step_ms": int(1000 * (time.time() - began)),
        }
        self.history.append(row)
        return row

    def measure(self) -> int:
        """Cut edges of the present state."""
        from graphdrift.operators.metrics import cut_edges

        both = cut_edges(self.sym.where("src < dst"), self.state).first()
        return both["cut"] or 0

    def rows(self) -> list[tuple]:
        """The history with the cut each iteration left, in HISTORY's order."""
        after = [h["cut_before"] for h in self.history[1:]] + ([self.measure()] if self.history else [])
        return [(h["iteration"], h["proposed"], h["damped"], h["refused"], h["moved"], c, h["edges"], h["max_load"], h["min_load"], h["step_ms"]) for h, c in zip(self.history, after)]

    def close(self) -> None:
        self.sym.unpersist()


def quiet_for(moved: list[int], patience: int = 30) -> bool:
    """More than ``patience`` iterations in a row without a move, up to now."""
    return len(moved) > patience and not any(moved[-patience - 1 :])


def convergence_iteration(moved: list[int]) -> int:
    """The iteration (from 1) of the last move; 0 if none moved."""
    return max((i + 1 for i, m in enumerate(moved) if m), default=0)


def adapt(edges: DataFrame, assignment: DataFrame, cfg: MigrationConfig, iterations: int | None = None) -> tuple[DataFrame, DataFrame]:
    """Run to quiescence (or ``iterations``); the final state and the history.

    A run to quiescence that meets ``cfg.max_iter`` first says so in a warning.
    """
    run = Adaptation.start(edges, assignment, cfg)
    last = cfg.max_iter if iterations is None else iterations
    while run.iteration < last:
        run.step()
        if iterations is None and quiet_for([h["moved"] for h in run.history], cfg.patience):
            break
    else:
        if iterations is None:
            warnings.warn(f"not quiet after {last} iterations", stacklevel=2)
    history = run.spark.createDataFrame(run.rows(), schemas.HISTORY)
    run.close()
    return run.state.select("vid", "part", "home", "settle"), history


def repartition_from_scratch(edges: DataFrame, vertices: DataFrame, cfg: MigrationConfig) -> tuple[DataFrame, DataFrame]:
    """Hash again and adapt to quiescence: the costly answer to change."""
    from graphdrift.operators.initial import assign_hash

    return adapt(edges, assign_hash(vertices, cfg.k, True, cfg.seed), cfg)


def worth_adapting(expected_iterations: int, static_ms: float, adaptive_ms: list[float], settled_ms: float) -> bool:
    """Does the adaptive run's total fall below the static one's within the expected iterations?"""
    n = min(expected_iterations, len(adaptive_ms))
    return sum(adaptive_ms[:n]) + (expected_iterations - n) * settled_ms < expected_iterations * static_ms


def label_propagation(sym: DataFrame, labels: DataFrame, iterations: int | None) -> DataFrame:
    """vid, label: unlabelled vertices take their neighbours' majority label (lowest on ties); seeds are fixed.

    For ``iterations``, or (None) until stable: until the labels are those of the step
    before or of the one before that, as majorities taken all at once can swing to and fro.
    """
    now = cut(labels.select("vid", F.col("label").cast("int").alias("part"), F.col("label").isNotNull().alias("seed")))
    sym, seen, done = sym.persist(), [], 0
    while iterations is None or done < iterations:
        hist = neighbour_histogram(sym, now.where("part is not null"))
        best = hist.groupBy("vid").agg(F.max(F.struct("cnt", (-F.col("part")).alias("p"))).alias("b")).select("vid", (-F.col("b.p")).alias("new"))
        old, now = now, cut(now.join(best, "vid", "left").select("vid", F.when(F.col("seed"), F.col("part")).otherwise(F.coalesce("new", "part")).alias("part"), "seed"))
        forget(old)
        done += 1
        if iterations is None:
            state = now.agg(F.sum(F.xxhash64("vid", "part").cast("decimal(20,0)"))).first()[0]
            if state in seen[-2:]:
                break
            seen.append(state)
    sym.unpersist()
    return now.select("vid", F.col("part").alias("label"))
