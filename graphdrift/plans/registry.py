"""Every query of the graph engine by name, with its DuckDB SQL where SQL can express it."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphdrift.config import MigrationConfig
from graphdrift.functions.lineage import checkpoint_dir, cut
from graphdrift.operators import apps, changes, deferred, engine, initial, metrics, migrate
from graphdrift.operators.graph import localise, locate, propagate_moves, symmetric, vertices_of
from graphdrift.plans import oracles as o
from graphdrift.plans import workloads as w
from graphdrift.sources import generators
from graphdrift.sources.graphs import GRAPHS, graph_from, interactions, mentions, next_key, table
from graphdrift.streaming import front

K = 9
_QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
_SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        _QUERIES[name] = f
        if sql:
            _SQL[name] = sql
        return f

    return add


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """History of three migration iterations on the lattice."""
    h = w.run_history(spark, sf_dir, "lattice", MigrationConfig(), 3)
    return h.select("iteration", "moved", "cut", "edges", (F.col("cut") / F.col("edges")).alias("cut_ratio"), "max_load")


# ---------------------------------------------------------------- graphs

for _name in GRAPHS:
    query(f"{_name}_edges", o.EDGES[_name])(lambda spark, d, n=_name: graph_from(spark, d, n))

query("mention_arcs", f"select src, dst, count(*) weight from ({o.CALL}) where src <> dst group by all")(lambda s, d: mentions(s, d))
query("degree_profile", o.on_edges("copurchase", "select degree, count(*) vertices from (select src, count(*) degree from sym group by src) group by degree"))(lambda s, d: metrics.degree_profile(graph_from(s, d, "copurchase")))

# ---------------------------------------------------------------- placements


def _placed(s: SparkSession, d: str, name: str, kind: str) -> tuple[DataFrame, DataFrame]:
    edges, a = w.started(s, d, name, MigrationConfig(k=K), kind)
    return edges, a


for _kind in ("hsh", "hsh_mixed", "rnd"):
    query(f"assign_{_kind}", o.on_edges("custsupp", o.assignment(_kind, K)))(lambda s, d, k=_kind: _placed(s, d, "custsupp", k)[1])
    query(f"cut_ratio_{_kind}", o.placed("custsupp", _kind, K, "select count(*) filter (src_part <> dst_part) cut, count(*) edges, count(*) filter (src_part <> dst_part) / count(*) ratio from l"))(lambda s, d, k=_kind: metrics.cut_ratio(*_placed(s, d, "custsupp", k)))
    query(f"balance_{_kind}", o.placed("custsupp", _kind, K, f"select sum(n)::bigint n, max(n) max_load, min(n) min_load, max(n) * {K} / sum(n) max_over_mean, 0::bigint as over from (select count(vid) n from range({K}) r(part) left join a using (part) group by r.part)"))(lambda s, d, k=_kind: metrics.balance(_placed(s, d, "custsupp", k)[1], K))


def _streamed(s: SparkSession, d: str, rule: str, below: int | None = None) -> DataFrame:
    """All vertices of the succession graph; with ``below``, what lower ids make of it."""
    edges = graph_from(s, d, "succession")
    if below is not None:
        edges = edges.where((F.col("src") < below) & (F.col("dst") < below))
    return initial.stream_exact(edges, vertices_of(edges), 3, rule)


def _stream_sql(rule: str, k: int = 3) -> str:
    """The stream as a recursion that carries the places so far as a list."""
    near = "coalesce(len(list_filter(st.placed, lambda p: p.part = i and list_contains(s.nbrs, p.vid))), 0)"
    load = "coalesce(len(list_filter(st.placed, lambda p: p.part = i)), 0)"
    score = {"dgr": f"{near} * (cap - {load})", "mnn": f"{near} - {load}", "mnn_literal": f"-{near}"}[rule]
    edges = o.EDGES["succession"]
    return f"""with recursive {o.graph("", f"select * from ({edges}) where src < 60 and dst < 60")},
s as materialized (select src vid, list(dst) nbrs, row_number() over (order by src) pos from sym group by src),
cap as (select (count(*) + {k - 1}) // {k} cap from s),
st as (select 0::bigint pos, []::struct(vid bigint, part int)[] placed
  union all select s.pos, list_append(st.placed, {{'vid': s.vid, 'part': (select i from (select i::int i, {load} l, {score} sc from range({k}) r(i), cap) order by (l < (select cap from cap)) desc, sc desc, l, i limit 1)}}) from st join s on s.pos = st.pos + 1)
select p.vid, p.part from (select unnest(placed) p from st where pos = (select max(pos) from s))"""


for _rule in ("dgr", "mnn", "mnn_literal"):
    query(f"assign_{_rule}_60", _stream_sql(_rule))(lambda s, d, r=_rule: _streamed(s, d, r, 60))
    query(f"assign_{_rule}")(lambda s, d, r=_rule: _streamed(s, d, r))
query("assign_dgr_chunked")(lambda s, d: _placed(s, d, "succession", "dgr")[1])

# ---------------------------------------------------------------- one iteration in parts

_A = f"a as materialized ({o.assignment('hsh_mixed', K)})"


def _parts(s: SparkSession, d: str, count_self: bool = False) -> tuple[DataFrame, DataFrame, DataFrame]:
    edges, a = _placed(s, d, "lattice", "hsh_mixed")
    a = cut(a)
    return edges, a, migrate.neighbour_histogram(symmetric(edges), a, count_self)


query("neighbour_histogram", o.on_edges("lattice", f"select vid, p as part, cnt from ({o.histogram('a')})", _A))(lambda s, d: _parts(s, d)[2])
query("neighbour_histogram_self", o.on_edges("lattice", f"select vid, p as part, cnt from ({o.histogram('a', True)})", _A))(lambda s, d: _parts(s, d, True)[2])
for _rule, _keep in (("majority", "cnt = m"), ("any", "true")):
    query(f"candidates_{_rule}", o.on_edges("lattice", f"select vid, string_agg(p::varchar, ',' order by p) parts from (select *, max(cnt) over (partition by vid) m from ({o.histogram('a')})) where {_keep} group by vid", _A))(
        lambda s, d, r=_rule: migrate.candidates(_parts(s, d)[2], r).select("vid", F.concat_ws(",", F.col("parts").cast("array<string>")).alias("parts"))
    )

_ONE = MigrationConfig(k=K)


def _preferred(s: SparkSession, d: str) -> DataFrame:
    _, a, hist = _parts(s, d)
    return migrate.preferred(hist, a, "hash", 1, 0).where("from_part <> to_part").select("vid", "from_part", "to_part", "gain")


_BEGUN = o.begin("lattice", _ONE)
_WANTED = "(select vid, part, p, gain from w1)"
query("preferred_moves", f"with {_BEGUN}, {o.migrations(_ONE, 1)} select vid, part from_part, p to_part, gain from w1")(_preferred)
for _s in (0.0, 0.5, 1.0):
    _c = _ONE.but(s=_s)
    query(f"damped_s{round(100 * _s)}", f"with {_BEGUN}, {o.migrations(_c, 1)} select vid, part from_part, p to_part, gain from w1 where acted")(lambda s, d, c=_c: migrate.damped(_preferred(s, d), c.s, 1, 0))


def _room(s: SparkSession, d: str) -> DataFrame:
    edges, a = _placed(s, d, "lattice", "hsh_mixed")
    a = cut(a)
    loads = [r["n"] for r in a.groupBy("part").agg(F.count(F.lit(1)).alias("n")).collect()]
    return migrate.partition_room(a, migrate.capacity_plan(sum(loads), K, 1.10, None, loads))


_ROOM = f"room as (select part, c::bigint cap, load, greatest(0, c - load)::bigint remaining from (select parts.part, count(a0.vid) load from parts left join a0 on a0.part = parts.part group by parts.part), cap)"
query("partition_room", f"with {_BEGUN}, {o.migrations(_ONE, 1)}, {_ROOM} select part, cap, load, remaining from room")(_room)
for _rem in ("drop", "rotate"):
    _extra = f" + (((case when f.part < t.part then f.part else f.part - 1 end - 1 + {K - 1}) % {K - 1}) < remaining % {K - 1})::int" if _rem == "rotate" else ""
    query(f"pair_quotas_{_rem}", f"with {_BEGUN}, {o.migrations(_ONE, 1)}, {_ROOM} select f.part from_part, t.part to_part, (remaining // {K - 1}{_extra})::bigint quota from parts f join room t on f.part <> t.part")(lambda s, d, r=_rem: migrate.pair_quotas(_room(s, d), K, r, 1))
for _adm in ("gain", "hash"):
    _c = _ONE.but(admission=_adm, s=1.0, slack=1.01)
    query(f"admitted_moves_{_adm}", f"with {_BEGUN}, {o.migrations(_c, 1)} select vid, from_part, to_part, gain from m1")(lambda s, d, c=_c: _admitted(s, d, c))


def _admitted(s: SparkSession, d: str, c: MigrationConfig) -> DataFrame:
    edges, a = _placed(s, d, "lattice", "hsh_mixed")
    a = cut(a)
    loads = [0] * K
    for r in a.groupBy("part").agg(F.count(F.lit(1)).alias("n")).collect():
        loads[r["part"]] = r["n"]
    caps = migrate.capacity_plan(sum(loads), K, c.slack, None, loads)
    wants = migrate.damped(_preferred(s, d), c.s, 1, 0)
    return migrate.admit(wants, migrate.partition_room(a, caps), K, c, 1, max(caps))


query("step_once", o.final("lattice", _ONE, 1, "select vid, part from a1"))(lambda s, d: w.run_state(s, d, "lattice", _ONE, 1).select("vid", "part"))
for _n, _c in (("adapt_t3", _ONE), ("adapt_deferred_t3", _ONE.but(deferred=True)), ("adapt_self_t3", _ONE.but(count_self=True))):
    query(_n, o.final("lattice", _c, 3, "select vid, part from a3"))(lambda s, d, c=_c: w.run_state(s, d, "lattice", c, 3).select("vid", "part"))
query("adapt_history_t4", o.history("lattice", _ONE, 4))(lambda s, d: w.run_history(s, d, "lattice", _ONE, 4))
query("adapt_history_custsupp_t3", o.history("custsupp", _ONE, 3))(lambda s, d: w.run_history(s, d, "custsupp", _ONE, 3))
for _n, _g in (("adapt_history", "lattice"), ("adapt_history_custsupp", "custsupp")):
    query(_n)(lambda s, d, g=_g: w.run_history(s, d, g, _ONE, None))


def _incremental(s: SparkSession, d: str) -> DataFrame:
    edges, a, hist = _parts(s, d)
    moves = cut(_admitted(s, d, _ONE))
    return migrate.refresh_histogram(hist, moves, symmetric(edges))


query("refreshed_histogram", f"with {_BEGUN}, {o.migrations(_ONE, 1)} select vid, p as part, cnt from ({o.histogram('a1')})")(_incremental)


def _forecast(s: SparkSession, d: str) -> DataFrame:
    return deferred.forecast_room(_room(s, d), cut(_admitted(s, d, _ONE)))


query("room_forecast", f"with {_BEGUN}, {o.migrations(_ONE, 1)} select part, (c - (select count(*) from a1 where a1.part = parts.part))::bigint remaining from parts, cap")(_forecast)


def _told(s: SparkSession, d: str) -> DataFrame:
    edges, a = _placed(s, d, "lattice", "hsh_mixed")
    return propagate_moves(localise(edges, cut(a)), cut(_admitted(s, d, _ONE)))


query("propagated_moves", f"with {_BEGUN}, {o.migrations(_ONE, 1)} select src, dst, x.part src_part, y.part dst_part from edges join a1 x on x.vid = src join a1 y on y.vid = dst")(_told)


_LATE = _ONE.but(deferred=True)


def _deliveries_sql(steps: int) -> str:
    """Stray messages by recount: who is physically elsewhere than its neighbours knew as the superstep began."""

    def home(t: int) -> str:
        before = f"ho{t - 1}" if t > 1 else "a0"
        return f"ho{t} as materialized (select a.vid, case when a.settle = {t + 1} then b.part else a.part end part from a{t} a join {before} b on a.vid = b.vid)"

    def stray(t: int, at: str) -> str:
        return f"(select count(*) from sym join a{t - 1} x on x.vid = dst join {at} y on y.vid = dst where x.part <> y.part)"

    sent = "(select count(*) from sym)"
    quick = " union all ".join(f"select unnest(['immediate', 'forward', 'rewrite']) as mode, {t}::int superstep, {sent} sent, unnest([n, 0, 0])::bigint lost, unnest([0, n, 0])::bigint forwarded, unnest([0, 0, n])::bigint rewritten from (select {stray(t, f'a{t}')} n)" for t in range(1, steps + 1))
    late = " union all ".join(f"select 'deferred' as mode, {t}::int superstep, {sent} sent, {stray(t, f"ho{t}")} lost, 0::bigint forwarded, 0::bigint rewritten" for t in range(1, steps + 1))
    homes = ", ".join(home(t) for t in range(1, steps + 1))
    return f"select * from (with {_BEGUN}, {o.migrations(_ONE, steps)} {quick}) union all select * from (with {_BEGUN}, {o.migrations(_LATE, steps)}, {homes} {late})"


query("message_deliveries", _deliveries_sql(3))(lambda s, d: deferred.deliveries(*w.started(s, d, "lattice", _ONE), _ONE, 3))
query("adapt_history_measures_t3", f"select iteration, moved, run, (run / sum(moved) over ()) share, (first_value(cut) over (order by iteration) - cut) gain from (select *, (sum(moved) over (order by iteration))::bigint run from ({o.history('lattice', _ONE, 3)}))")(
    lambda s, d: metrics.accumulated(w.run_history(s, d, "lattice", _ONE, 3)).select("iteration", "moved", "run", "share", "gain")
)
query("iterations_to_half_t4", f"select min(iteration) iteration from (select iteration, sum(moved) over (order by iteration) / sum(moved) over () share from ({o.history('lattice', _ONE, 4)})) where share >= 0.5")(lambda s, d: metrics.iterations_to(w.run_history(s, d, "lattice", _ONE, 4), 0.5))
query("adapt_history_measures")(lambda s, d: metrics.accumulated(w.run_history(s, d, "lattice", _ONE, None)).select("iteration", "moved", "run", "share", "gain", "quiet"))
query("iterations_to_half")(lambda s, d: metrics.iterations_to(w.run_history(s, d, "lattice", _ONE, None), 0.5))

query("cut_gain_t3", o.final("lattice", _ONE, 3, f"select before, after, (before - after) gain, (before - after) / before relative from (select {o.cut_of('a0')} before, {o.cut_of('a3')} after)"))(
    lambda s, d: (lambda e, a: metrics.cut_gain(e, a, migrate.adapt(e, a, _ONE, 3)[0]))(*w.started(s, d, "lattice", _ONE))
)
query("convergence_iteration_t4", f"select max(case when moved > 0 then iteration else 0 end)::int iteration from ({o.history('lattice', _ONE, 4)})")(lambda s, d: metrics.converged_at(w.run_history(s, d, "lattice", _ONE, 4)))
query("convergence_iteration")(lambda s, d: metrics.converged_at(w.run_history(s, d, "lattice", _ONE, None)))
#: Every other partition closed: a vector of capacities instead of slack.
_CAPS = _ONE.but(caps=tuple(10**9 if p % 2 else 0 for p in range(K)))
query("adapt_capacity_vector_t2", o.final("lattice", _CAPS, 2, "select vid, part from a2"))(lambda s, d: w.run_state(s, d, "lattice", _CAPS, 2).select("vid", "part"))
_ANY = _ONE.but(candidate_rule="any")
query("adapt_any_candidate")(lambda s, d: w.run_history(s, d, "lattice", _ANY, None))


def _grouped(s: SparkSession, d: str) -> DataFrame:
    edges, a = _placed(s, d, "cop", "hsh_mixed")
    sent = engine.combine_messages(engine.local_and_remote(symmetric(edges), a.withColumn("value", F.lit(0).cast("long")), engine.degree_program()), engine.degree_program())
    return sent.groupBy("src_part", "dst_part").agg(F.count(F.lit(1)).alias("grouped"), F.sum("n").alias("messages"))


query("grouped_messages", o.placed("cop", "hsh_mixed", K, "select x.part src_part, y.part dst_part, count(distinct dst) as grouped, count(*) messages from sym join a x on x.vid = src join a y on y.vid = dst group by 1, 2"))(_grouped)
query("locate_vertices", o.placed("custsupp", "hsh_mixed", K, "select o_custkey::bigint vid, part from (select distinct o_custkey from orders union all select 1000000000 + max(o_custkey) from orders) left join a on a.vid = o_custkey"))(
    lambda s, d: (lambda ids: locate(_placed(s, d, "custsupp", "hsh_mixed")[1], ids.unionAll(ids.agg((F.max("vid") + 1_000_000_000).alias("vid")))))(table(s, d, "orders", "o_custkey").distinct().select(F.col("o_custkey").cast("long").alias("vid")))
)

# ---------------------------------------------------------------- measures

query("cut_matrix", o.placed("cop", "hsh_mixed", K, "select least(src_part, dst_part) a, greatest(src_part, dst_part) b, count(*) edges from l group by all"))(lambda s, d: metrics.cut_matrix(*_placed(s, d, "cop", "hsh_mixed")))
query("cut_rollup", o.placed("cop", "hsh_mixed", K, "select least(src_part, dst_part) a, greatest(src_part, dst_part) b, count(*) edges, grouping(least(src_part, dst_part), greatest(src_part, dst_part))::int as level from l where src_part <> dst_part group by rollup (least(src_part, dst_part), greatest(src_part, dst_part))"))(lambda s, d: metrics.cut_rollup(*_placed(s, d, "cop", "hsh_mixed")))
query("cut_pivot", o.placed("cop", "hsh_mixed", K, "select least(src_part, dst_part) a, " + ", ".join(f'count(*) filter (greatest(src_part, dst_part) = {p}) "{p}"' for p in range(K)) + " from l group by least(src_part, dst_part)"))(lambda s, d: metrics.cut_pivot(*_placed(s, d, "cop", "hsh_mixed"), K))
query("message_cost", o.placed("cop", "hsh_mixed", K, "select (2 * count(*))::bigint messages, (2 * count(*) filter (src_part = dst_part))::bigint as \"local\", (2 * count(*) filter (src_part <> dst_part))::bigint remote, (select count(*) from (select distinct x.part, dst from sym join a x on x.vid = src join a y on y.vid = dst where x.part <> y.part)) as grouped, (2 * count(*) filter (src_part <> dst_part)) / (2 * count(*)) remote_share from l"))(lambda s, d: metrics.message_cost(*_placed(s, d, "cop", "hsh_mixed")))
query("state_size", o.on_edges("cop", "select (select count(*) from v) vertices, count(*) edges, ((select count(*) from v) * 16 + count(*) * 32)::bigint bytes from edges"))(lambda s, d: metrics.state_size(graph_from(s, d, "cop")))
query("hot_zones")(lambda s, d: apps.hot_zones(*_placed(s, d, "succession", "hsh_mixed")))
query("overhead_fit")(lambda s, d: metrics.overhead_fit(migrate.adapt(*w.started(s, d, "cop", _ONE), _ONE, 12)[1]))
# the tissue runs in both arms
query("break_even_speedup")(lambda s, d: w.arms_summary(s, d, "tissue", 12).where("arm = 'adaptive'").select(F.col("break_even").alias("iteration"), "speedup"))
query("coordination_rows", f"select iteration, (moved + {K})::bigint as rows from ({o.history('lattice', _ONE, 2)})")(lambda s, d: metrics.coordination_rows(w.run_history(s, d, "lattice", _ONE, 2), K))


def _wasted(s: SparkSession, d: str) -> DataFrame:
    run = migrate.Adaptation.start(*w.started(s, d, "lattice", _ONE.but(s=1.0)), _ONE.but(s=1.0))
    trail, before = [], cut(run.state.select("vid", F.col("part").alias("from_part")))
    for t in range(1, 4):
        run.step()
        now = cut(run.state.select("vid", F.col("part").alias("to_part")))  # the run drops its own checkpoints
        trail.append(before.join(now, "vid").where("from_part <> to_part").withColumn("iteration", F.lit(t)))
        before = now.withColumnRenamed("to_part", "from_part")
    run.close()
    return metrics.wasted_moves(w.union(trail))


_S1 = _ONE.but(s=1.0)
_TRAIL = " union all ".join(f"select {t} t, vid, from_part f, to_part p from m{t}" for t in (1, 2, 3))
query("wasted_moves", o.final("lattice", _S1, 3, f"select count(*) filter (b) wasted, count(*) moves from (select coalesce(lag(f) over (partition by vid order by t) = p and lag(p) over (partition by vid order by t) = f, false) b from ({_TRAIL}))"))(_wasted)

# ---------------------------------------------------------------- change

query("weekly_churn", f"with ties as (select distinct date_trunc('week', ts) as week, least(src, dst) a, greatest(src, dst) b from ({o.CALL}) where src <> dst) select x.week::timestamp as week, (select count(*) from ties t where t.week = x.week) ties, (select count(*) from ties t where t.week = x.week and not exists (from ties u where u.week = x.week - interval 7 days and u.a = t.a and u.b = t.b)) added, (select count(*) from ties t where t.week = x.week - interval 7 days and not exists (from ties u where u.week = x.week and u.a = t.a and u.b = t.b)) deleted from (select distinct week from ties) x")(lambda s, d: metrics.weekly_churn(interactions(s, d)))

_OPS = f"""ops as (select event_id seq, case when event_id % 50 = 7 then 'del_vertex' when event_id % 9 = 4 then 'del_edge' else 'add_edge' end op, src, dst, (event_id % 3) * -1 p from ({o.CALL})),
ranked as (select *, row_number() over (order by p, seq) r from ops),
eops as (select op, least(src, dst) a, greatest(src, dst) b, r from ranked where op <> 'del_vertex' and src <> dst union all select 'add_edge', src, dst, 0 from edges),
laste as (select a, b, max(r) r, arg_max(op, r) op from eops group by a, b),
died as (select src vid, max(r) r from ranked where op = 'del_vertex' group by src)"""
query("apply_changes", o.on_edges("succession", "select a src, b dst from laste where op = 'add_edge' and not exists (from died where vid in (a, b) and died.r > laste.r)", _OPS))(w.changed_graph)


def _newcomers(s: SparkSession, d: str) -> DataFrame:
    edges = graph_from(s, d, "cop")
    v = cut(vertices_of(edges))
    return changes.reassign(v.where("vid % 3 = 0").select("vid", F.lit(0).alias("part")), v, K)


query("newcomers_hash", o.on_edges("cop", f"select vid, case when vid % 3 = 0 then 0 else {o.hashed(K)} end::int part from v"))(_newcomers)

# ---------------------------------------------------------------- analyses

query("influence_t5", o.influence(5))(lambda s, d: apps.influence(mentions(s, d)))
query("pagerank_t3", o.pagerank("pagelinks", 3))(lambda s, d: apps.pagerank(symmetric(graph_from(s, d, "pagelinks"))))
query("components", f"with recursive {o.graph('pagelinks')}, reach as (select vid, vid u from v union select reach.vid, dst from reach join sym on src = u) select vid, min(u) component from reach group by vid")(lambda s, d: apps.components(graph_from(s, d, "pagelinks")))
query("max_cliques", o.cliques(o.EDGES["knn"], False))(lambda s, d: apps.max_cliques(graph_from(s, d, "knn")))
query("max_cliques_ordered", o.cliques(o.EDGES["knn"], True))(lambda s, d: apps.max_cliques(graph_from(s, d, "knn"), True))
query("clique_hit_rate")(lambda s, d: apps.clique_hit_rate(graph_from(s, d, "knn")))


def _small(s: SparkSession, d: str) -> DataFrame:
    edges = graph_from(s, d, "pagelinks")
    return cut(edges)


_BFS = "reach as (select vid root, vid, 0 h from v union all select * from (select distinct r.root, sym.dst, r.h + 1 from reach r join sym on sym.src = r.vid where r.h < 14))"
query("diameter_exact", f"with recursive {o.graph('pagelinks')}, {_BFS} select max(h)::int diameter from (select root, vid, min(h) h from reach group by all)")(lambda s, d: apps.diameter_exact(_small(s, d)))
query("diameter_sweep")(lambda s, d: apps.diameter_sweep(_small(s, d)))
query("diameter_sketch")(lambda s, d: apps.diameter_sketch(_small(s, d)))
_CELLS = f"select vid, (o_totalprice::double % 1000) / 1000 excitation, vid % side + (vid // side) % side + vid // (side * side) < 3 inert from (select o_orderkey::bigint vid, o_totalprice, {o.SIDE}::bigint side from orders) where vid < side * side * side"
query("tissue_t3", o.tissue(o.EDGES["lattice"], _CELLS, 3, 6))(lambda s, d: apps.tissue(*w.heart(s, d), steps=3, n_vars=6))


def _labels(s: SparkSession, d: str) -> DataFrame:
    edges = graph_from(s, d, "lattice")
    seeds = vertices_of(edges).select("vid", F.when(F.col("vid") % 10 == 0, (F.col("vid") / 10 % 4).cast("int")).alias("label"))
    return apps.top_per(migrate.label_propagation(symmetric(edges), seeds, 3).withColumn("one", F.lit(1)), "vid", "one", 1).select("vid", "label")


def _labels_sql(steps: int) -> str:
    out = ["x0 as materialized (select vid, case when vid % 10 = 0 then floor(vid / 10 % 4)::int end label, vid % 10 = 0 as fixed from v)"]
    for t in range(1, steps + 1):
        out.append(f"b{t} as (select vid, label from (select sym.src vid, label, row_number() over (partition by sym.src order by count(*) desc, label) r from sym join x{t - 1} y on y.vid = dst where label is not null group by sym.src, label) where r = 1)")
        out.append(f"x{t} as materialized (select x.vid, case when fixed then x.label else coalesce(b.label, x.label) end label, fixed from x{t - 1} x left join b{t} b on b.vid = x.vid)")
    return o.on_edges("lattice", f"select vid, label from x{steps}", ", ".join(out))


query("label_propagation_t3", _labels_sql(3))(_labels)
query("forest_fire_burst")(lambda s, d: generators.forest_fire(cut(graph_from(s, d, "cop")), 50, 0.3, 2))
query("border_growth")(lambda s, d: generators.attach_border(cut(graph_from(s, d, "lattice")), w.heart(s, d)[1].where("inert").select("vid"), 100))
query("powerlaw_graph")(lambda s, d: generators.powerlaw_clustered(s, table(s, d, "customer", "c_custkey").count(), 5, vertices=table(s, d, "customer", F.col("c_custkey").cast("long").alias("vid"))))
#: Cells numbered by the order keys, in whole layers of 10 by 10.
_CUBOID = "select o_orderkey::bigint src, (o_orderkey + dd)::bigint dst from orders, (select count(*) // 100 c from orders), (values (0, 1), (1, 10), (2, 100)) t(x, dd) where o_orderkey < 100 * c and case x when 0 then o_orderkey % 10 < 9 when 1 then o_orderkey // 10 % 10 < 9 else o_orderkey // 100 < c - 1 end"


def _cuboid(s: SparkSession, d: str) -> DataFrame:
    orders = table(s, d, "orders", F.col("o_orderkey").cast("long").alias("vid"))
    return generators.lattice3d(s, 10, 10, orders.count() // 100, orders)


query("lattice3d_graph", _CUBOID)(_cuboid)
query("vertex_program_degree", o.on_edges("pagelinks", "select src vid, count(*) as value from sym group by src"))(
    lambda s, d: engine.run_program(_small(s, d), initial.assign_hash(vertices_of(_small(s, d)), 4), engine.degree_program(), MigrationConfig(k=4, adaptive=False), 1)[0].select("vid", "value")
)
query("vertex_program_min_t3", o.on_edges("pagelinks", "select vid, least(v.vid, min(least(a.vid0, a.m))) as value from v join (select s1.src vid1, s1.dst vid0, min(least(s2.dst, s3.dst)) m from sym s1 join sym s2 on s2.src = s1.dst join sym s3 on s3.src = s2.dst group by all) a on a.vid1 = vid group by vid"))(
    lambda s, d: engine.run_program(_small(s, d), initial.assign_hash(vertices_of(_small(s, d)), 4), engine.min_label_program(), MigrationConfig(k=4, deferred=True), 3)[0].select("vid", "value")
)

# ---------------------------------------------------------------- workloads

_SLICE = f"(select least(src, dst) a, greatest(src, dst) b, min(date_diff('day', date '2024-01-01', ts::date) // 10) d from ({o.CALL}) where src <> dst group by 1, 2)"
query("w1_drift_hsh", f"with t as materialized {_SLICE} select d::int slice, (select count(*) from t where t.d <= x.d and {o.hashed(K, 0, 'a')} <> {o.hashed(K, 0, 'b')}) cut, (select count(*) from t where t.d <= x.d) edges from (select range d from range((select max(d) + 1 from t))) x")(lambda s, d: w.drift(s, d, "hsh"))
query("w1_daily_hsh", f"with t as materialized (select least(src, dst) a, greatest(src, dst) b, min(date_diff('day', date '2024-01-01', ts::date)) d from ({o.CALL}) where src <> dst group by 1, 2) select d::int slice, (select count(*) from t where t.d <= x.d and {o.hashed(K, 0, 'a')} <> {o.hashed(K, 0, 'b')}) cut, (select count(*) from t where t.d <= x.d) edges from (select range d from range((select max(d) + 1 from t))) x")(lambda s, d: w.drift(s, d, "hsh", days=1))
for _strategy in ("dtg", "adp", "scratch"):
    query(f"w1_daily_{_strategy}")(lambda s, d, x=_strategy: w.drift(s, d, x, days=1))
query("w1_drift_dtg")(lambda s, d: w.drift(s, d, "dtg"))
query("w1_drift_adp")(lambda s, d: w.drift(s, d, "adp"))
query("w1_drift_scratch")(lambda s, d: w.drift(s, d, "scratch"))
query("w2_s_sweep_t3", " union all ".join(f"select {round(100 * s)}::int s_percent, 0::int seed, * from ({o.history('lattice', MigrationConfig(s=s), 3)})" for s in (0.1, 0.5, 1.0)))(lambda s, d: w.s_sweep(s, d, "lattice", (0.1, 0.5, 1.0), 3, (0,)))
query("w2_s_sweep_powerlaw_t2", " union all ".join(f"select {round(100 * s)}::int s_percent, 0::int seed, * from ({o.history('copurchase', MigrationConfig(s=s), 2)})" for s in (0.5, 1.0)))(lambda s, d: w.s_sweep(s, d, "copurchase", (0.5, 1.0), 2, (0,)))
query("w2_s_sweep")(lambda s, d: w.s_sweep(s, d))
query("w2_s_sweep_powerlaw")(lambda s, d: w.s_sweep(s, d, "copurchase"))
query("w2_s_sweep_spread")(lambda s, d: w.sweep_spread(w.s_sweep(s, d)))
query("w2_s_sweep_powerlaw_spread")(lambda s, d: w.sweep_spread(w.s_sweep(s, d, "copurchase")))
_W3 = list(GRAPHS)  # the six surveyed graphs, and succession


def _quality_sql(graphs: list[str], kinds: list[str], steps: int) -> str:
    return " union all ".join(f"select * from ({o.final(g, _ONE, steps, f'''select '{g}' as graph, '{k}' as start, {o.cut_of('a0')} before, {o.cut_of(f'a{steps}')} after, (select count(*) from edges) edges''', k)})" for g in graphs for k in kinds)


query("w3_initial_quality_t3", _quality_sql(["lattice", "cop", "succession"], ["hsh_mixed", "rnd"], 3))(lambda s, d: w.initial_quality(s, d, ["lattice", "cop", "succession"], ["hsh_mixed", "rnd"], 3, seeds=(0,)))
query("w3_initial_quality")(lambda s, d: w.initial_quality(s, d, _W3, ["hsh_mixed", "rnd"], None))
query("w3_initial_quality_stream")(lambda s, d: w.initial_quality(s, d, _W3, ["dgr", "mnn", "mnn_literal"], None))
query("w4_convergence_t4", o.history("cop", _ONE, 4))(lambda s, d: w.run_history(s, d, "cop", _ONE, 4))
query("w4_convergence")(lambda s, d: w.run_history(s, d, "cop", _ONE, None))
query("w5_bursts_adaptive")(lambda s, d: w.bursts(s, d))
query("w5_bursts_static")(lambda s, d: w.bursts(s, d, adaptive=False))
_MENTION_EDGES = f"select distinct least(src, dst) src, greatest(src, dst) dst from ({o.CALL}) where src <> dst"
_MENTION_ROW = "select '{}' as arm, {} cut, (select count(*) from edges) edges, {} / (select count(*) from edges) ratio"
query("w6_mentions_t3", f"with {o.begin('', _ONE, edges=_MENTION_EDGES)}, {o.migrations(_ONE, 3)} " + " union all ".join(_MENTION_ROW.format(arm, o.cut_of(a), o.cut_of(a)) for arm, a in (("adaptive", "a3"), ("static", "a0"))))(lambda s, d: w.mention_cuts(s, d, 3))
query("w6_mentions")(lambda s, d: w.mention_cuts(s, d, None))
query("w6_influence", f"select vid, influence from ({o.influence(5)}) order by influence desc, vid limit 20")(lambda s, d: apps.top(apps.influence(mentions(s, d)), "influence", 20))
query("w6_throughput", f"select time_bucket(interval 10 minutes, ts) as start, count(*) as events from ({o.CALL}) group by 1")(lambda s, d: metrics.throughput(interactions(s, d)))
query("w7_window_edges", f"select (date_trunc('week', ts) + interval 7 days)::timestamp week_end, least(src, dst) src, greatest(src, dst) dst, max(ts) last_seen from (select ts, src, dst from ({o.CALL}) where src <> dst) group by 1, 2, 3")(w.window_edges)
query("w7_cuts_weekly_static", f"with t as (select distinct date_trunc('week', ts) as week, least(src, dst) a, greatest(src, dst) b from ({o.CALL}) where src <> dst) select (dense_rank() over (order by week) - 1)::int as week, count(*) filter ({o.hashed(K, 0, 'a')} <> {o.hashed(K, 0, 'b')}) cut, count(*) edges from t group by week")(lambda s, d: w.weekly_cuts(s, d, False))
query("w7_cuts_weekly_adaptive")(lambda s, d: w.weekly_cuts(s, d, True))
query("w7_cliques_second_week", o.cliques(f"select distinct least(src, dst) src, greatest(src, dst) dst from ({o.CALL}) where src <> dst and date_trunc('week', ts) = timestamp '2024-01-08'", True))(lambda s, d: apps.max_cliques(w.last_week(s, d), True))
query("w7_cliques")(w.weekly_cliques)
query("w8_tissue", o.tissue(o.EDGES["lattice"], _CELLS, 2, 10))(lambda s, d: apps.tissue(*w.heart(s, d), steps=2, n_vars=10))
query("w8_expand_adaptive")(lambda s, d: w.expanded_heart(s, d, True))
query("w8_expand_static")(lambda s, d: w.expanded_heart(s, d, False))
query("w9_ablation_t2", " union all ".join(f"select '{n}' as variant, * from ({o.history('lattice', c, 2)})" for n, c in w.ABLATIONS.items()))(lambda s, d: w.ablation(s, d, "lattice", w.ABLATIONS, 2))
query("w9_ablation")(lambda s, d: w.ablation(s, d, "lattice", w.ABLATIONS))
query("w10_scale_t2", " union all ".join(f"select 'k{k}' as variant, * from ({o.history('lattice', MigrationConfig(k=k), 2)})" for k in (2, 4, 16)))(lambda s, d: w.ablation(s, d, "lattice", {f"k{k}": MigrationConfig(k=k) for k in (2, 4, 16)}, 2))
query("w10_scale")(lambda s, d: w.ablation(s, d, "lattice", {f"k{k}": MigrationConfig(k=k) for k in (2, 4, 9, 16, 64)}))


def _slice(s: SparkSession, d: str, steps: int | None = None) -> DataFrame:
    state = w.run_state(s, d, "lattice", _ONE, steps)
    side = w.cube_side(table(s, d, "orders", "o_orderkey").count())
    return metrics.same_part_slice(state, side, side // 2)


query("w11_slice_t3", o.final("lattice", _ONE, 3, f"select (vid % side)::int x, ((vid // side) % side)::int y, part from a3, (select {o.SIDE}::bigint side) where vid // (side * side) = side // 2"))(lambda s, d: _slice(s, d, 3))
query("w11_slice")(_slice)


def _slices(s: SparkSession, d: str, share: bool) -> DataFrame:
    side = w.cube_side(table(s, d, "orders", "o_orderkey").count())
    return w.slices(s, d, _ONE, side, side // 2, 3, share)


def _slices_sql(share: bool) -> str:
    plane = lambda t: f"(select (vid % side)::int x, ((vid // side) % side)::int y, part from a{t}, (select {o.SIDE}::bigint side) where vid // (side * side) = side // 2)"
    one = lambda t: f"select {t}::int iteration, x, y, part from {plane(t)}"
    if share:
        one = lambda t: f"select {t}::int iteration, count(*) filter (p.part = q.part) / count(*) share from {plane(t)} p join {plane(t)} q on (q.x = p.x + 1 and q.y = p.y) or (q.x = p.x and q.y = p.y + 1)"
    return o.final("lattice", _ONE, 3, " union all ".join(one(t) for t in range(4)))


query("w11_slices_t3", _slices_sql(False))(lambda s, d: _slices(s, d, False))
query("w11_same_part_t3", _slices_sql(True))(lambda s, d: _slices(s, d, True))
query("w12_newcomers")(lambda s, d: w.newcomers(s, d))


def _log_sql(begun: str, cfg: MigrationConfig, steps: int, adaptive: bool, arcs: str = "sym", label: str = "") -> str:
    """Counts of an engine's supersteps: places after each iteration, messages along ``arcs``. Deferred moves count by physical place."""
    rows, homes = [], []
    for t in range(1, steps + 1):
        at = f"a{t}" if adaptive else "a0"
        if adaptive and cfg.deferred:
            homes.append(f"ho{t} as materialized (select a.vid, case when a.settle = {t + 1} then b.part else a.part end part from a{t} a join {f"ho{t - 1}" if t > 1 else "a0"} b on a.vid = b.vid)")
            at = f"ho{t}"
        moved = f"(select count(*) from m{t})" if adaptive else "0::bigint"
        place = f"{arcs} join {at} x on x.vid = src join {at} y on y.vid = dst"
        rows.append(f"select {label}{t}::int superstep, {moved} moved, (select count(*) from {arcs}) messages, (select count(*) from {place} where x.part <> y.part) remote, (select count(*) from (select distinct x.part, dst from {place})) as grouped, (select count(*) from (select distinct x.part, dst from {place} where x.part <> y.part)) remote_grouped")
    more = f", {o.migrations(cfg, steps)}" if adaptive else ""
    return f"with {begun}{more}{''.join(', ' + h for h in homes)} " + " union all ".join(rows)


for _n, _on in (("adaptive", True), ("static", False)):
    query(f"superstep_{_n}", _log_sql(_BEGUN, _LATE, 3, _on))(lambda s, d, a=_on: w.superstep_log(s, d, a))
_CASES = {
    "w5_burst_arms": ("bursts", o.begin("cop", _ONE), "sym"),
    "w6_mention_arms": ("mentions", f"{o.begin('', _ONE, edges=_MENTION_EDGES)}, arcs as materialized (select distinct src, dst from ({o.CALL}) where src <> dst)", "arcs"),
    "w8_tissue_arms": ("tissue", _BEGUN, "sym"),
}
for _n, (_case, _begun, _arcs) in _CASES.items():
    _both = " union all ".join(f"select * from ({_log_sql(_begun, _ONE, 3, on, _arcs, chr(39) + arm + chr(39) + ' as arm, ')})" for arm, on in (("adaptive", True), ("static", False)))
    query(_n, _both)(lambda s, d, c=_case: w.arms(s, d, c))
    query(f"{_n}_timed")(lambda s, d, c=_case: w.arms_summary(s, d, c))
query("w6_recovery", o.influence(4).replace("round(i / 1000000000, 6) influence", "i as value"))(lambda s, d: w.recovered(s, d).select("vid", "value"))
query("w7_clique_weeks_adaptive")(lambda s, d: w.clique_weeks(s, d, True))
query("w7_clique_weeks_static")(lambda s, d: w.clique_weeks(s, d, False))

# ---------------------------------------------------------------- streams


def _stream(s: SparkSession, d: str, make: Callable[[DataFrame], DataFrame], mode: str = "append", keys: list[str] | None = None) -> DataFrame:
    folder, users, at = w.stream_folder(s, d)
    return front.drain_to(make(front.event_stream(s, folder, users)), at, mode, keys)


query("stream_throughput", f"select time_bucket(interval 10 minutes, ts) as start, count(*) as events from ({o.CALL}) group by 1")(lambda s, d: _stream(s, d, front.throughput_stream, "update", ["start"]))
query("stream_calls_window", f"select (date_trunc('day', ts) - to_days(b::int))::timestamp as start, least(src, dst) src, greatest(src, dst) dst, count(*) calls from ({o.CALL}), (select unnest(range(7)) b) where src <> dst group by 1, 2, 3")(lambda s, d: _stream(s, d, front.active_ties, "update", ["start", "src", "dst"]))
query("stream_user_bursts", f"with e as (select *, coalesce(ts - lag(ts) over (partition by src order by ts) > interval 30 minutes, true) fresh from ({o.CALL})), g as (select *, sum(fresh::int) over (partition by src order by ts rows unbounded preceding) n from e) select min(ts)::timestamp as start, src, count(*) as events from g group by src, n")(lambda s, d: _stream(s, d, front.user_bursts, "complete"))


def _stream_changes(s: SparkSession, d: str) -> DataFrame:
    """Ties of the stream, batch by batch through the change queue."""
    folder, users, at = w.stream_folder(s, d)
    queue, graph = changes.ChangeQueue(s), [s.createDataFrame([], "src long, dst long"), s.createDataFrame([], "vid long")]

    def take(batch: DataFrame, number: int) -> None:
        queue.push(batch.select(F.col("event_id").alias("seq"), F.lit("add_edge").alias("op"), "src", "dst", F.lit(0).alias("priority"), "ts"))
        edges, vertices, _ = queue.drain(number, *graph)
        graph[:] = [cut(edges), cut(vertices)]

    front.for_each_batch(front.event_stream(s, folder, users), f"{at}/state", take)
    return graph[0]


query("stream_changes", f"select distinct least(src, dst) src, greatest(src, dst) dst from ({o.CALL}) where src <> dst")(_stream_changes)
query("stream_dedup", f"select event_id, ts, src, dst from ({o.CALL})")(lambda s, d: _stream(s, d, front.deduplicated))
query("stream_reciprocated", f"with c as (select * from ({o.CALL}) where src <> dst) select a.ts ts1, a.src s1, a.dst d1, b.ts ts2 from c a join c b on a.src = b.dst and a.dst = b.src and b.ts > a.ts and b.ts <= a.ts + interval 1 day")(lambda s, d: _stream(s, d, front.reciprocated))
query("stream_expiry", f"with c as (select least(src, dst) a, greatest(src, dst) b, ts from ({o.CALL}) where src <> dst), g as (select *, lag(ts) over (partition by a, b order by ts) p from c) select 'add_edge' op, a src, b dst, ts from g where p is null or ts - p > interval 7 days union all select 'del_edge', a, b, p + interval 7 days from g where ts - p > interval 7 days union all select 'del_edge', a, b, m + interval 7 days from (select a, b, max(ts) m from c group by a, b) where m + interval 7 days < (select date_trunc('millisecond', max(ts)) - interval 1 day from c)")(lambda s, d: _stream(s, d, front.expiring_ties))

# ---------------------------------------------------------------- relational helpers

_L = "lineitem"


def _tab(name: str, sql: str):
    """An operator over the tables, told in Spark SQL with views of the tables it names."""

    def add(f):
        return query(f"op_{name}", sql)(f)

    return add


_tab("broadcast_join", "select r_name, count(*) n from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by r_name")(
    lambda s, d: table(s, d, "customer", "c_nationkey").join(F.broadcast(table(s, d, "nation", "n_nationkey", "n_regionkey")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(table(s, d, "region", "r_regionkey", "r_name")), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.count(F.lit(1)).alias("n"))
)
_tab("shuffle_hash_join", "select o_custkey, count(*) lines from orders join lineitem on o_orderkey = l_orderkey group by o_custkey")(
    lambda s, d: table(s, d, "orders", "o_orderkey", "o_custkey").hint("shuffle_hash").join(table(s, d, _L, "l_orderkey"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_custkey").agg(F.count(F.lit(1)).alias("lines"))
)
_tab("merge_join", "select l_orderkey, count(*) n from orders join lineitem on o_orderkey = l_orderkey group by l_orderkey")(
    lambda s, d: table(s, d, "orders", "o_orderkey").hint("merge").join(table(s, d, _L, "l_orderkey"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("n"))
)


def _bucketed_join(s: SparkSession, d: str) -> DataFrame:
    """Both sides written bucketed by the key, so that the join moves neither."""
    names = []
    for name, column in (("orders", "o_orderkey"), (_L, "l_orderkey")):
        names.append(f"graphdrift_{name}_{uuid.uuid4().hex}")
        at = f"{checkpoint_dir(s)}/{names[-1]}"
        table(s, d, name, column).write.bucketBy(8, column).option("path", at).saveAsTable(names[-1])
    left, right = (s.table(n) for n in names)
    return left.hint("merge").join(right, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("n"))


_tab("bucketed_join", "select l_orderkey, count(*) n from orders join lineitem on o_orderkey = l_orderkey group by l_orderkey")(_bucketed_join)


def _cells_source(s: SparkSession, d: str) -> DataFrame:
    """The cuboid of the orders from the data source: its edges that begin at an order's key."""
    from graphdrift.sources.cells import CellSource

    s.dataSource.register(CellSource)
    orders = table(s, d, "orders", "o_orderkey")
    edges = s.read.format("cells").option("a", 10).option("b", 10).option("c", orders.count() // 100).load()
    return edges.join(orders, edges.src == orders.o_orderkey, "left_semi")


_tab("data_source", _CUBOID)(_cells_source)


def _recursion(s: SparkSession, d: str) -> DataFrame:
    """Doubling from the orders of ten groups of customers."""
    table(s, d, "orders", "o_custkey").createOrReplaceTempView("gd_orders")
    return s.sql("with recursive t(k, n, f) as (select o_custkey % 10, 1, count(*) from gd_orders group by 1 union all select k, n + 1, f * 2 from t where n < 40) select k, n, f from t")


_tab("recursion", "with recursive t(k, n, f) as (select o_custkey % 10, 1, count(*) from orders group by 1 union all select k, n + 1, f * 2 from t where n < 40) select k, n, f from t")(_recursion)
_tab("left_join", "select c_custkey, count(o_orderkey) orders from customer left join orders on c_custkey = o_custkey group by c_custkey")(
    lambda s, d: table(s, d, "customer", "c_custkey").join(table(s, d, "orders", "o_orderkey", "o_custkey"), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("orders"))
)
_tab("full_join", "select coalesce(a.k, b.k) k, a.n a, b.n b from (select user_id k, count(*) n from events where event_id % 2 = 0 group by 1) a full join (select user_id k, count(*) n from events where event_id % 3 = 0 group by 1) b on a.k = b.k")(
    lambda s, d: (lambda e: e.where("event_id % 2 = 0").groupBy(F.col("user_id").alias("k")).agg(F.count(F.lit(1)).alias("a")).join(e.where("event_id % 3 = 0").groupBy(F.col("user_id").alias("k")).agg(F.count(F.lit(1)).alias("b")), "k", "full"))(table(s, d, "events", "event_id", "user_id"))
)
_tab("semi_join", "select s_suppkey from supplier where s_suppkey in (select l_suppkey from lineitem where l_orderkey % 7 = 0)")(lambda s, d: table(s, d, "supplier", "s_suppkey").join(table(s, d, _L, "l_suppkey", "l_orderkey").where("l_orderkey % 7 = 0"), F.col("s_suppkey") == F.col("l_suppkey"), "left_semi"))
_tab("anti_join", "select o_orderkey from orders where o_orderkey not in (select l_orderkey from lineitem)")(lambda s, d: table(s, d, "orders", "o_orderkey").join(table(s, d, _L, "l_orderkey"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti"))
_tab("theta_join", "select a.r_regionkey a, b.r_regionkey b from region a join region b on a.r_regionkey < b.r_regionkey")(
    lambda s, d: table(s, d, "region", "r_regionkey").select(F.col("r_regionkey").alias("a")).crossJoin(table(s, d, "region", "r_regionkey").select(F.col("r_regionkey").alias("b"))).where("a < b")
)


def _range_join(s: SparkSession, d: str, ranges: int | None = None) -> DataFrame:
    """Values into ranges [64 i, 64 i + 63): both sides meet on the bucket, not on all pairs. Ranges reach the largest key."""
    points = table(s, d, "orders", "o_orderkey").select("o_orderkey", F.expr("o_orderkey div 64").alias("b"))
    if ranges is None:
        ranges = -(-next_key(points, "o_orderkey") // 64)
    spans = s.range(ranges).select(F.col("id").alias("b"), (F.col("id") * 64).alias("lo"), (F.col("id") * 64 + 62).alias("hi"))
    return points.join(spans, "b").where("o_orderkey between lo and hi").groupBy("lo").agg(F.count(F.lit(1)).alias("n"))


_tab("range_join_100", "select lo, count(*) n from orders join (select range * 64 lo, range * 64 + 62 hi from range(100)) on o_orderkey between lo and hi group by lo")(lambda s, d: _range_join(s, d, 100))
query("op_range_join")(_range_join)


def _as_of(s: SparkSession, d: str) -> DataFrame:
    """Each event with the user's latest earlier purchase, by a union and a running maximum."""
    e = table(s, d, "events", "event_id", "ts", "user_id", "event_type")
    marked = e.withColumn("p", F.when(F.col("event_type") == "purchase", F.col("event_id")))
    before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return marked.select("event_id", F.max(F.when(F.col("p").isNotNull(), F.struct("ts", "p"))).over(before).getField("p").alias("last_purchase"))


_tab("as_of_join", "select e.event_id, (select arg_max(p.event_id, (p.ts, p.event_id)) from events p where p.user_id = e.user_id and p.event_type = 'purchase' and (p.ts, p.event_id) < (e.ts, e.event_id)) last_purchase from events e")(_as_of)
_tab("filtered_agg", "select event_type, count(*) n, count(*) filter (user_id % 2 = 0) even, count(distinct user_id) users from events group by event_type")(lambda s, d: table(s, d, "events", "event_type", "user_id").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("user_id") % 2 == 0).alias("even"), F.count_distinct("user_id").alias("users")))
_tab("max_by", "select user_id, arg_max(event_id, (ts, event_id)) last from events group by user_id")(lambda s, d: table(s, d, "events", "event_id", "ts", "user_id").groupBy("user_id").agg(F.max_by("event_id", F.struct("ts", "event_id")).alias("last")))
_tab("cube", "select c_mktsegment, c_nationkey, count(*) n, grouping(c_mktsegment, c_nationkey)::int as level from customer group by cube (c_mktsegment, c_nationkey)")(lambda s, d: table(s, d, "customer", "c_mktsegment", "c_nationkey").cube("c_mktsegment", "c_nationkey").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("int").alias("level")))


def _grouping_sets(s: SparkSession, d: str) -> DataFrame:
    table(s, d, "events", "event_type", "user_id").createOrReplaceTempView("gd_events")
    return s.sql("select event_type, user_id % 3 as r, count(*) as n from gd_events group by grouping sets ((event_type), (user_id % 3), ())")


_tab("grouping_sets", "select event_type, user_id % 3 as r, count(*) n from events group by grouping sets ((event_type), (user_id % 3), ())")(_grouping_sets)
_tab("pivot", "select user_id, count(*) filter (event_type = 'click') click, count(*) filter (event_type = 'view') as view from events where event_type in ('click', 'view') group by user_id")(lambda s, d: table(s, d, "events", "event_type", "user_id").where(F.col("event_type").isin("click", "view")).groupBy("user_id").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1))).na.fill(0))
_RANKED = "event_id, row_number() over w::int rn, rank() over w::int rk, dense_rank() over w::int dr, ntile(4) over w::int nt, round(percent_rank() over w, 9) pr, round(cume_dist() over w, 9) cd"
_tab("window_ranks", f"select {_RANKED} from events window w as (partition by user_id order by event_id % 10, event_id)".replace(" over w::int", " over w"))(
    lambda s, d: (lambda win: table(s, d, "events", "event_id", "user_id").select("event_id", F.row_number().over(win).alias("rn"), F.rank().over(win).alias("rk"), F.dense_rank().over(win).alias("dr"), F.ntile(4).over(win).alias("nt"), F.round(F.percent_rank().over(win), 9).alias("pr"), F.round(F.cume_dist().over(win), 9).alias("cd")))(Window.partitionBy("user_id").orderBy(F.col("event_id") % 10, "event_id"))
)
_tab("window_analytic", "select event_id, lag(event_id) over w a, lead(event_id) over w b, first_value(event_id) over w c, nth_value(event_id, 2) over w e from events window w as (partition by user_id order by ts, event_id)")(
    lambda s, d: (lambda win: table(s, d, "events", "event_id", "ts", "user_id").select("event_id", F.lag("event_id").over(win).alias("a"), F.lead("event_id").over(win).alias("b"), F.first("event_id").over(win).alias("c"), F.nth_value("event_id", 2).over(win).alias("e")))(Window.partitionBy("user_id").orderBy("ts", "event_id"))
)
_tab("window_frames", "select event_id, count(*) over (partition by user_id order by ts, event_id rows between 29 preceding and current row) r, count(*) over (partition by user_id order by ts range between interval 7 days preceding and current row) w from events")(
    lambda s, d: table(s, d, "events", "event_id", "ts", "user_id").select("event_id", F.expr("count(1) over (partition by user_id order by ts, event_id rows between 29 preceding and current row)").alias("r"), F.expr("count(1) over (partition by user_id order by ts range between interval 7 days preceding and current row)").alias("w"))
)
_tab("top_k", "select o_orderkey vid, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 10")(lambda s, d: apps.top(table(s, d, "orders", "o_orderkey", "o_totalprice").withColumnRenamed("o_orderkey", "vid"), "o_totalprice", 10))
_tab("top_k_per_group", "select vid, o_custkey, rn from (select o_orderkey vid, o_custkey, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) rn from orders) where rn <= 2")(lambda s, d: apps.top_per(table(s, d, "orders", "o_orderkey", "o_custkey", "o_totalprice").withColumnRenamed("o_orderkey", "vid"), "o_custkey", "o_totalprice", 2).select("vid", "o_custkey", "rn"))
_EVEN, _THIRD = "select user_id from events where event_id % 2 = 0", "select user_id from events where event_id % 3 = 0"
for _n, _op, _f in (("union", "union", lambda a, b: a.unionByName(b).distinct()), ("union_all", "union all", lambda a, b: a.unionByName(b)), ("intersect", "intersect", lambda a, b: a.intersect(b)), ("intersect_all", "intersect all", lambda a, b: a.intersectAll(b)), ("except_all", "except all", lambda a, b: a.exceptAll(b))):
    _tab(_n, f"{_EVEN} {_op} {_THIRD}")(lambda s, d, f=_f: f(table(s, d, "events", "event_id", "user_id").where("event_id % 2 = 0").select("user_id"), table(s, d, "events", "event_id", "user_id").where("event_id % 3 = 0").select("user_id")))
_tab("scalar_math", "select o_orderkey, (o_orderkey % 7)::bigint m, o_orderkey // 7 q, floor(o_totalprice)::bigint f, ceil(o_totalprice)::bigint c, (o_orderkey >> 3) s, (o_orderkey & 255) a, xor(o_orderkey, 21) x from orders")(
    lambda s, d: table(s, d, "orders", "o_orderkey", "o_totalprice").select("o_orderkey", F.pmod("o_orderkey", F.lit(7)).cast("long").alias("m"), F.expr("o_orderkey div 7").alias("q"), F.floor("o_totalprice").cast("long").alias("f"), F.ceil("o_totalprice").cast("long").alias("c"), F.shiftright("o_orderkey", 3).alias("s"), F.col("o_orderkey").bitwiseAND(F.lit(255)).alias("a"), F.col("o_orderkey").bitwiseXOR(F.lit(21)).alias("x"))
)
_tab("json", "select event_id, json_extract_string(props, '$.k')::bigint k from events")(lambda s, d: table(s, d, "events", "event_id", "props").select("event_id", F.from_json("props", "k long").getField("k").alias("k")))
_tab("strings", "select c_custkey, upper(c_mktsegment) u, length(c_name) n, split_part(c_name, '#', 2) p, sha256(c_name) h, concat_ws('-', c_name, c_mktsegment) j from customer")(lambda s, d: table(s, d, "customer", "c_custkey", "c_name", "c_mktsegment").select("c_custkey", F.upper("c_mktsegment").alias("u"), F.length("c_name").cast("long").alias("n"), F.split_part("c_name", F.lit("#"), F.lit(2)).alias("p"), F.sha2("c_name", 256).alias("h"), F.concat_ws("-", "c_name", "c_mktsegment").alias("j")))
_tab("dates", "select event_id, date_trunc('week', ts)::timestamp as week, time_bucket(interval 10 minutes, ts) as bucket, epoch_us(ts) as us, date_diff('day', timestamp '2024-01-01', ts) as n_days from events")(lambda s, d: table(s, d, "events", "event_id", "ts").withColumn("ts", F.col("ts").cast("timestamp")).select("event_id", F.date_trunc("week", "ts").alias("week"), F.window("ts", "10 minutes").getField("start").alias("bucket"), F.unix_micros("ts").alias("us"), F.datediff("ts", F.lit("2024-01-01").cast("date")).cast("long").alias("n_days")))
_tab("arrays", "select l_orderkey, array_to_string(list_sort(list(l_partkey)), ',') parts, sum(l_partkey)::bigint total, count(*) filter (l_partkey % 2 = 0) even from lineitem group by l_orderkey")(
    lambda s, d: table(s, d, _L, "l_orderkey", "l_partkey").groupBy("l_orderkey").agg(F.array_sort(F.collect_list("l_partkey")).alias("a")).select("l_orderkey", F.concat_ws(",", F.col("a").cast("array<string>")).alias("parts"), F.aggregate("a", F.lit(0).cast("long"), lambda x, y: x + y).alias("total"), F.size(F.filter("a", lambda x: x % 2 == 0)).cast("long").alias("even"))
)
_tab("maps", "select user_id, event_type k, count(*) v from events group by all")(lambda s, d: table(s, d, "events", "user_id", "event_type").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m")).select("user_id", F.explode("m").alias("k", "v")))
_tab("explode", "select vec_id, generate_subscripts(embedding, 1) - 1 as pos, unnest(embedding) x from embeddings")(lambda s, d: table(s, d, "embeddings", "vec_id", "embedding").select("vec_id", F.posexplode("embedding").alias("pos", "x")).withColumn("pos", F.col("pos").cast("long")))
query("op_approx_distinct")(lambda s, d: table(s, d, "events", "user_id", "event_type").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"), F.percentile_approx("user_id", 0.5).alias("mid")))


def _session_sql(s: SparkSession, d: str) -> DataFrame:
    from graphdrift.plans.sql import register_graph

    edges, a = _placed(s, d, "custsupp", "hsh_mixed")
    register_graph(s, "g", edges, a)
    return s.sql("select hash_part(e.src, 9) as part, count(*) as n from g_edges e group by 1")


query("op_sql_surface", o.on_edges("custsupp", f"select {o.hashed(K, 0, 'src')} part, count(*) n from edges group by 1"))(_session_sql)


def _udtf(s: SparkSession, d: str) -> DataFrame:
    """The neighbours of every cell of the cube that the customers' keys number."""
    from graphdrift.plans.sql import cell_neighbours

    s.udtf.register("cell_neighbours", cell_neighbours())
    customers = table(s, d, "customer", F.col("c_custkey").cast("long").alias("id"))
    side = w.cube_side(customers.count())
    customers.createOrReplaceTempView("gd_customers")
    return s.sql(f"select c.id as vid, n.nbr from gd_customers c, lateral cell_neighbours(c.id, {side}, {side}, {side}) n where c.id < {side**3}")


_CUSTOMER_SIDE = o.SIDE.replace("orders", "customer")
query("op_udtf", f"select vid, vid + d * p nbr from (select c_custkey::bigint vid, side, unnest([1::bigint, side, side * side]) p from (select c_custkey, {_CUSTOMER_SIDE}::bigint side from customer)), (values (-1), (1)) t(d) where vid < side * side * side and vid // p % side + d between 0 and side - 1")(_udtf)
