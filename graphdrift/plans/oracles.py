"""DuckDB SQL for the queries, written apart from the Spark code: windows and ranks where
the engine uses struct aggregates, one CTE an iteration."""

from __future__ import annotations

from graphdrift.config import MigrationConfig
from graphdrift.functions.hashing import ADMIT, COIN, PLACE, TIE, mix32_sql, salt_sql, threshold

N_C = "(select max(c_custkey) + 1 from customer)"
N_O = "(select max(o_orderkey) + 1 from orders)"
USERS = "(select count(distinct user_id) from events)"
SIDE = "(select max(i) from range(1, 5000) t(i) where i * i * i <= (select count(*) from orders))"
CALL = f"select event_id, ts::timestamp ts, user_id::bigint src, (json_extract_string(props, '$.k')::bigint % {USERS})::bigint dst from events"

EDGES = {
    "lattice": f"""select vid src, vid + d dst from (select o_orderkey::bigint vid, {SIDE}::bigint side from orders),
  (values (0), (1), (2)) ax(a), lateral (select case a when 0 then 1 when 1 then side else side * side end d)
  where vid < side * side * side and (vid // d) % side < side - 1""",
    "custsupp": f"select distinct o_custkey::bigint src, (l_suppkey + {N_C})::bigint dst from orders join lineitem on o_orderkey = l_orderkey",
    "cop": f"""select distinct o_custkey::bigint src, (o_orderkey + {N_C})::bigint dst from orders
  union all select distinct (l_orderkey + {N_C})::bigint, (l_partkey + {N_C} + {N_O})::bigint from lineitem""",
    "copurchase": "select distinct a.l_partkey::bigint src, b.l_partkey::bigint dst from lineitem a join lineitem b on a.l_orderkey = b.l_orderkey and a.l_partkey < b.l_partkey",
    "pagelinks": """select page_id::bigint src, (dense_rank() over (order by target) - 1 + (select max(page_id) + 1 from pages))::bigint dst
  from (select distinct page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) target from pages)""",
    "succession": "select distinct least(u, w)::bigint src, greatest(u, w)::bigint dst from (select user_id u, lead(user_id) over (order by ts, event_id) w from events) where w is not null and u <> w",
    "knn": """select distinct least(q, c)::bigint src, greatest(q, c)::bigint dst from (
  select a.vec_id q, b.vec_id c, row_number() over (partition by a.vec_id order by list_cosine_similarity(a.embedding::double[], b.embedding::double[]) desc, b.vec_id) r
  from embeddings a join embeddings b on a.vec_id <> b.vec_id) where r <= 8""",
}


def graph(name: str, edges: str | None = None) -> str:
    """CTEs edges, sym, v of a graph."""
    return f"edges as materialized ({edges or EDGES[name]}), sym as materialized (select src, dst from edges union all select dst, src from edges), v as materialized (select distinct src vid from sym)"


def hashed(k: int, seed: int = 0, vid: str = "vid") -> str:
    return f"({mix32_sql(vid, salt_sql(seed, PLACE))} % {k})::int"


def assignment(kind: str, k: int, seed: int = 0) -> str:
    """select vid, part of an initial placement over v."""
    if kind == "hsh":
        return f"select vid, (vid % {k})::int part from v"
    if kind == "hsh_mixed":
        return f"select vid, {hashed(k, seed)} part from v"
    return f"select vid, ((row_number() over (order by {mix32_sql('vid', salt_sql(seed, PLACE))}, vid) - 1) % {k})::int part from v"


def histogram(a: str, count_self: bool = False) -> str:
    own = f" union all select vid, part from {a}" if count_self else ""
    return f"select vid, part p, count(*) cnt from (select src vid, part from sym join {a} on dst = {a}.vid{own}) group by all"


def migrations(cfg: MigrationConfig, steps: int, start: str = "a0") -> str:
    """CTEs a1 .. aT (vid, part, settle) and m1 .. mT (the moves), from ``start`` (vid, part, settle)."""
    k, out = cfg.k, []
    slack = round(cfg.slack * 100)
    caps = f"cap as (select unnest({list(cfg.caps)})::bigint c, unnest(range({k}))::int cp)" if cfg.caps else None
    met = "join cap on cap.cp = parts.part" if cfg.caps else "cross join cap"
    cap = f"greatest((n * {slack} + {100 * k - 1}) // {100 * k}, top)" if cfg.use_quota else "n"
    out.append(f"parts as (select range::int part from range({k})), {caps}" if caps else f"parts as (select range::int part from range({k})), cap as (select {cap} c from (select sum(n) n, max(n) top from (select count(*) n from {start} group by part)))")
    for t in range(1, steps + 1):
        a = start if t == 1 else f"a{t - 1}"
        tie = mix32_sql("h.vid", salt_sql(cfg.seed, TIE, t, "h.p")) if cfg.tie_break == "hash" else "0"
        first = "gain desc, " if cfg.admission == "gain" else ""
        turn = f"((case when part < p then part else part - 1 end - {t}) % {k - 1} + {k - 1}) % {k - 1}"
        quota = f"room // {k - 1}" + (f" + (({turn}) < room % {k - 1})::int" if cfg.quota_remainder == "rotate" else "")
        chosen = f"rn <= {quota}" if cfg.use_quota else "true"
        out.append(f"h{t} as materialized ({histogram(a, cfg.count_self)})")
        out.append(f"r{t} as materialized (select h.vid, a.part, h.p, h.cnt, a.settle, row_number() over (partition by h.vid order by h.cnt desc, (h.p = a.part) desc, {tie} desc, h.p) r, sum(case when h.p = a.part then h.cnt else 0 end) over (partition by h.vid) own from h{t} h join {a} a on a.vid = h.vid)")
        out.append(f"w{t} as materialized (select vid, part, p, cnt - own gain, {mix32_sql('vid', salt_sql(cfg.seed, COIN, t))} < {threshold(cfg.s)} acted from r{t} where r = 1 and p <> part and (settle is null or settle < {t}))")
        out.append(f"room{t} as materialized (select parts.part j, greatest(0, c - count(a.vid))::bigint room from parts {met} left join {a} a on a.part = parts.part group by parts.part, c)")
        out.append(f"m{t} as materialized (select vid, part from_part, p to_part, gain from (select w.*, room, row_number() over (partition by part, p order by {first}{mix32_sql('vid', salt_sql(cfg.seed, ADMIT, t))}, vid) rn from w{t} w join room{t} on j = p where acted) where {chosen})")
        settle = f"case when m.vid is not null then {t + 1} when a.settle > {t} then a.settle end" if cfg.deferred else "null"
        out.append(f"a{t} as materialized (select a.vid, coalesce(m.to_part, a.part)::int part, ({settle})::int settle from {a} a left join m{t} m on m.vid = a.vid)")
    return ", ".join(out)


def begin(name: str, cfg: MigrationConfig, start: str = "hsh_mixed", edges: str | None = None) -> str:
    return f"{graph(name, edges)}, a0 as materialized (select vid, part, null::int settle from ({assignment(start, cfg.k, cfg.seed)}))"


def cut_of(a: str) -> str:
    return f"(select count(*) from edges join {a} x on x.vid = src join {a} y on y.vid = dst where x.part <> y.part)"


def history(name: str, cfg: MigrationConfig, steps: int, start: str = "hsh_mixed", edges: str | None = None, columns: str = "") -> str:
    rows = [
        f"select {t}::int iteration, (select count(*) from w{t}) proposed, (select count(*) from w{t} where not acted) damped, (select count(*) from w{t} where acted) - (select count(*) from m{t}) refused, (select count(*) from m{t}) moved, {cut_of(f'a{t}')} cut, (select count(*) from edges) edges, (select max(n) from (select count(vid) n from parts left join a{t} using (part) group by parts.part)) max_load, (select min(n) from (select count(vid) n from parts left join a{t} using (part) group by parts.part)) min_load{columns}"
        for t in range(1, steps + 1)
    ]
    return f"with {begin(name, cfg, start, edges)}, {migrations(cfg, steps)} " + " union all ".join(rows)


def final(name: str, cfg: MigrationConfig, steps: int, select: str, start: str = "hsh_mixed", edges: str | None = None) -> str:
    return f"with {begin(name, cfg, start, edges)}, {migrations(cfg, steps)} {select}"


def on_edges(name: str, select: str, more: str = "") -> str:
    return f"with {graph(name)}{', ' + more if more else ''} {select}"


def placed(name: str, kind: str, k: int, select: str) -> str:
    """A query over edges, sym, v, a (vid, part) and l (localised edges)."""
    return on_edges(name, select, f"a as materialized ({assignment(kind, k)}), l as materialized (select src, dst, x.part src_part, y.part dst_part from edges join a x on x.vid = src join a y on y.vid = dst)")


def influence(steps: int, p: float = 0.5, unit: int = 1_000_000_000) -> str:
    out = [f"arcs as materialized (select distinct src, dst from ({CALL}) where src <> dst), outs as (select src, count(*) o from arcs group by src), i0 as (select distinct unnest([src, dst]) vid, 0::bigint i from arcs)"]
    for t in range(1, steps + 1):
        out.append(f"i{t} as materialized (select x.vid, coalesce(s, 0)::bigint i from i0 x left join (select dst, sum(floor(({unit} + {p} * i) / o)::bigint)::bigint s from arcs join outs using (src) join i{t - 1} on vid = src group by dst) on dst = x.vid)")
    return f"with {', '.join(out)} select vid, round(i / {unit}, 6) influence from i{steps}"


def pagerank(name: str, steps: int, damping: float = 0.85, unit: int = 1_000_000_000) -> str:
    out = [graph(name), f"outs as (select src, count(*) o from sym group by src), i0 as (select vid, {unit}::bigint i from v)"]
    for t in range(1, steps + 1):
        out.append(f"i{t} as materialized (select v.vid, floor({(1 - damping) * unit!r} + {damping}::double * coalesce(s, 0))::bigint i from v left join (select dst, sum(i // o)::bigint s from sym join outs using (src) join i{t - 1} on vid = src group by dst) on dst = v.vid)")
    return f"with {', '.join(out)} select vid, round(i / {unit}, 6) rank from i{steps}"


def cliques(edges: str, ordered: bool) -> str:
    arcs = "select src, dst from edges" if ordered else "select src, dst from sym"
    own = "list_filter(x.nbrs, lambda n: n > a.src)" if ordered else "x.nbrs"
    return f"""with {graph("", edges)}, arcs as materialized ({arcs}),
lists as materialized (select src vid, list_sort(list(dst)) nbrs from sym group by src),
rows_ as (select a.src vid, list_sort(list_distinct(list_concat(list_intersect({own}, y.nbrs), [a.src, a.dst]))) members from arcs a join lists x on x.vid = a.src join lists y on y.vid = a.dst),
every as (select vid, members from rows_ group by vid, members having count(*) = len(members) - 1
  union all select src, list_sort([src, min(dst)]) from arcs group by src union all select vid, [vid] from v)
select vid, len(members)::int size, array_to_string(members, ',') members from (select *, row_number() over (partition by vid order by len(members) desc, members) r from every) where r = 1"""


def tissue(edges: str, cells: str, steps: int, n_vars: int, dt=0.1, diffusion=0.1, epsilon=0.08, a=0.7, b=0.8, current=0.5, unit=1_000_000) -> str:
    pads = n_vars - 2
    cols = "".join(f", 0::bigint p{j}" for j in range(pads))
    d = lambda x: f"{x}::double"
    out = [graph("", edges), f"c0 as materialized (select vid, case when inert then 0 else floor(excitation * {unit})::bigint end u, 0::bigint w, inert{cols} from ({cells}))"]
    for t in range(1, steps + 1):
        u, w = f"(c.u / {d(unit)})", f"(c.w / {d(unit)})"
        pull = f"((coalesce(f.s, 0) - coalesce(f.n, 0) * c.u)::double / {d(unit)})"
        du = f"({u} - {u} * {u} * {u} / 3 - {w} + {d(current)} + {d(diffusion)} * {pull})"
        dw = f"({d(epsilon)} * ({u} + {d(a)} - {d(b)} * {w}))"
        chain = "".join(f", floor(c.p{j} + {d(0.5)} * ({'c.u' if j == 0 else f'c.p{j - 1}'} - c.p{j}))::bigint p{j}" for j in range(pads))
        out.append(f"c{t} as materialized (select c.vid, case when c.inert then 0 else round(({u} + {d(dt)} * {du}) * {unit})::bigint end u, case when c.inert then 0 else round(({w} + {d(dt)} * {dw}) * {unit})::bigint end w, c.inert{chain} from c{t - 1} c left join (select src, sum(u)::bigint s, count(*) n from sym join c{t - 1} x on x.vid = dst group by src) f on f.src = c.vid)")
    total = " + ".join(f"p{j}" for j in range(pads)) or "0"
    return f"with {', '.join(out)} select vid, u, w, ({total})::bigint pad_sum from c{steps}"
