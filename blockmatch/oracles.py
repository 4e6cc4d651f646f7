"""DuckDB SQL for the queries: a chain of common tables, and one final select for each query.

The chain restates the definitions in set terms, independently of the engine's plans:
walks are followed half-edge by half-edge in a recursive query, membership compares every
home with every side, scores are literal double sums.
"""

from __future__ import annotations

import re

from .params import SearchParams

KINDS, M = 8, 5
P = SearchParams()


def spread(key: str, salt: int, modulus: int) -> str:
    x = f"(({key}) * 48271 + {salt * 7919 + 1}) % 2147483647"
    return f"((({x}) * ({x})) % 2147483647) % {modulus}"


def _walk(source: str) -> str:
    """Every half-edge's walk until it is back: (start, cur, step)."""
    return f"""
    select hid as start, hid as cur, 0::bigint as step from {source}
    union all
    select w.start, n.nxt, w.step + 1 from WALK w join {source} n on n.hid = w.cur where n.nxt <> w.start"""


def _next(halves: str) -> str:
    return f"""
    select hid + 1 - 2 * (hid % 2) as hid,
           coalesce(lag(hid) over (partition by src order by angle, hid), last_value(hid) over (partition by src order by angle, hid rows between unbounded preceding and unbounded following)) as nxt
    from {halves}"""


def _dot(a: str, b: str) -> str:
    return f"list_dot_product({a}, {b})"


def _within(p: str, s: str, r: int) -> str:
    dx, dy, wx, wy = f"({s}.bx - {s}.ax)", f"({s}.by - {s}.ay)", f"({p}.x - {s}.ax)", f"({p}.y - {s}.ay)"
    along, long2 = f"({wx} * {dx} + {wy} * {dy})", f"({dx} * {dx} + {dy} * {dy})"
    end = f"(({p}.x - {s}.bx) * ({p}.x - {s}.bx) + ({p}.y - {s}.by) * ({p}.y - {s}.by))"
    cross = f"({dx} * {wy} - {dy} * {wx})"
    return f"case when {along} <= 0 then {wx} * {wx} + {wy} * {wy} <= {r * r} when {along} >= {long2} then {end} <= {r * r} else {cross} * {cross} <= {r * r}::bigint * {long2} end"


_MS = range(M)

def base_chain(theta: float = P.theta, radius: int = P.radius, keep: int = 75, diag: int = 10) -> dict[str, str]:
    """The common tables for settings of the lattice network and of a search; a query centre's part holds most vertices."""
    return {
        "size": "select count(*)::bigint as n, floor(sqrt(count(*) - 1))::bigint + 1 as w from customer",
        "vertices": f"""
        select c_custkey::bigint as vid, (1000 * (c_custkey % w) + {spread("c_custkey", 1, 401)} - 200)::bigint as x,
               (1000 * (c_custkey // w) + {spread("c_custkey", 2, 401)} - 200)::bigint as y from customer, size""",
        "links": f"""
        select c_custkey * 4 as eid, c_custkey as u, c_custkey + 1 as v from customer, size where c_custkey % w < w - 1 and {spread("c_custkey", 3, 100)} < {keep}
        union all select c_custkey * 4 + 1, c_custkey, c_custkey + w from customer, size where {spread("c_custkey", 4, 100)} < {keep}
        union all select c_custkey * 4 + 2, c_custkey, c_custkey + w + 1 from customer, size where c_custkey % w < w - 1 and {spread("c_custkey", 5, 100)} < {diag}""",
        "edges": """
        select l.eid::bigint as eid, l.u::bigint as u, l.v::bigint as v, sqrt(((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y))::double) as len
        from links l join vertices a on a.vid = l.u join vertices b on b.vid = l.v""",
        "incident": """
        select vid, eid, row_number() over (partition by vid order by eid) - 1 as nth, count(*) over (partition by vid) as degree
        from (select u as vid, eid from edges union all select v, eid from edges)""",
        "edge_poi": """
        select i.eid, substr(o_orderpriority, 1, 1)::int - 1 as poi_type, count(*) as cnt
        from orders join incident i on i.vid = o_custkey and i.nth = o_orderkey % i.degree group by all""",
        "edge_vec": f"select eid, [{', '.join(f'coalesce(sum(cnt) filter (poi_type = {i}), 0)::double' for i in _MS)}] as vec from edge_poi group by eid",
        "halves": """
        select 2 * e.eid as hid, e.eid, a.vid as src, b.vid as dst, atan2((b.y - a.y)::double, (b.x - a.x)::double) as angle, a.x, a.y, b.x - a.x as dx, b.y - a.y as dy
        from edges e join vertices a on a.vid = e.u join vertices b on b.vid = e.v
        union all
        select 2 * e.eid + 1, e.eid, b.vid, a.vid, atan2((a.y - b.y)::double, (a.x - b.x)::double), b.x, b.y, a.x - b.x, a.y - b.y
        from edges e join vertices a on a.vid = e.u join vertices b on b.vid = e.v""",
        "next1": _next("halves"),
        "walk1": _walk("next1").replace("WALK", "walk1"),
        "orbit1": "select cur as hid, min(start) as orbit from walk1 group by cur",
        "bridges": "select hid // 2 as eid from orbit1 group by 1 having min(orbit) = max(orbit)",
        "rest": "select * from halves where eid not in (select eid from bridges)",
        "next2": _next("rest"),
        "walk2": _walk("next2").replace("WALK", "walk2"),
        "orbit2": "select w.cur as hid, w.start as orbit, w.step as place, count(*) over (partition by w.start) as size from walk2 w join (select cur, min(start) as low from walk2 group by cur) m on m.cur = w.cur and m.low = w.start",
        "visits": "select o.*, r.src, count(*) over (partition by o.orbit, r.src) as times from orbit2 o join rest r on r.hid = o.hid",
        "odd": "select distinct orbit from visits where times > 1",
        "before": """
        select orbit, place, coalesce(lag(hid) over (partition by orbit, src order by place), last_value(hid) over (partition by orbit, src order by place rows between unbounded preceding and unbounded following)) as nxt
        from visits where orbit in (select orbit from odd)""",
        "next3": "select v.hid, b.nxt from visits v join before b on b.orbit = v.orbit and b.place = (v.place + 1) % v.size",
        "walk3": _walk("next3").replace("WALK", "walk3"),
        "orbit3": "select w.cur as hid, w.start as orbit, w.step as place from walk3 w join (select cur, min(start) as low from walk3 group by cur) m on m.cur = w.cur and m.low = w.start",
        "loops": "select hid, orbit, place from orbit2 where orbit not in (select orbit from odd) union all select hid, orbit, place from orbit3",
        "rings": """
        select l.orbit as bid, count(*) as n_sides, list(r.src order by l.place) as vids, list(r.eid order by l.place) as eids
        from loops l join rest r on r.hid = l.hid group by l.orbit having sum(r.x * r.dy - r.y * r.dx) > 0""",
        "blocks": """
        select bid, least(n_sides, 9)::int as kind, n_sides::int as n_sides, vids, eids from rings
        union all select 2 * eid, 2, 2, [u, v], [eid] from edges where eid in (select eid from bridges)""",
        "boxes": "select b.bid, min(x) as xmin, min(y) as ymin, max(x) as xmax, max(y) as ymax from (select bid, unnest(vids) as vid from blocks) b join vertices v on v.vid = b.vid group by b.bid",
        "bvec": f"""
        select k.bid, k.kind, [{', '.join(f'coalesce(sum(e.vec[{i + 1}]), 0)' for i in _MS)}] as vec
        from (select bid, kind, unnest(eids) as eid from blocks) k left join edge_vec e on e.eid = k.eid group by k.bid, k.kind""",
        "bunit": f"select bid, kind, vec, case when {_dot('vec', 'vec')} > 0 then list_transform(vec, lambda x: x / sqrt({_dot('vec', 'vec')})) else vec end as uvec from bvec",
        "sides": """
        select k.bid, a.x as ax, a.y as ay, b.x as bx, b.y as by
        from (select bid, kind, vids, unnest(range(case when kind = 2 then 1 else len(vids) end)) as i from blocks) k
        join vertices a on a.vid = k.vids[k.i + 1] join vertices b on b.vid = k.vids[(k.i + 1) % len(k.vids) + 1]""",
        "members": f"""
        select distinct v.vid as home, s.bid from vertices v join sides s
        on v.x between least(s.ax, s.bx) - {radius} and greatest(s.ax, s.bx) + {radius} and v.y between least(s.ay, s.by) - {radius} and greatest(s.ay, s.by) + {radius}
        where {_within("v", "s", radius)}""",
        "own": "select m.home, b.bid, b.kind, b.vec, b.uvec from members m join bunit b on b.bid = m.bid",
        "stats": "select home, kind, count(*) as cnt, " + ", ".join(f"[{', '.join(f'{f}({v}[{i + 1}])' for i in _MS)}] as {name}" for f, v, name in (("sum", "uvec", "usum"), ("max", "uvec", "umax"), ("sum", "vec", "csum"), ("max", "vec", "cmax"))) + " from own group by home, kind",
        "bounds": "select o.bid, min(s.cnt) as min_cnt, max(s.cnt) as max_cnt from own o join stats s on s.home = o.home and s.kind = o.kind group by o.bid",
        "hashed": f"select vid, x, y, {spread('vid', 99, 2147483647)} as o from vertices where vid in (select home from stats) order by o, vid limit 100",
        "near_hashed": "select vid, vid as seen from hashed union select r.vid, e.b from near_hashed r join (select u as a, v as b from edges union all select v, u from edges) e on e.a = r.seen",
        "centres": """
        select (row_number() over (order by o, vid) - 1)::int as qid, vid as home, x as qx, y as qy from hashed
        where vid in (select vid from near_hashed group by vid having 2 * count(*) > (select count(*) from vertices)) qualify qid < 15""",
        "asked": "select c.qid, s.kind, s.cnt as q_cnt, s.usum as q_usum, s.umax as q_umax, s.csum as q_csum, s.cmax as q_cmax, count(*) over (partition by c.qid) as n_kinds from centres c join stats s on s.home = c.home",
        "asked_blocks": "select c.qid, o.kind, o.uvec, o.vec, a.q_cnt, a.n_kinds from centres c join own o on o.home = c.home join asked a on a.qid = c.qid and a.kind = o.kind",
        "sims": f"""
        select q.qid, o.home, sum({_dot("o.uvec", "q.uvec")} / q.q_cnt / q.n_kinds) as sim, sum({_dot("o.vec", "q.vec")} / q.q_cnt / q.n_kinds) as raw,
               sum({_dot("o.uvec", "q.uvec")} / q.q_cnt / q.n_kinds / s.cnt) as pairs
        from own o join asked_blocks q on q.kind = o.kind join stats s on s.home = o.home and s.kind = o.kind group by q.qid, o.home""",
        "ubs": f"""
        select a.qid, s.home, sum({_dot("s.umax", "a.q_umax")}) as printed, sum(s.cnt * {_dot("s.umax", "a.q_umax")} / a.n_kinds) as safe, sum(s.cnt * {_dot("s.umax", "a.q_usum")} / a.q_cnt / a.n_kinds) as tight
        from stats s join asked a on a.kind = s.kind group by a.qid, s.home""",
        "cands": f"select a.qid, b.bid from bunit b join bounds n on n.bid = b.bid join asked a on a.kind = b.kind where {_dot('b.uvec', 'a.q_usum')} * n.max_cnt >= {theta} * a.q_cnt - 1e-12",
        "named": "select distinct c.qid, m.home from cands c join members m on m.bid = c.bid",
        "placed": "select s.qid, s.home, s.sim, (v.x - c.qx) * (v.x - c.qx) + (v.y - c.qy) * (v.y - c.qy) as d2 from sims s join vertices v on v.vid = s.home join centres c on c.qid = s.qid",
        "ranked": f"select qid, row_number() over (partition by qid order by d2, home) as rank, home, sim, d2 from placed where sim >= {theta}",
    }


CHAIN = base_chain()
#: Common tables that queries add.
MORE: dict[str, str] = {}


def chain(final: str, **settings) -> str:
    """The final select with exactly the common tables it needs, in order."""
    tables = (base_chain(**settings) if settings else CHAIN) | MORE
    need, todo = set(), [final]
    while todo:
        text = todo.pop()
        for name in tables:
            if name not in need and re.search(rf"\b{name}\b", text):
                need.add(name)
                todo.append(tables[name])
    text = "with recursive " + ",\n".join(f"{n} as materialized ({tables[n]})" for n in tables if n in need) + "\n" + final
    return re.sub(r"\bsim >= ([0-9.]+)(?! - 1e-12)\b", r"sim >= \1 - 1e-12", text)  # sums in another order


def flat(column: str, prefix: str, m: int = M) -> str:
    return ", ".join(f"round({column}[{i + 1}], 6) as {prefix}{i}" for i in range(m))


ANSWER = "select qid, rank::int as rank, home, round(sim, 6) as sim, round(sqrt(d2::double), 6) as dist from {} where rank <= 10"
