"""All queries of the engine over the given tables, and their DuckDB SQL.

Every query runs over whole tables with the default settings; a count that is part of a
feature (15 query centres, ranks up to k) is the only limit. Artefacts are built once for
a session and table folder.
"""

from __future__ import annotations

import re
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import oracles as O
from .functions import vectors
from .functions.geometry import disc_interval, dist2
from .operators import blocks as B
from .operators import community as C
from .operators import network as N
from .operators import similarity as S
from .operators.boxtree import LEAF
from .params import SearchParams
from .plans import corridor as K
from .plans import ranked as R
from .plans import workloads
from .plans.artifacts import artifacts, base_of, net_a, net_b, query_homes
from .sources.tables import Cuts, table
from .streaming import events as E

P = SearchParams()
O.MORE["reach"] = "select vid, vid as seen from vertices union select e.b, r.seen from reach r join (select u as a, v as b from edges union all select v, u from edges) e on e.a = r.vid"
Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    """Register the function under its name, with the SQL that gives the same rows."""

    def add(f):
        Q[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return add


def same(name: str, as_name: str, f) -> None:
    """Another way to the rows of a query that has SQL."""
    Q[name] = f
    if as_name in SQL:
        SQL[name] = SQL[as_name]


def spread_out(df: DataFrame, column: str, prefix: str, m: int, *keys: str) -> DataFrame:
    return df.select(*keys, *[F.round(F.col(column)[i], 6).alias(f"{prefix}{i}") for i in range(m)])


# -- networks --


@query(O.chain("select * from vertices"))
def net_vertices(spark, d):
    return N.lattice_vertices(table(spark, d, "customer"), "c_custkey")


@query(O.chain("select eid, u, v, round(len, 6) as len from edges"))
def net_edges(spark, d):
    return N.lattice_network(table(spark, d, "customer"), "c_custkey").edges.withColumn("len", F.round("len", 6))


@query(O.chain("select (select count(*) from vertices) as vertices, (select count(*) from edges) as edges, (select sum(cnt)::bigint from edge_poi) as pois, (select count(distinct poi_type) from edge_poi) as poi_types, round(2.0 * (select count(*) from edges) / (select count(*) from vertices), 6) as avg_degree, round((select count(*) from edges)::double / (select count(*) from vertices), 6) as links_per_vertex"))
def net_profile(spark, d):
    net = net_a(spark, d)
    v, e = net.vertices.agg(F.count("*").alias("vertices")), net.edges.agg(F.count("*").alias("edges"))
    p = net.edge_poi.agg(F.sum("cnt").alias("pois"), F.count_distinct("poi_type").alias("poi_types"))
    rows = v.crossJoin(F.broadcast(e)).crossJoin(F.broadcast(p))  # one row each
    return rows.withColumns({"avg_degree": F.round(2.0 * F.col("edges") / F.col("vertices"), 6), "links_per_vertex": F.round(F.col("edges") / F.col("vertices"), 6)})


@query(O.chain("select vid, min(seen) as comp from reach group by vid"))
def net_components(spark, d):
    net = N.lattice_network(table(spark, d, "customer"), "c_custkey")
    return N.components(net.vertices, net.edges, Cuts(spark))


@query()
def generated_uniform(spark, d):
    return N.generate_network(table(spark, d, "customer"), "c_custkey", "uniform").edges


@query()
def generated_cluster(spark, d):
    return N.generate_network(table(spark, d, "customer"), "c_custkey", "cluster", seed_column="c_nationkey").edges


@query(O.chain(f"select eid, {', '.join(f'vec[{i + 1}] as v{i}' for i in range(O.M))} from edge_vec"))
def edge_poi_vectors(spark, d):
    net = net_a(spark, d)
    return spread_out(N.edge_vectors(net.edge_poi, net.m), "vec", "v", net.m, "eid")


@query(O.chain("select eid, " + ", ".join(f"coalesce(sum(cnt) filter (poi_type = {i}), 0)::bigint as t{i}" for i in range(O.M)) + " from edge_poi group by eid"))
def poi_type_pivot(spark, d):
    rows = net_a(spark, d).edge_poi.groupBy("eid").pivot("poi_type", list(range(5))).agg(F.sum("cnt"))
    return rows.na.fill(0).toDF("eid", *[f"t{i}" for i in range(5)])


_METRO = {
    "size": O.CHAIN["size"].replace("customer", "orders"),
    "links": O.CHAIN["links"].replace("c_custkey", "o_orderkey").replace("customer", "orders"),
    "vertices": O.CHAIN["vertices"].replace("c_custkey", "o_orderkey").replace("customer", "orders"),
}


@query(
    f"with size as ({_METRO['size']}), vertices as ({_METRO['vertices']}), links as ({_METRO['links']}), edges as ({O.CHAIN['edges']}), incident as ({O.CHAIN['incident']}) "
    "select i.eid, p_brand as poi_type, count(*) as cnt from lineitem join part on p_partkey = l_partkey join incident i on i.vid = l_orderkey and i.nth = (l_partkey + l_linenumber) % i.degree group by all"
)
def metro_poi_vectors(spark, d):
    names = table(spark, d, "part").select("p_brand").distinct().orderBy("p_brand").withColumn("poi_type", (F.row_number().over(W.orderBy("p_brand")) - 1))  # a few brands
    return net_b(spark, d).edge_poi.join(F.broadcast(names), "poi_type").select("eid", F.col("p_brand").alias("poi_type"), "cnt")


# -- blocks --


@query(O.chain("select hid, nxt from next1"))
def half_edge_next(spark, d):
    net = N.lattice_network(table(spark, d, "customer"), "c_custkey")
    return B.link_half_edges(B.half_edges(net.vertices, net.edges))


_VIDS = "list_aggregate(list_sort(vids)::varchar[], 'string_agg', ',')"


def _sorted_vids() -> F.Column:
    return F.concat_ws(",", F.array_sort("vids").cast("array<string>"))


@query(O.chain(f"select bid, kind, n_sides, {_VIDS} as vids from blocks where kind > 2"))
def block_rings(spark, d):
    return artifacts(spark, d).blocks.filter("kind > 2").select("bid", "kind", "n_sides", _sorted_vids().alias("vids"))


def _strategy(name):
    def run(spark, d):
        rows = B.detect_blocks(N.lattice_network(table(spark, d, "customer"), "c_custkey"), P.max_sides, Cuts(spark), name)
        return rows.filter("kind > 2").select("bid", "kind", "n_sides", _sorted_vids().alias("vids"))

    return run


same("block_rings_doubling", "block_rings", _strategy("doubling"))
same("block_rings_trace", "block_rings", _strategy("trace"))
Q["block_rings_walk"] = _strategy("walk")
SQL["block_rings_walk"] = O.chain(f"select bid, kind, n_sides, {_VIDS} as vids from blocks where kind > 2 and n_sides <= {P.max_sides}")


@query(O.chain(f"select bid, kind, n_sides, {_VIDS} as vids from blocks where kind = 2"))
def block_bridges(spark, d):
    return artifacts(spark, d).blocks.filter("kind = 2").select("bid", "kind", "n_sides", _sorted_vids().alias("vids"))


@query(O.chain(f"select bid, kind, {O.flat('vec', 'v')}, {O.flat('uvec', 'u')} from bunit"))
def block_vectors(spark, d):
    a = artifacts(spark, d)
    cols = [F.round(F.col(c)[i], 6).alias(f"{p}{i}") for c, p in (("vec", "v"), ("uvec", "u")) for i in range(a.m)]
    return a.blocks.select("bid", "kind", *cols)


@query(O.chain("select * from boxes"))
def block_boxes(spark, d):
    return artifacts(spark, d).blocks.select("bid", "xmin", "ymin", "xmax", "ymax")


@query(O.chain("select kind, count(*) as n from blocks group by kind"))
def block_kind_census(spark, d):
    return artifacts(spark, d).blocks.groupBy("kind").agg(F.count("*").alias("n"))


_WHERE = "from (select b.kind, r_name, n_name from blocks b join customer c on c.c_custkey = b.vids[1] join nation on n_nationkey = c_nationkey join region on r_regionkey = n_regionkey) t"


def _census(spark, d):
    """Blocks by region, nation and kind; a block counts where its first vertex lies."""
    a = artifacts(spark, d)
    rows = a.blocks.select("kind", F.col("vids")[0].alias("vid")).join(table(spark, d, "customer"), F.col("vid") == F.col("c_custkey"))
    return rows.join(F.broadcast(table(spark, d, "nation")), F.col("n_nationkey") == F.col("c_nationkey")).join(F.broadcast(table(spark, d, "region")), F.col("r_regionkey") == F.col("n_regionkey"))


@query(O.chain(f"select r_name, n_name, coalesce(kind, -1) as kind, count(*) as n {_WHERE} group by rollup (r_name, n_name, kind)"))
def census_rollup(spark, d):
    return _census(spark, d).rollup("r_name", "n_name", "kind").agg(F.count("*").alias("n")).na.fill({"kind": -1})


@query(O.chain(f"select r_name, coalesce(kind, -1) as kind, count(*) as n {_WHERE} group by cube (r_name, kind)"))
def census_cube(spark, d):
    return _census(spark, d).cube("r_name", "kind").agg(F.count("*").alias("n")).na.fill({"kind": -1})


@query(O.chain(f"select r_name, coalesce(kind, -1) as kind, count(*) as n {_WHERE} group by grouping sets ((r_name), (kind), ())"))
def census_grouping_sets(spark, d):
    return _census(spark, d).groupingSets([["r_name"], ["kind"], []], "r_name", "kind").agg(F.count("*").alias("n")).na.fill({"kind": -1})


# -- communities --


@query(O.chain("select * from members"))
def members_grid(spark, d):
    return artifacts(spark, d).members


def _members_tree(spark, d):
    a = artifacts(spark, d)
    return C.members_tree(a.vertices, a.sides, a.nodes, a.entries.select("bid", "node_id"), a.radius, P.fanout_bits)


def _members_allpairs(spark, d):
    base = base_of(spark, d)  # no other table is needed
    return C.members_allpairs(base.net.vertices, base.sides, P.radius)


same("members_tree", "members_grid", _members_tree)
same("members_allpairs", "members_grid", _members_allpairs)


@query()
def members_connected(spark, d):
    a = artifacts(spark, d)
    return C.connected_members(a.members, a.blocks, a.cut)


@query(O.chain("select home, kind, cnt from stats"))
def community_counts(spark, d):
    return artifacts(spark, d).stats.select("home", "kind", "cnt")


@query(O.chain(f"select home, kind, {O.flat('umax', 'u')}, {O.flat('cmax', 'c')} from stats"))
def community_maxvec(spark, d):
    a = artifacts(spark, d)
    return a.stats.select("home", "kind", *[F.round(F.col(c)[i], 6).alias(f"{p}{i}") for c, p in (("umax", "u"), ("cmax", "c")) for i in range(a.m)])


@query(O.chain("select * from bounds"))
def block_count_bounds(spark, d):
    return artifacts(spark, d).bounds


@query(O.chain("""
select home, sum(cnt)::bigint as blocks, round(coalesce(sum(cnt) filter (kind = 4), 0) / sum(cnt)::double, 6) as grid_share, round(coalesce(sum(cnt) filter (kind = 2), 0) / sum(cnt)::double, 6) as tree_share,
       count(*) as kinds, round(abs(ln(sum(cnt)::double) - sum(cnt * ln(cnt::double)) / sum(cnt)), 6) as entropy from stats group by home"""))
def motif_profile(spark, d):
    rows = C.motif_profile(artifacts(spark, d).stats)
    return rows.withColumns({"grid_share": F.round("grid_share", 6), "tree_share": F.round("tree_share", 6), "entropy": F.round(F.abs("entropy"), 6)})


_Z = " + ".join(f"(((cx >> {b}) % 2) << {2 * b}) + (((cy >> {b}) % 2) << {2 * b + 1})" for b in range(20))
_CELL = 2.0 * LEAF
O.MORE |= {
    "coded": f"select bid, {_Z} as z from (select bid, (floor((xmin + xmax) / {_CELL}) - min(floor((xmin + xmax) / {_CELL})) over ())::bigint as cx, (floor((ymin + ymax) / {_CELL}) - min(floor((ymin + ymax) / {_CELL})) over ())::bigint as cy from boxes)",
    "height": f"select level from (select unnest(range(11)) as level), (select max(z) as top from coded) where level = 0 or (top >> ({P.fanout_bits} * (level - 1))) > 0",
    "placed_blocks": f"select l.level, c.z >> ({P.fanout_bits} * l.level) as node_id, k.*, x.xmin, x.ymin, x.xmax, x.ymax, coalesce(n.min_cnt, 0) as min_cnt, coalesce(n.max_cnt, 0) as max_cnt from coded c join bunit k on k.bid = c.bid join boxes x on x.bid = c.bid left join bounds n on n.bid = c.bid, height l",
    "node_kinds": "select level, node_id, kind, min(min_cnt) as min_cnt, max(max_cnt) as max_cnt, [" + ", ".join(f"max(uvec[{i + 1}])" for i in range(O.M)) + "] as umax from placed_blocks group by level, node_id, kind",
    "node_passes": f"select distinct a.qid, n.level, n.node_id from node_kinds n join asked a on a.kind = n.kind where list_dot_product(n.umax, a.q_usum) * n.max_cnt >= 0.6 * a.q_cnt - 1e-12",
}


@query(O.chain("select level, count(distinct node_id) as nodes, count(*)::bigint as blocks from placed_blocks group by level"))
def tree_levels(spark, d):
    rows = artifacts(spark, d).nodes.groupBy("level").agg(F.count("*").alias("nodes"), F.sum("n_blocks").alias("blocks"))
    return rows.withColumn("level", F.col("level").cast("long"))


@query()
def tree_levels_str(spark, d):
    """The tree by slices and runs: every block under one root; rank ties make its shape ours."""
    rows = artifacts(spark, d, params=P.but(packing="str")).nodes.groupBy("level").agg(F.count("*").alias("nodes"), F.sum("n_blocks").alias("blocks"))
    return rows.withColumn("level", F.col("level").cast("long"))


@query(O.chain("select level, node_id, min(xmin) as xmin, min(ymin) as ymin, max(xmax) as xmax, max(ymax) as ymax, count(*)::bigint as n_blocks, " + " || ".join(f"case when max(vec[{i + 1}]) > 0 then '1' else '0' end" for i in range(O.M)) + " as poi_bits from placed_blocks group by level, node_id"))
def node_summary(spark, d):
    rows = artifacts(spark, d).nodes.withColumn("level", F.col("level").cast("long"))
    return rows.select("level", "node_id", "xmin", "ymin", "xmax", "ymax", "n_blocks", F.concat_ws("", F.transform("poi_bits", lambda b: F.when(b, "1").otherwise("0"))).alias("poi_bits"))


@query(O.chain("select level, node_id, kind, min_cnt, max_cnt from node_kinds"))
def node_count_bounds(spark, d):
    rows = artifacts(spark, d).nodes.select(F.col("level").cast("long").alias("level"), "node_id", F.explode("kinds").alias("e"))
    return rows.select("level", "node_id", "e.kind", "e.min_cnt", "e.max_cnt")


# -- similarity and bounds --


def _scores(spark, d, params: SearchParams, parts=("sim",)):
    a = artifacts(spark, d)
    return S.scores(a.stats, S.query_stats(a.stats, query_homes(a)), params, parts)


def _rounded(rows, *names):
    return rows.select("qid", "home", *[F.round(n, 6).alias(n) for n in names])


@query(O.chain("select qid, home, round(sim, 6) as sim from sims"))
def sim_factored(spark, d):
    return _rounded(_scores(spark, d, P), "sim")


def _pairwise(spark, d, **changes):
    a = artifacts(spark, d)
    return _rounded(S.pairwise(a.members, a.blocks, query_homes(a), P.but(**changes)), "sim")


same("sim_pairwise", "sim_factored", lambda spark, d: _pairwise(spark, d))


@query(O.chain("select qid, home, round(raw, 6) as sim from sims"))
def sim_raw_dot(spark, d):
    return _rounded(_scores(spark, d, P.but(normalize=False)), "sim")


@query(O.chain("select qid, home, round(pairs, 6) as sim from sims"))
def sim_pairs_denominator(spark, d):
    return _rounded(_scores(spark, d, P.but(denominator="pairs")), "sim")


for _bound in ("printed", "safe", "tight"):
    Q[f"bound_{_bound}"] = lambda spark, d, b=_bound: _rounded(_scores(spark, d, P, (b,)), b)
    SQL[f"bound_{_bound}"] = O.chain(f"select qid, home, round({_bound}, 6) as {_bound} from ubs")


@query(O.chain("""
select qid, count(*) as homes, count(*) filter (printed < sim - 1e-9) as printed_below, count(*) filter (safe < sim - 1e-9) as safe_below, count(*) filter (tight < sim - 1e-9) as tight_below,
       round(avg(safe - sim), 6) as safe_slack, round(avg(tight - sim), 6) as tight_slack, count(*) filter (printed < 0.6 and sim >= 0.6) as printed_lost
from sims join ubs using (qid, home) group by qid"""))
def bound_audit(spark, d):
    a = artifacts(spark, d)
    return R.bound_audit(a, query_homes(a), P)


@query(O.chain("select qid, home from ubs where safe < 0.6 - 1e-12"))
def pruned_by_bound(spark, d):
    return _scores(spark, d, P, ("safe",)).filter(F.col("safe") < P.theta - 1e-12).select("qid", "home")


@query(O.chain("select qid, bid from cands"))
def candidate_blocks(spark, d):
    a = artifacts(spark, d)
    return S.candidate_blocks(a.blocks, a.bounds, S.query_stats(a.stats, query_homes(a)), P).select("qid", "bid")


def _candidate_tree(packing):
    def run(spark, d):
        p = P.but(packing=packing)
        a = artifacts(spark, d, params=p)
        return S.retrieve(a, R.asked_of(a, query_homes(a)), p)[0].select(F.col("qid").cast("int").alias("qid"), "bid")

    return run


same("candidate_blocks_tree", "candidate_blocks", _candidate_tree("zorder"))
same("candidate_blocks_tree_str", "candidate_blocks", _candidate_tree("str"))


@query(O.chain("select c.qid, m.home, round(max(list_dot_product(b.uvec, a.q_usum) / a.q_cnt), 6) as best_score from cands c join members m on m.bid = c.bid join bunit b on b.bid = c.bid join asked a on a.qid = c.qid and a.kind = b.kind group by c.qid, m.home"))
def candidate_homes(spark, d):
    a = artifacts(spark, d)
    found = S.candidate_blocks(a.blocks, a.bounds, S.query_stats(a.stats, query_homes(a)), P)
    return S.candidate_homes(found, a.members).withColumn("best_score", F.round("best_score", 6)).orderBy("qid", F.desc("best_score"), "home")


_VISITS_SQL = ("""
select c.qid, l.level, count(*) as visited from (select distinct qid from asked) c, height l, (select distinct level, node_id from node_kinds) n
where n.level = l.level and (l.level = (select max(level) from height) or exists (select 1 from node_passes p where p.qid = c.qid and p.level = l.level + 1 and p.node_id = n.node_id >> """ + str(P.fanout_bits) + """)) group by c.qid, l.level""")


@query(O.chain(_VISITS_SQL))
def traversal_visits(spark, d):
    a = artifacts(spark, d)
    log = S.retrieve(a, R.asked_of(a, query_homes(a)), P, log=True)[1]
    return log.select(F.col("qid").cast("int").alias("qid"), F.col("level").cast("long").alias("level"), "visited")


# -- ranked search --


def _search(f, **changes):
    def run(spark, d):
        a = artifacts(spark, d)
        return f(a, query_homes(a), P.but(**changes))

    return run


@query(O.chain(O.ANSWER.format("ranked")))
def ranked_search_many(spark, d):
    return _search(R.ranked_search)(spark, d)


for _name, _f in {
    "ranked_search": _search(R.ranked_search, bound="tight"),
    "ranked_search_tree": _search(R.ranked_search, use_tree=True),
    "ranked_search_tree_everywhere": _search(R.ranked_search, use_tree=True, use_distance_stop=False),
    "ranked_search_no_candidates": _search(R.ranked_search, use_candidates=False),
    "ranked_search_no_bound": _search(R.ranked_search, bound="none"),
    "ranked_search_no_distance_stop": _search(R.ranked_search, use_distance_stop=False),
    "ranked_search_count_bound": _search(R.ranked_search, bound_basis="count"),
    "ranked_search_global_count": _search(R.ranked_search, count_scope="global"),
    "scan_baseline": _search(R.scan_baseline),
    "enumerate_baseline": _search(R.enumerate_baseline),
}.items():
    same(_name, "ranked_search_many", _f)


def _packed_search(spark, d):
    p = P.but(packing="str", use_tree=True)
    a = artifacts(spark, d, params=p)
    return R.ranked_search(a, query_homes(a), p)


same("ranked_search_tree_str", "ranked_search_many", _packed_search)


@query()
def ranked_search_printed_bound(spark, d):
    """The printed bound may lose answers; `bound_audit` counts the homes it can lose."""
    return _search(R.ranked_search, bound="printed")(spark, d)


@query(O.chain("select p.qid, round(count(*) filter (l.printed >= 0.6 - 1e-12) / count(*)::double, 6) as recall from (select * from ranked where rank <= 10) p join ubs l on l.qid = p.qid and l.home = p.home group by p.qid"))
def printed_bound_recall(spark, d):
    """Share of the exact answers that the printed bound alone lets through."""
    a = artifacts(spark, d)
    exact = R.ranked_search(a, query_homes(a), P).select("qid", "home")
    through = _scores(spark, d, P, ("printed",)).filter(F.col("printed") >= P.theta - 1e-12).select("qid", "home")
    return R.recall(through.join(exact, ["qid", "home"], "left_semi"), exact).select("qid", F.coalesce("recall", F.lit(0.0)).alias("recall"))


@query(O.chain("select qid, 1.0::double as recall, 0::bigint as false_answers from (select distinct qid from ranked)"))
def search_recall(spark, d):
    """Recall of the pruned search against full enumeration."""
    a = artifacts(spark, d)
    q = query_homes(a)
    return R.recall(R.ranked_search(a, q, P), R.enumerate_baseline(a, q, P))


@query()
def ranked_search_connected(spark, d):
    p = P.but(connected=True)
    a = artifacts(spark, d, params=p)
    return R.ranked_search(a, query_homes(a), p)


_SETS = "(select home, string_agg(bid::varchar, ',' order by bid) as sets from members group by home)"


@query(O.chain(O.ANSWER.format(f"(select qid, row_number() over (partition by qid order by d2, home) as rank, home, sim, d2 from (select p.*, row_number() over (partition by p.qid, s.sets order by p.d2, p.home) as nth from placed p join {_SETS} s on s.home = p.home where p.sim >= 0.6) where nth = 1)")))
def ranked_search_distinct_sets(spark, d):
    return _search(R.ranked_search, distinct_sets=True)(spark, d)


def _one(**changes):
    """One query's answers; the tables of the search are read from the wide table only."""

    def run(spark, d):
        a = artifacts(spark, d)
        home = query_homes(a, 1).first()["home"]
        rows = R.ranked_one(a, home, P, **changes)
        return rows.select(F.lit(0).alias("qid"), F.row_number().over(W.orderBy("d2", "home")).alias("rank"), "home", F.round("sim", 6).alias("sim"), F.round(F.sqrt(F.col("d2").cast("double")), 6).alias("dist"))  # k rows

    return run


_FIRST = O.chain(O.ANSWER.format("ranked") + " and qid = 0")
Q["ranked_search_ring"] = _one()
Q["ranked_search_wide"] = _one(use_rings=False)
SQL["ranked_search_ring"] = SQL["ranked_search_wide"] = _FIRST
Q["ranked_search_elsewhere"] = _search(R.ranked_search, anchor_xy=(5000, 5000))
SQL["ranked_search_elsewhere"] = O.chain("select qid, rank::int as rank, home, round(sim, 6) as sim, round(sqrt(d2::double), 6) as dist from (select s.qid, row_number() over (partition by s.qid order by (v.x - 5000) * (v.x - 5000) + (v.y - 5000) * (v.y - 5000), s.home) as rank, s.home, s.sim, (v.x - 5000) * (v.x - 5000) + (v.y - 5000) * (v.y - 5000) as d2 from sims s join vertices v on v.vid = s.home where s.sim >= 0.6) where rank <= 10")
Q["ranked_search_exclude_home"] = _search(R.ranked_search, exclude_home=True)
SQL["ranked_search_exclude_home"] = O.chain(O.ANSWER.format("(select p.qid, row_number() over (partition by p.qid order by d2, p.home) as rank, p.home, sim, d2 from placed p join centres c on c.qid = p.qid where sim >= 0.6 and p.home <> c.home)"))


_MOTIF = "(select home, sum(cnt)::bigint as blocks, round(coalesce(sum(cnt) filter (kind = 4), 0) / sum(cnt)::double, 6) as grid_share, round(coalesce(sum(cnt) filter (kind = 2), 0) / sum(cnt)::double, 6) as tree_share from stats group by home)"


@query(O.chain(f"select r.qid, r.rank::int as rank, r.home, m.blocks, m.grid_share, m.tree_share from (select p.qid, row_number() over (partition by p.qid order by d2, p.home) as rank, p.home from placed p join centres c on c.qid = p.qid where sim >= 0.6 and p.home <> c.home) r join {_MOTIF} m on m.home = r.home where r.rank <= 10"))
def lens_view(spark, d):
    """The lens scenario: communities like the one under the lens, without it, each with its profile of motifs."""
    a = artifacts(spark, d)
    found = R.ranked_search(a, query_homes(a), P.but(exclude_home=True)).select("qid", "rank", "home")
    profile = C.motif_profile(a.stats).select("home", "blocks", F.round("grid_share", 6).alias("grid_share"), F.round("tree_share", 6).alias("tree_share"))
    return found.join(profile, "home").select("qid", "rank", "home", "blocks", "grid_share", "tree_share")


_REPORT_SQL = """
select qid, count(*) as total, count(*) filter (why = 'candidate') as candidate, count(*) filter (why = 'bound') as bound, count(*) filter (why = 'distance') as distance, count(*) filter (why = 'score') as score, count(*) filter (why = 'answer') as answer,
       round(100.0 * count(*) filter (why in ('candidate', 'bound', 'distance')) / count(*), 4) as pruned_all,
       coalesce(round(100.0 * count(*) filter (why in ('bound', 'distance')) / nullif(count(*) filter (why <> 'candidate'), 0), 4), 0.0) as pruned_nominated
from (
  select c.qid, h.home, case when n.home is null then 'candidate' when coalesce(u.safe, 0) < 0.6 - 1e-12 then 'bound'
         when coalesce(f.found >= 10 and (v.x - c.qx) * (v.x - c.qx) + (v.y - c.qy) * (v.y - c.qy) > f.far, false) then 'distance' when not coalesce(s.sim >= 0.6, false) then 'score' else 'answer' end as why
  from centres c, (select distinct home from stats) h join vertices v on v.vid = h.home
  left join named n on n.qid = c.qid and n.home = h.home left join ubs u on u.qid = c.qid and u.home = h.home left join sims s on s.qid = c.qid and s.home = h.home
  left join (select qid, count(*) as found, max(d2) as far from ranked where rank <= 10 group by qid) f on f.qid = c.qid
) group by qid"""


@query(O.chain(_REPORT_SQL))
def pruning_report(spark, d):
    a = artifacts(spark, d)
    return R.pruning_report(a, query_homes(a), P)


# -- corridor (vertex reach: discs around vertices) --

_SEG = f"(select qid as sid, qx as x0, qy as y0, qx + round(cos(radians(({O.spread('home', 98, 360)})::double)) * 4000)::bigint as x1, qy + round(sin(radians(({O.spread('home', 98, 360)})::double)) * 4000)::bigint as y1 from centres)"
_C = {
    "segs": f"select * from {_SEG}",
    "discs": """
    select sid, bid, greatest((-b - sqrt(b * b - a * c)) / a, 0.0) as low, least((-b + sqrt(b * b - a * c)) / a, 1.0) as high from (
      select s.sid, k.bid, ((s.x1 - s.x0) ** 2 + (s.y1 - s.y0) ** 2)::double as a, ((s.x0 - v.x) * (s.x1 - s.x0) + (s.y0 - v.y) * (s.y1 - s.y0))::double as b, ((s.x0 - v.x) ** 2 + (s.y0 - v.y) ** 2)::double - 1e6 as c
      from segs s, (select bid, unnest(vids) as vid from blocks) k join vertices v on v.vid = k.vid)
    where b * b - a * c >= 0 and greatest((-b - sqrt(b * b - a * c)) / a, 0.0) <= least((-b + sqrt(b * b - a * c)) / a, 1.0)""",
    "united": """
    select sid, bid, min(low) as low, max(high) as high from (
      select *, sum(fresh) over (partition by sid, bid order by low, high rows unbounded preceding) as island from (
        select *, coalesce((low > max(high) over (partition by sid, bid order by low, high rows between unbounded preceding and 1 preceding))::int, 1) as fresh from discs)) group by sid, bid, island""",
    "marks": "select distinct sid, round(t, 9) as t from (select sid, low as t from united union all select sid, high from united union all select sid, 0.0 from segs union all select sid, 1.0 from segs)",
    "ivls": "select * from (select sid, row_number() over (partition by sid order by t) - 1 as ivl, t as t_lo, lead(t) over (partition by sid order by t) as t_hi from marks) where t_hi is not null",
    "inside": "select distinct i.sid, i.ivl, u.bid from ivls i join united u on u.sid = i.sid and u.low <= (i.t_lo + i.t_hi) / 2 and (i.t_lo + i.t_hi) / 2 < u.high",
    "ivl_asked": "select i.sid, i.ivl, b.kind, b.uvec, count(*) over (partition by i.sid, i.ivl, b.kind) as q_cnt from inside i join bunit b on b.bid = i.bid",
    "ivl_kinds": "select sid, ivl, count(distinct kind) as n_kinds from ivl_asked group by sid, ivl",
    "ivl_pairs": f"select a.sid, a.ivl, o.home, sum({O._dot('o.uvec', 'a.uvec')} / a.q_cnt / n.n_kinds) as sim from own o join ivl_asked a on a.kind = o.kind join ivl_kinds n on n.sid = a.sid and n.ivl = a.ivl group by all",
    "ivl_ranked": "select p.sid, p.ivl, row_number() over (partition by p.sid, p.ivl order by (v.x - s.x0) * (v.x - s.x0) + (v.y - s.y0) * (v.y - s.y0), p.home) as rank, p.home, p.sim, (v.x - s.x0) * (v.x - s.x0) + (v.y - s.y0) * (v.y - s.y0) as d2 from ivl_pairs p join vertices v on v.vid = p.home join segs s on s.sid = p.sid where p.sim >= 0.6",
}
_CAPSULE = """
    select sid, bid, low, high from (
      select sid, bid,
             least(case when p2 >= 0 and pl <= ph then pl end, case when q2 >= 0 and ql <= qh then ql end, case when fits and sl <= sh then sl end) as low,
             greatest(case when p2 >= 0 and pl <= ph then ph end, case when q2 >= 0 and ql <= qh then qh end, case when fits and sl <= sh then sh end) as high
      from (
        select *, greatest((-p - sqrt(greatest(p2, 0))) / s2, 0.0) as pl, least((-p + sqrt(greatest(p2, 0))) / s2, 1.0) as ph, greatest((-q - sqrt(greatest(q2, 0))) / s2, 0.0) as ql, least((-q + sqrt(greatest(q2, 0))) / s2, 1.0) as qh,
               greatest(0.0, least(a0, a1), least(b0, b1)) as sl, least(1.0, greatest(a0, a1), greatest(b0, b1)) as sh,
               (go <> 0 or (along >= 0 and along <= l2)) and (turn <> 0 or (aside >= -w and aside <= w)) as fits
        from (
          select *, p * p - s2 * pc as p2, q * q - s2 * qc as q2, sqrt(l2) * 1000 as w, case when go <> 0 then (0 - along) / go end as a0, case when go <> 0 then (l2 - along) / go end as a1,
                 case when turn <> 0 then (-sqrt(l2) * 1000 - aside) / turn end as b0, case when turn <> 0 then (sqrt(l2) * 1000 - aside) / turn end as b1
          from (
            select sid, bid, (sx * sx + sy * sy)::double as s2, (dx * dx + dy * dy)::double as l2, (fx * sx + fy * sy)::double as p, (gx * sx + gy * sy)::double as q, (fx * fx + fy * fy)::double - 1e6 as pc, (gx * gx + gy * gy)::double - 1e6 as qc,
                   (fx * dx + fy * dy)::double as along, (dx * sx + dy * sy)::double as go, (fx * dy - fy * dx)::double as aside, (dy * sx - dx * sy)::double as turn
            from (select s.sid, k.bid, k.bx - k.ax as dx, k.by - k.ay as dy, s.x1 - s.x0 as sx, s.y1 - s.y0 as sy, s.x0 - k.ax as fx, s.y0 - k.ay as fy, s.x0 - k.bx as gx, s.y0 - k.by as gy from segs s, sides k))))) where low is not null"""
_INNER = """
    select m.sid, m.bid, m.low, m.high from (select sid, bid, t as low, lead(t) over (partition by sid, bid order by t) as high from ring_marks) m
    join segs s on s.sid = m.sid join sides k on k.bid = m.bid where m.high is not null
    group by m.sid, m.bid, m.low, m.high
    having count(*) filter ((k.ay > s.y0 + (m.low + m.high) / 2 * (s.y1 - s.y0)) <> (k.by > s.y0 + (m.low + m.high) / 2 * (s.y1 - s.y0))
      and s.x0 + (m.low + m.high) / 2 * (s.x1 - s.x0) < k.ax + (s.y0 + (m.low + m.high) / 2 * (s.y1 - s.y0) - k.ay) * (k.bx - k.ax) / nullif(k.by - k.ay, 0)) % 2 = 1"""
_C["capsules"] = _CAPSULE
_C["ring_marks"] = """
    select distinct sid, bid, t from (
      select s.sid, k.bid, ((k.ax - s.x0) * (k.by - k.ay) - (k.ay - s.y0) * (k.bx - k.ax))::double / nullif((s.x1 - s.x0) * (k.by - k.ay) - (s.y1 - s.y0) * (k.bx - k.ax), 0) as t,
             ((k.ax - s.x0) * (s.y1 - s.y0) - (k.ay - s.y0) * (s.x1 - s.x0))::double / nullif((s.x1 - s.x0) * (k.by - k.ay) - (s.y1 - s.y0) * (k.bx - k.ax), 0) as u
      from segs s, sides k where k.bid in (select bid from blocks where kind > 2)) where t > 0 and t < 1 and u >= 0 and u <= 1
    union all select sid, bid, e from segs, (select bid from blocks where kind > 2), (select unnest([0.0::double, 1.0::double]) as e)"""
_C["inner_parts"] = _INNER
_C["bound_raw"] = "select * from capsules union all select * from inner_parts"
for _new, _old, _from, _to in (("bound_united", "united", "discs", "bound_raw"), ("bound_marks", "marks", "united", "bound_united"), ("bound_ivls", "ivls", "marks", "bound_marks"), ("bound_inside", "inside", "united", "bound_united"), ("bound_asked", "ivl_asked", "inside", "bound_inside"), ("bound_kinds", "ivl_kinds", "ivl_asked", "bound_asked"), ("bound_pairs", "ivl_pairs", "ivl_asked", "bound_asked"), ("bound_ranked", "ivl_ranked", "ivl_pairs", "bound_pairs")):
    _C[_new] = _C[_old].replace(f"from {_from}", f"from {_to}").replace(f"join {_from} ", f"join {_to} ").replace("from ivls ", "from bound_ivls ").replace("join ivl_kinds ", "join bound_kinds ")
O.MORE.update(_C)
_V = P.but(reach="vertex")


def _corridor(spark, d):
    a = artifacts(spark, d)
    seg = K.query_segments(a)
    return a, seg, a.cut.cut(K.merge_intervals(K.raw_intervals(a, seg, a.radius, "vertex")), "merged")


@query(O.chain("select sid, bid, round(low, 6) as low, round(high, 6) as high from discs"))
def disc_intervals(spark, d):
    a = artifacts(spark, d)
    rows = K.raw_intervals(a, K.query_segments(a), a.radius, "vertex")
    return rows.select("sid", "bid", F.round("low", 6).alias("low"), F.round("high", 6).alias("high"))


@query(O.chain("select distinct sid, bid from discs"))
def sweep_blocks(spark, d):
    a = artifacts(spark, d)
    return K.raw_intervals(a, K.query_segments(a), a.radius, "vertex").select("sid", "bid").distinct()


@query(O.chain("select sid, bid, round(low, 6) as low, round(high, 6) as high from united"))
def merged_intervals(spark, d):
    return _corridor(spark, d)[2].select("sid", "bid", F.round("low", 6).alias("low"), F.round("high", 6).alias("high"))


@query(O.chain("select sid, ivl, round(t_lo, 6) as t_lo, round(t_hi, 6) as t_hi from ivls"))
def split_points(spark, d):
    a, seg, merged = _corridor(spark, d)
    return K.split_segment(seg, merged).select("sid", F.col("ivl").cast("long").alias("ivl"), F.round("t_lo", 6).alias("t_lo"), F.round("t_hi", 6).alias("t_hi"))


@query(O.chain("select sid, ivl, bid from inside"))
def interval_blocks_contain(spark, d):
    a, seg, merged = _corridor(spark, d)
    return K.interval_blocks(K.split_segment(seg, merged), merged, "contain").withColumn("ivl", F.col("ivl").cast("long"))


def _delta(spark, d):
    a, seg, merged = _corridor(spark, d)
    return K.interval_blocks(K.split_segment(seg, merged), merged, "delta").select("sid", F.col("ivl").cast("long").alias("ivl"), "bid")


same("interval_blocks_delta", "interval_blocks_contain", _delta)
_IVL_ANSWER = "select sid, ivl::int as ivl, rank::int as rank, home, round(sim, 6) as sim, round(sqrt(d2::double), 6) as dist from ivl_ranked where rank <= 10"


@query(O.chain(_IVL_ANSWER))
def corridor_search(spark, d):
    a = artifacts(spark, d)
    return K.corridor_search(a, K.query_segments(a), _V)


def _corridor_baseline(spark, d):
    a = artifacts(spark, d)
    return K.corridor_baseline(a, K.query_segments(a), _V)


def _corridor_tree(spark, d):
    a = artifacts(spark, d)
    return K.corridor_search(a, K.query_segments(a), _V.but(use_tree=True, bound="tight"), "delta")


def _corridor_everywhere(spark, d):
    a = artifacts(spark, d)
    return K.corridor_search(a, K.query_segments(a), _V.but(use_distance_stop=False, use_candidates=False, bound="none"))


same("corridor_baseline", "corridor_search", _corridor_baseline)
same("corridor_search_tree", "corridor_search", _corridor_tree)
same("corridor_search_everywhere", "corridor_search", _corridor_everywhere)


@query(O.chain(_IVL_ANSWER.replace("ivl_ranked", "bound_ranked")))
def corridor_boundary(spark, d):
    a = artifacts(spark, d)
    return K.corridor_search(a, K.query_segments(a), P)


@query(O.chain("select sid, bid, round(low, 6) as low, round(high, 6) as high from bound_united"))
def boundary_intervals(spark, d):
    a = artifacts(spark, d)
    rows = K.merge_intervals(K.raw_intervals(a, K.query_segments(a), a.radius, "boundary"))
    return rows.select("sid", "bid", F.round("low", 6).alias("low"), F.round("high", 6).alias("high"))


@query(O.chain("select sid, bid, round(low, 6) as low, round(high, 6) as high from inner_parts"))
def ring_interiors(spark, d):
    a = artifacts(spark, d)
    rows = K.interiors(a, a.cut.cut(K.sweep_blocks(a, K.query_segments(a), a.radius), "swept"))
    return rows.select("sid", "bid", F.round("low", 6).alias("low"), F.round("high", 6).alias("high"))


@query()
def corridor_moving(spark, d):
    """Distances from the moving centre; intervals are split where two answers change places."""
    a = artifacts(spark, d)
    return K.corridor_search(a, K.query_segments(a), P.but(anchor="moving"))


@query()
def corridor_visits(spark, d):
    """Nodes read by one descent for all intervals of a segment."""
    a = artifacts(spark, d)
    return K.corridor_visits(a, K.query_segments(a), P)


@query()
def corridor_visits_apart(spark, d):
    """Nodes read when every interval descends by itself."""
    a = artifacts(spark, d)
    return K.corridor_visits(a, K.query_segments(a), P, shared=False)


@query(O.chain("""
select sid, min(ivl) as first_ivl, max(ivl) as last_ivl, any_value(homes) as homes from (
  select *, sum(fresh) over (partition by sid order by ivl) as run from (
    select *, coalesce(homes <> lag(homes) over (partition by sid order by ivl) or ivl <> lag(ivl) over (partition by sid order by ivl) + 1, true)::int as fresh
    from (select sid, ivl, string_agg(home::varchar, ',' order by rank) as homes from ivl_ranked where rank <= 10 group by sid, ivl))) group by sid, run"""))
def corridor_folded(spark, d):
    rows = K.fold_intervals(corridor_search(spark, d))
    return rows.select("sid", F.col("first_ivl").cast("long").alias("first_ivl"), F.col("last_ivl").cast("long").alias("last_ivl"), "homes")


# -- relational forms around the searches --


@query(O.chain("select qid, home, d2, count(*) over (partition by qid order by d2 range between 25000000 preceding and current row) as ring from placed where sim >= 0.6"))
def distance_rings(spark, d):
    a = artifacts(spark, d)
    q = query_homes(a)
    rows = a.wide.crossJoin(F.broadcast(R.spots_of(q, P))).withColumn("d2", dist2(F.col("x"), F.col("y"), F.col("qx"), F.col("qy")))
    rows = R.qualified(a, rows, R.asked_of(a, q), 15, P.but(bound="none", use_candidates=False)).withColumn("qid", F.col("qid").cast("int"))
    return rows.select("qid", "home", "d2", F.count("*").over(W.partitionBy("qid").orderBy("d2").rangeBetween(-25000000, 0)).alias("ring"))


@query(O.chain("select vid from vertices where vid not in (select u from edges) and vid not in (select v from edges)"))
def isolated_vertices(spark, d):
    net = N.lattice_network(table(spark, d, "customer"), "c_custkey")
    return net.vertices.select("vid").join(N.incident(net.edges).select("vid"), "vid", "left_anti")


@query(O.chain("select distinct home from members where bid in (select bid from cands)"))
def candidate_semi(spark, d):
    return artifacts(spark, d).members.join(candidate_blocks(spark, d).select("bid"), "bid", "left_semi").select("home").distinct()


@query(O.chain("select coalesce(a.kind, b.kind) as kind, a.n as in_queries, b.n as in_network from (select kind, count(*) as n from asked group by kind) a full outer join (select kind, count(*) as n from blocks group by kind) b on a.kind = b.kind"))
def kinds_full_outer(spark, d):
    a = artifacts(spark, d)
    asked = S.query_stats(a.stats, query_homes(a)).groupBy("kind").agg(F.count("*").alias("in_queries"))
    return asked.join(a.blocks.groupBy("kind").agg(F.count("*").alias("in_network")), "kind", "full_outer").select("kind", "in_queries", "in_network")


def _set_op(op: str):
    def run(spark, d):
        a = artifacts(spark, d)
        q = query_homes(a)
        one, two = R.ranked_search(a, q, P).select("qid", "home"), R.ranked_search(a, q, P.but(theta=1.0)).select("qid", "home")
        return getattr(one, op)(two)

    return run


_TOP = "select qid, home from (select qid, home, row_number() over (partition by qid order by d2, home) as r from placed where sim >= {}) where r <= 10"
for _op, _word in (("exceptAll", "except all"), ("intersect", "intersect")):
    _key = "answers_except" if _op == "exceptAll" else "answers_intersect"
    Q[_key] = _set_op(_op)
    SQL[_key] = O.chain(f"{_TOP.format(0.6)} {_word} {_TOP.format(1.0)}")


# -- events and embeddings --


@query("""
select p.event_id, p.user_id, arg_max(e.event_id, (e.ts, e.event_id)) as seen from events p join events e on e.user_id = p.user_id and e.event_type = 'view' and e.ts <= p.ts
where p.event_type = 'purchase' group by p.event_id, p.user_id
union all select event_id, user_id, -1 from events p where event_type = 'purchase' and not exists (select 1 from events e where e.user_id = p.user_id and e.event_type = 'view' and e.ts <= p.ts)""")
def event_vertex_asof(spark, d):
    """As-of: the last view of the user at each purchase, by one ordered pass over each user's events."""
    w = W.partitionBy("user_id").orderBy("ts", F.col("event_type") == "purchase", "event_id").rowsBetween(W.unboundedPreceding, 0)
    rows = table(spark, d, "events").filter("event_type in ('view', 'purchase')")
    rows = rows.withColumn("seen", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w))
    return rows.filter("event_type = 'purchase'").select("event_id", "user_id", F.coalesce("seen", F.lit(-1)).alias("seen"))


def _as_text(rows: DataFrame) -> DataFrame:
    return rows.withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss.SSSSSS"))


@query("select strftime(time_bucket(interval '1 day', ts, timestamp '1970-01-01'), '%Y-%m-%d %H:%M:%S.%f') as start, user_id, event_type, count(*) as cnt from events group by all")
def poi_tumbling(spark, d):
    return _as_text(E.poi_activity(table(spark, d, "events")))


@query("select strftime(time_bucket(interval '1 day', ts, timestamp '1970-01-01') - k * interval '1 day', '%Y-%m-%d %H:%M:%S.%f') as start, user_id, event_type, count(*) as cnt from events, (select unnest(range(7)) as k) group by all")
def poi_sliding(spark, d):
    return _as_text(E.poi_activity(table(spark, d, "events"), "7 days", "1 day"))


@query("""
select user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S.%f') as start, count(*) as cnt, arg_min(event_id, (ts, event_id)) as first_event, arg_max(event_id, (ts, event_id)) as last_event from (
  select *, sum(fresh) over (partition by user_id order by ts, event_id) as trip from (
    select *, coalesce((ts >= lag(ts) over (partition by user_id order by ts, event_id) + interval '12 hours')::int, 1) as fresh from events)) group by user_id, trip""")
def trip_sessions(spark, d):
    return _as_text(E.trips(table(spark, d, "events")))


@query("select v.event_id as v_id, p.event_id as p_id, v.user_id from events v join events p on v.user_id = p.user_id and p.ts >= v.ts and p.ts <= v.ts + interval '1 day' where v.event_type = 'view' and p.event_type = 'purchase'")
def views_then_purchases(spark, d):
    return E.views_then_purchases(table(spark, d, "events"))


@query("select event_type, sum(cast(json_extract(props, '$.k') as bigint))::bigint as k_sum, count(*) as n from events group by event_type")
def event_props_json(spark, d):
    rows = table(spark, d, "events").select("event_type", F.from_json("props", "k long")["k"].alias("k"))
    return rows.groupBy("event_type").agg(F.sum("k").alias("k_sum"), F.count("*").alias("n"))


@query("""
select vec_id, round(cos, 5) as cos from (
  select e.vec_id, list_sum(list_transform(list_zip(e.embedding, q.embedding), lambda x: x[1]::double * x[2]::double)) / sqrt(list_sum(list_transform(e.embedding, lambda x: x::double * x::double)) * list_sum(list_transform(q.embedding, lambda x: x::double * x::double))) as cos
  from embeddings e, (select embedding from embeddings where vec_id = 0) q) order by cos desc, vec_id limit 10""")
def embedding_cosine_topk(spark, d):
    rows = table(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("e"))
    q = F.array(*[F.lit(float(v)) for v in rows.filter("vec_id = 0").first()["e"]])
    return rows.select("vec_id", vectors.cosine(F.col("e"), q).alias("cos")).orderBy(F.desc("cos"), "vec_id").limit(10).withColumn("cos", F.round("cos", 5))


# -- measures over the parameter sweeps --

Q |= workloads.queries()


def _point_sql(name: str, value: float, **settings) -> str:
    """A row of a sweep on the lattice; the settings of the tables go into the chain, theta and k into the text."""
    theta, k = settings.get("theta", P.theta), 10 if name != "k" else value
    own = lambda sql: re.sub(r"\b0\.6\b", repr(float(theta)), sql).replace(">= 10 and", f">= {k} and").replace("rank <= 10", f"rank <= {k}")
    report, seen = own(_REPORT_SQL), own(_VISITS_SQL)
    chain = O.chain(f"select '{name}' as setting, {float(value)}::double as value, round(avg(total), 4) as total, round(avg(pruned_all), 4) as pruned_all, round(avg(pruned_nominated), 4) as pruned_nominated, round(avg(visited), 4) as visited, round(avg(answer), 4) as answer from ({report}) r join (select qid, sum(visited) as visited from ({seen}) group by qid) v on v.qid = r.qid", **settings)
    return own(chain)


for _name, _values in (("k", [(v, {}) for v in workloads.SWEEPS["k"]]), ("theta", [(v, {"theta": v}) for v in workloads.SWEEPS["theta"] + workloads.HIGH_THETA]), ("radius", [(v, {"radius": v}) for v in workloads.SWEEPS["radius"]]), ("degree", [(v, dict(zip(("keep", "diag"), workloads.LATTICE[v]))) for v in workloads.SWEEPS["degree"]])):
    SQL[f"sweep_{_name}"] = " union all ".join(f"select * from ({_point_sql(_name, v, **more)})" for v, more in _values)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(Q)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)


__all__ = ["disc_interval", "oracle_sql", "queries"]
