"""The offline part: network -> blocks -> communities -> statistics -> box tree, as written tables."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field
from functools import cached_property
from threading import RLock

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import blocks as B
from ..operators import boxtree, community
from ..operators.network import Network, attach_pois, components, edge_counts, generate_network, lattice_network
from ..params import SearchParams
from ..sources.tables import Cuts, sent, table

TABLES = ("vertices", "edges", "edge_poi", "blocks", "sides", "members", "stats", "bounds", "entries", "nodes", "wide")


@dataclass
class Artifacts:
    spark: SparkSession
    radius: int
    m: int
    vertices: DataFrame
    edges: DataFrame
    edge_poi: DataFrame
    blocks: DataFrame
    sides: DataFrame
    members: DataFrame
    stats: DataFrame
    bounds: DataFrame
    entries: DataFrame
    nodes: DataFrame
    wide: DataFrame
    connected: bool = False
    fanout: int = 16
    packing: str = "zorder"
    cut: Cuts | None = None
    shared: dict = field(default_factory=dict)  # of the network: artefacts for several radii have the same one

    def tables(self) -> dict[str, DataFrame]:
        return {t: getattr(self, t) for t in TABLES}

    def require(self, params: SearchParams) -> None:
        """Refuse settings that these tables weren't built for."""
        for name in ("radius", "connected", "fanout", "packing"):
            if getattr(self, name) != getattr(params, name) and (name in ("radius", "connected") or params.use_tree):
                raise ValueError(f"the artefacts were built for {name} {getattr(self, name)}, not {getattr(params, name)}")

    def pin(self) -> Artifacts:
        """Keep what a search reads in memory, as far as it fits; for sessions with many searches."""
        for name in ("wide", "nodes", "entries", "members", "vertices", "sides", "blocks"):
            setattr(self, name, getattr(self, name).persist())
            getattr(self, name).count()
        return self

    @cached_property
    def levels(self) -> int:
        """Levels of the box tree; 0 if it is empty."""
        top = self.nodes.agg(F.max("level")).first()[0]
        return 0 if top is None else top + 1

    @cached_property
    def top_counts(self) -> dict[int, int]:
        """The largest number of blocks of a kind in a community: a row for each kind."""
        rows = self.stats.groupBy("kind").agg(F.max("cnt").alias("n")).collect()
        return {r["kind"]: r["n"] for r in rows}

    @cached_property
    def extent(self) -> tuple[int, int, int, int, int]:
        """Least and largest x and y of the homes, and their number."""
        r = self.wide.agg(F.min("x"), F.min("y"), F.max("x"), F.max("y"), F.count("*")).first()
        return (r[0] or 0, r[1] or 0, r[2] or 0, r[3] or 0, r[4])


@dataclass
class Base:
    """A network and its blocks: what doesn't depend on the radius."""

    net: Network
    blocks: DataFrame
    sides: DataFrame
    cut: Cuts
    shared: dict = field(default_factory=dict)


def together(*runs) -> list:
    """Results of functions that run at the same time; the first error is raised."""
    with ThreadPoolExecutor(len(runs)) as pool:
        return [f.result() for f in [pool.submit(run) for run in runs]]


_LOCK = RLock()


def kept(store: dict, key, make):
    """What `make` gives, made once for a key of a store; who asks meanwhile waits for it."""
    with _LOCK:
        lock = store.setdefault(("lock", key), RLock())
    with lock:
        if key not in store:
            store[key] = make()
        return store[key]


def build_base(net: Network, max_sides: int, strategy: str = "auto") -> Base:
    cuts = Cuts(net.vertices.sparkSession)
    vertices, edges = cuts.cut(net.vertices, "vertices"), cuts.cut(net.edges, "edges")
    scratch, shared = cuts.scratch(), {}
    # walks and parts are one task each, the points many
    found, poi, _ = together(
        lambda: scratch.cut(B.detect_blocks(Network(vertices, edges, None, net.m), max_sides, scratch, strategy, places=True), "found"),
        lambda: cuts.cut(net.edge_poi, "edge_poi"),
        lambda: kept(shared, "parts", lambda: cuts.cut(components(vertices, edges, cuts), "parts")),
    )
    net = Network(vertices, edges, poi, net.m)
    blocks, sides = together(lambda: cuts.cut(B.describe_blocks(found, net), "blocks"), lambda: cuts.cut(B.block_sides(found, vertices), "sides"))
    scratch.close()
    return Base(net, blocks, sides, cuts, shared)


def wide_table(base: Base, members: DataFrame, stats: DataFrame, bounds: DataFrame) -> DataFrame:
    """One row a home: place, map from kind to statistics, the blocks it holds, a digest of that set; in order of place.

    A search reads rows near it by the ranges of x and y in the files' footers, and scores a
    row without a shuffle.
    """
    entry = F.struct("kind", F.struct("cnt", "usum", "umax", "csum", "cmax").alias("s"))
    kinds = stats.groupBy("home").agg(F.map_from_entries(F.collect_list(entry)).alias("kinds"))
    rows = members.join(base.blocks.select("bid", "kind", "vec", "uvec"), "bid").join(bounds.select("bid", "max_cnt"), "bid")
    held = rows.groupBy("home").agg(F.collect_list(F.struct("kind", "vec", "uvec", "max_cnt")).alias("held"), F.md5(F.array_join(F.array_sort(F.collect_list("bid")).cast("array<string>"), ",").cast("binary")).alias("set_key"))
    at = base.net.vertices.withColumnRenamed("vid", "home")
    return kinds.join(held, "home").join(at, "home").repartitionByRange("x", "y").sortWithinPartitions("x", "y")


def square_table(base: Base, bounds: DataFrame, r: int) -> DataFrame:
    """The same, and the ids of the blocks, for communities by radius: made square by square, so neither members nor statistics are shuffled."""
    rows = community.square_homes(base.net.vertices, base.sides, base.blocks, bounds, r, base.net.m)
    return rows.select("home", "kinds", "held", F.md5(F.array_join(F.col("bids").cast("array<string>"), ",").cast("binary")).alias("set_key"), "x", "y", "bids")


def build_artifacts(net: Network | Base, params: SearchParams) -> Artifacts:
    """All offline tables of a network; each is written once in the shared folder."""
    base = net if isinstance(net, Base) else build_base(net, params.max_sides)
    net, cuts, blocks = base.net, base.cut, base.blocks
    scratch = cuts.scratch()
    if params.connected:
        members = community.members_grid(net.vertices, base.sides, params.radius)
        members = cuts.cut(community.connected_members(cuts.cut(members, "members"), blocks, scratch), "connected")
        stats = cuts.cut(community.community_stats(members, blocks, net.m), "stats")
        bounds = cuts.cut(community.block_count_bounds(members, blocks), "bounds")
        homes = lambda: cuts.cut(wide_table(base, members, stats, bounds), "wide")
    else:
        bounds = cuts.cut(community.square_bounds(net.vertices, base.sides, params.radius, net.m), "bounds")
        homes = lambda: cuts.cut(square_table(base, bounds, params.radius), "wide")

    def tree():
        leaves = boxtree.leaf_codes(blocks, packing=params.packing, fanout=params.fanout)
        block = F.struct("kind", "vec", "uvec", F.coalesce("max_cnt", F.lit(0)).alias("max_cnt"), F.coalesce("min_cnt", F.lit(0)).alias("min_cnt"), "xmin", "ymin", "xmax", "ymax")
        entries = cuts.cut(blocks.join(leaves, "bid").join(bounds, "bid", "left").select("node_id", "bid", block.alias("block")), "entries")
        return entries, cuts.cut(boxtree.build_tree(entries, net.m, scratch, params.fanout_bits), "nodes")

    wide, (entries, nodes) = together(homes, tree)
    scratch.close()
    if not params.connected:  # read from the wide table, which has all of them
        members = wide.select("home", F.explode("bids").alias("bid"))
        stats = wide.select("home", F.explode("kinds").alias("kind", "s")).select("home", "kind", "s.*")
    return Artifacts(net.vertices.sparkSession, params.radius, net.m, net.vertices, net.edges, net.edge_poi, blocks, base.sides, members, stats, bounds, entries, nodes, wide, params.connected, params.fanout, params.packing, cuts, base.shared)


def net_a(spark: SparkSession, sf_dir: str, keep: int = 75, diag: int = 10) -> Network:
    """Customers as vertices, orders as points of five types."""
    net = lattice_network(table(spark, sf_dir, "customer"), "c_custkey", keep, diag)
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("poi_id"), F.col("o_custkey").alias("vid"), F.col("o_orderkey").alias("pick"), (F.substring("o_orderpriority", 1, 1).cast("int") - 1).alias("poi_type"))
    net.edge_poi, net.m = edge_counts(attach_pois(net.edges, orders)), 5
    return net


#: Types of points in dense vectors; more raise an error.
MOST_TYPES = 1000


def net_b(spark: SparkSession, sf_dir: str, column: str = "p_brand", vertices: int | None = None, keep: int = 75, diag: int = 10) -> Network:
    """Orders as vertices, line items as points typed by their part."""
    orders = table(spark, sf_dir, "orders")
    if vertices is not None:
        orders = orders.filter(F.col("o_orderkey") < vertices)
    net = lattice_network(orders, "o_orderkey", keep, diag)
    part = table(spark, sf_dir, "part").select("p_partkey", column)
    names = part.select(column).distinct().orderBy(column).collect()  # a dictionary column; vectors have an element a name
    if len(names) > MOST_TYPES:
        raise ValueError(f"{column} has {len(names)} names; dense vectors are for {MOST_TYPES} types at most, see edge_maps")
    number = spark.createDataFrame([(r[0], i) for i, r in enumerate(names)], "_name string, poi_type int")
    part = part.join(sent(number, len(names)), F.col(column).eqNullSafe(F.col("_name"))).drop("_name")
    items = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_linenumber").join(part, F.col("l_partkey") == F.col("p_partkey"))
    pois = items.select(F.lit(None).cast("long").alias("poi_id"), F.col("l_orderkey").alias("vid"), (F.col("l_partkey") + F.col("l_linenumber")).alias("pick"), "poi_type")
    net.edge_poi, net.m = edge_counts(attach_pois(net.edges, pois)), len(names)
    return net


def net_d(spark: SparkSession, sf_dir: str, dist: str, degree: int = 3, deg_max: int | None = None, vertices: int | None = None, source: str = "customer", seed: int = 0) -> Network:
    """Generated positions from the keys of `customer` or `orders`, a degree from `degree` to `deg_max` each; points as in net_a and net_b (five order priorities, five line numbers)."""
    key, cluster = ("c_custkey", "c_nationkey") if source == "customer" else ("o_orderkey", "o_custkey")
    keys = table(spark, sf_dir, source)
    if vertices is not None:
        keys = keys.filter(F.col(key) < vertices)
    if source == "orders":
        keys = keys.withColumn("o_custkey", F.col("o_custkey") % 25)
    net = generate_network(keys, key, dist, degree, cluster, deg_max=deg_max, seed=seed)
    if source == "customer":
        pois = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("poi_id"), F.col("o_custkey").alias("vid"), F.col("o_orderkey").alias("pick"), (F.substring("o_orderpriority", 1, 1).cast("int") - 1).alias("poi_type"))
    else:
        pois = table(spark, sf_dir, "lineitem").select(F.lit(None).cast("long").alias("poi_id"), F.col("l_orderkey").alias("vid"), (F.col("l_partkey") + F.col("l_linenumber")).alias("pick"), ((F.col("l_linenumber") - 1) % 5).cast("int").alias("poi_type"))
    net.edge_poi, net.m = edge_counts(attach_pois(net.edges, pois)), 5
    return net


NETWORKS = {"a": net_a, "b": net_b, "d": net_d}
_BASES: dict[tuple, Base] = {}
_BUILT: dict[tuple, Artifacts] = {}


def base_of(spark: SparkSession, sf_dir: str, kind: str = "a", params: SearchParams = SearchParams(), **options) -> Base:
    """A named network and its blocks, built once for a session, folder and every setting they depend on."""
    key = (spark.sparkContext.applicationId, sf_dir, kind, params.max_sides, tuple(sorted(options.items())))
    return kept(_BASES, key, lambda: build_base(NETWORKS[kind](spark, sf_dir, **options), params.max_sides))


def artifacts(spark: SparkSession, sf_dir: str, kind: str = "a", params: SearchParams = SearchParams(), **options) -> Artifacts:
    """Artefacts of a named network, built once for a session, folder and every setting they depend on; radii share the network's blocks."""
    key = (spark.sparkContext.applicationId, sf_dir, kind, params.max_sides, tuple(sorted(options.items())), params.radius, params.connected, params.fanout, params.packing)
    return kept(_BUILT, key, lambda: build_artifacts(base_of(spark, sf_dir, kind, params, **options), params))


def query_homes(art: Artifacts, n: int = 15, most: int = 2147483647) -> DataFrame:
    """qid, home, qx, qy: of the network's largest connected part (ties: the one with the smallest vertex), the n vertices that a hash puts first."""
    from ..functions.geometry import spread

    def centres():
        part = kept(art.shared, "parts", lambda: art.cut.cut(components(art.vertices, art.edges, art.cut), "parts"))
        giant = part.groupBy("comp").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "comp").limit(1)
        rows = part.join(F.broadcast(giant.select("comp")), "comp").join(art.wide.select(F.col("home").alias("vid"), "x", "y"), "vid")
        rows = rows.withColumn("o", spread(F.col("vid"), 99, most)).orderBy("o", "vid").limit(n).collect()
        return [(i, r["vid"], r["x"], r["y"]) for i, r in enumerate(rows)]

    known = art.__dict__.setdefault("_centres", {})
    return art.spark.createDataFrame(kept(known, (n, most), centres), "qid int, home long, qx long, qy long")
