"""Registered queries of the network joins and the SQL they must equal."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from netjoin.operators import baselines, measures, objects, partition, relational
from netjoin.operators.network import Network, swap_operands
from netjoin.plans import catalog_sql as sql
from netjoin.plans.joins import JoinReport, closest_pairs, distance_join, leaf_tables
from netjoin.plans.object_joins import closest_objects_by_parts
from netjoin.plans.schedule import cut_hierarchy, schedule_plan
from netjoin.plans.workloads import BOUND_LEAVES, SWEEPS, THETAS, prepare, prepared_network, prepared_tree
from netjoin.sources import networks
from netjoin.sources.tables import load
from netjoin.streaming.positions import positions_of

Query = Callable[[SparkSession, str], DataFrame]
NAMES = {"urban": 400, "interstate": 400, "lines": 2000, "mesh": 6000}


def _edges(name: str) -> Query:
    return lambda spark, d: networks.NETWORKS[name](spark, d).edges.select("src", "dst", "w")


def degree_profile(spark: SparkSession, d: str) -> DataFrame:
    return prepared_network(spark, d, "urban").arcs.groupBy("a").agg(F.count(F.lit(1)).alias("degree")).groupBy("degree").agg(F.count(F.lit(1)).alias("n"))


def weight_quantiles(spark: SparkSession, d: str) -> DataFrame:
    q = prepared_network(spark, d, "urban").edges.agg(F.min("w").alias("least"), F.percentile("w", F.lit(0.5)).alias("median"), F.max("w").alias("most"), F.count(F.lit(1)).alias("n"))
    return q.select("least", F.col("median").cast("double"), "most", "n")


def _hash_sets(spark: SparkSession, d: str) -> DataFrame:
    r, s = networks.hash_sets(prepared_network(spark, d, "urban"), 8, 8)
    return r.select("id", F.lit("r").alias("role")).unionByName(s.select("id", F.lit("s").alias("role")))


def _attr_sets(spark: SparkSession, d: str) -> DataFrame:
    r, s = networks.attribute_sets(spark, d, "lines")
    return r.select("id", F.lit("r").alias("role")).unionByName(s.select("id", F.lit("s").alias("role")))


def _disjoint(spark: SparkSession, d: str) -> DataFrame:
    r, s = networks.hash_sets(prepared_network(spark, d, "interstate"), 50, 50)
    return r.intersect(s).agg(F.count(F.lit(1)).alias("shared"))


def _dj(name: str, theta: int, **options) -> Query:
    def run(spark, d):
        p = prepare(spark, d, name)
        return distance_join(p.net, p.r, p.s, theta, hierarchy=p.tree, **options)

    return run


def dj_directed_lines(spark: SparkSession, d: str) -> DataFrame:
    net = networks.event_lines(spark, d, directed=True)
    r, s = networks.hash_sets(net, 8, 8)
    return distance_join(net, r, s, 1000)


def dj_trade(spark: SparkSession, d: str) -> DataFrame:
    net = prepared_network(spark, d, "trade")
    r, s = networks.hash_sets(net, 8, 8)
    return distance_join(net, r, s, 3, hierarchy=prepared_tree(spark, d, "trade", leaves=2))


def dj_swapped(spark: SparkSession, d: str) -> DataFrame:
    """S before R on an undirected network, turned round again: the same pairs."""
    p = prepare(spark, d, "interstate")
    return swap_operands(distance_join(p.net, p.s, p.r, 200, hierarchy=p.tree))


def _kcp(name: str, k: int = 80, r: int = 8, s: int = 8, alpha: float = 0.5, theta: int | None = None, leaves: int | None = 16, **options) -> Query:
    def run(spark, d):
        p = prepare(spark, d, name, r=r, s=s, alpha=alpha, leaves=leaves)
        return closest_pairs(p.net, p.r, p.s, k, theta, hierarchy=p.tree, **options)

    return run


def _kcp_parallel(n: int, name: str = "urban") -> Query:
    def run(spark, d):
        p = prepare(spark, d, name)
        return closest_pairs(p.net, p.r, p.s, 80, hierarchy=cut_hierarchy(p.tree, p.net, n), parallelism=n, schedule="pool")

    return run


def kcp_attr(spark: SparkSession, d: str) -> DataFrame:
    net = prepared_network(spark, d, "lines")
    return closest_pairs(net, *networks.attribute_sets(spark, d, "lines"), 80, hierarchy=prepared_tree(spark, d, "lines"))


def kcp_trajectory(spark: SparkSession, d: str) -> DataFrame:
    """Closest points of two trajectories: the lines of the two users with the most events."""
    net = prepared_network(spark, d, "lines")
    e = load(spark, d, "events").select(F.col("event_id").alias("id"), "user_id")
    users = [r["user_id"] for r in e.groupBy("user_id").count().orderBy(F.desc("count"), "user_id").limit(2).collect()]
    return closest_pairs(net, e.where(F.col("user_id") == users[0]).select("id"), e.where(F.col("user_id") == users[1]).select("id"), 10, 20000, hierarchy=prepared_tree(spark, d, "lines"))


def _given(spark: SparkSession, d: str, leaves: int = 2):
    """Lines cut at equal spans of the event ids: an assignment that SQL can repeat."""
    net = prepared_network(spark, d, "lines")
    n = net.vertices.agg(F.max("id")).first()[0] + 1
    tree = partition.from_assignment(net, net.vertices.select("id", (leaves + F.floor(F.col("id") * leaves / n)).cast("long").alias("gp")))
    return net, tree, *networks.hash_sets(net, 8, 8)


def given_cross(spark, d):
    return _given(spark, d)[1].cross.select("gp", "a", "b", "w", "a_side")


def given_border(spark, d):
    return _given(spark, d)[1].border


def given_routes(spark, d):
    net, tree, r, s = _given(spark, d)
    return leaf_tables(net, tree, r, s, 1000).where("kind = 'route'").select("gp", F.col("x").alias("u"), F.col("y").alias("border"), "d")


def _given_pairs(mode: str) -> Query:
    def run(spark, d):
        net, tree, r, s = _given(spark, d)
        return distance_join(net, r, s, 1000, hierarchy=tree, crossings=mode)

    return run


def mst_mesh(spark, d):
    return partition.spanning_forest(prepared_network(spark, d, "mesh")).agg(F.count(F.lit(1)).alias("n_edges"), F.sum("w").alias("weight"))


def bisect_sep_urban(spark, d):
    """Separation of the unsmoothed split of the grid between its first and its last order, by growth."""
    net = prepared_network(spark, d, "urban")
    low, high = net.vertices.agg(F.min("id"), F.max("id")).first()
    tree = partition.build_hierarchy(net, leaves=2, explicit={1: (low, high)})
    return measures.separation(tree).select("sep")


def bisect_sep_forest(spark, d):
    """The same separation on the mesh by spanning forests alone."""
    net = prepared_network(spark, d, "mesh")
    side = partition.bisect_forest(net, *net.vertices.agg(F.min("id"), F.max("id")).first())
    cut = net.edges.join(side.toDF("src", "s1"), "src").join(side.toDF("dst", "s2"), "dst").where("s1 <> s2")
    return cut.agg(F.min("w").alias("sep"))


def bisect_alpha(spark, d):
    out = None
    for alpha in SWEEPS["alpha"]:
        one = measures.imbalance(prepared_tree(spark, d, "urban", alpha=alpha)).withColumn("alpha", F.lit(alpha))
        out = one if out is None else out.unionByName(one)
    return out


def _seeds(how: str) -> Query:
    def run(spark, d):
        return prepared_tree(spark, d, "mesh", leaves=4, seeds=how).nodes.where("seed_l IS NOT NULL").select("gp", "seed_l", "seed_r", "sep")

    return run


def euclid(spark, d):
    points = load(spark, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("e"))
    return baselines.euclid_pairs(points, *networks.hash_sets(Network(points.select("id"), points), 8, 8), 80, 100_000)


def _cut_of(net, at) -> DataFrame:
    """n_cut, cut_weight, largest: edges between parts, their weight, and the largest part over the mean."""
    ends = net.edges.join(at.toDF("src", "g1"), "src").join(at.toDF("dst", "g2"), "dst").where("g1 <> g2")
    size = at.groupBy("gp").agg(F.count(F.lit(1)).alias("n")).agg((F.max("n") / F.avg("n")).alias("largest"))
    return ends.agg(F.count(F.lit(1)).alias("n_cut"), F.sum("w").alias("cut_weight"), F.min("w").alias("sep")).join(size)


def balanced_cut(spark, d):
    """Parts by label propagation under a capacity: their edge cut."""
    net = prepared_network(spark, d, "mesh")
    return _cut_of(net, partition.balanced_assign(net, 4, objective="cut"))


def balanced_hash(spark, d):
    """Parts of equal size by bands of the operand hash: their edge cut."""
    net = prepared_network(spark, d, "urban")
    return _cut_of(net, partition.balanced_assign(net, 4, objective="size"))


def recall_modes(spark, d):
    """Recall, exact-distance share and stretch of every crossing mode on the lines cut in two, theta 1000."""
    net, tree, r, s = _given(spark, d)
    exact, out = distance_join(net, r, s, 1000), None
    for mode in ("none", "one", "per_level", "closure"):
        report = JoinReport()
        answer = distance_join(net, r, s, 1000, hierarchy=tree, crossings=mode, report=report)
        one = measures.recall_report(answer, exact).withColumn("crossings", F.lit(mode)).withColumn("certified", F.lit(report.certified))
        out = one if out is None else out.unionByName(one)
    return out.withColumn("mean_stretch", F.round("mean_stretch", 9))


def work_counters(spark, d):
    """Work of every crossing mode, and without route reuse and the early stop, for theta 1500 over 16 leaves."""
    p, rows = prepare(spark, d, "urban"), []
    for mode in ("none", "one", "per_level", "closure"):
        for name, options in (("full", {}), ("no_reuse", {"reuse_routes": False}), ("no_stop", {"stop_by_weight": False})):
            if mode == "none" and options:
                continue
            report = JoinReport()
            n = distance_join(p.net, p.r, p.s, 1500, hierarchy=p.tree, crossings=mode, report=report, **options).count()
            rows.append((mode, name, n, report.settled, report.relaxed, report.bridges_live, report.bridges_pruned))
    return spark.createDataFrame(rows, "crossings string, options string, n_pairs long, settled long, relaxed long, bridges_live long, bridges_pruned long")


def bound_trace(spark, d):
    """The bound after every wave, for each policy."""
    p, rows = prepare(spark, d, "urban"), []
    for threshold in ("pilot+wave", "wave", "local"):
        report = JoinReport()
        closest_pairs(p.net, p.r, p.s, 80, hierarchy=p.tree, crossings="per_level", threshold=threshold, report=report).count()
        rows += [(threshold, i, bound, report.refreshes, report.pruned) for i, bound in enumerate(report.trace)]
    return spark.createDataFrame(rows, "threshold string, wave long, bound long, refreshes long, pruned long")


def hierarchy_nodes(spark, d):
    return _given(spark, d, 8)[1].nodes.select("gp", "parent", "side", "level", "height", "n_vertices", "n_edges", "sep", "leaf")


def idle_slots(spark, d):
    """Idle slot share of the schedule if a part costs its vertices."""
    tree = _given(spark, d, 8)[1]
    return measures.idle_share(schedule_plan(tree, 3), tree.nodes.select("gp", F.col("n_vertices").alias("cost")), 3)


def _objects(spark, d):
    net = networks.urban_grid(spark, d)
    n = net.vertices.count()
    now = objects.latest_positions(positions_of(load(spark, d, "events"), net.edges, n))
    return net, now, now.where("kind = 'r'"), now.where("kind = 's'")


def objects_latest(spark, d):
    net, now, *_ = _objects(spark, d)
    return now.join(net.edges, "eid").select("oid", "src", "dst", "off", "kind")


def objects_closest(spark, d):
    net, _, r, s = _objects(spark, d)
    return objects.closest_objects(net, r, s, 40, 1000)


def objects_embedded(spark, d):
    net, _, r, s = _objects(spark, d)
    return objects.closest_embedded(net, r, s, 40, 1000)


def objects_by_parts(spark, d):
    """Objects through the partitioned join."""
    net, _, r, s = _objects(spark, d)
    return closest_objects_by_parts(net, r, s, 40, 1000, prepared_tree(spark, d, "urban"))


def _pairs(spark, d):
    p = prepare(spark, d, "interstate")
    return distance_join(p.net, p.r, p.s, 100, hierarchy=p.tree)


def _geo(spark, d):
    o, c, n, r = (load(spark, d, t) for t in ("orders", "customer", "nation", "region"))
    return (o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))
            .select(F.col("o_orderkey").alias("id"), "r_name", "n_name"))


def rollup_pairs_by_region(spark, d):
    return relational.rollup_pairs(_pairs(spark, d), _geo(spark, d), "r_name", "n_name")


def cube_gp_pairs(spark, d):
    bands = prepared_network(spark, d, "interstate").vertices.select("id", F.pmod("id", F.lit(4)).alias("gp"))
    return relational.cube_pairs(_pairs(spark, d), bands)


def grouping_sets_pairs(spark, d):
    _pairs(spark, d).createOrReplaceTempView("near_pairs")
    return spark.sql("SELECT u % 3 AS ub, v % 3 AS vb, grouping_id(u % 3, v % 3) AS g, count(*) AS n FROM near_pairs GROUP BY GROUPING SETS ((u % 3), (v % 3), ())").withColumn("g", F.col("g").cast("long"))


def knn_per_u(spark, d):
    return relational.nearest_per_source(_pairs(spark, d), 2).select("u", "v", "d", F.col("rank").cast("long").alias("rank"))


def asof_position(spark, d):
    e = load(spark, d, "events")
    return relational.as_of(e.where("event_type = 'purchase'").select("user_id", "ts", "event_id"), e.where("event_type = 'view'").select("user_id", "ts", F.col("event_id").alias("seen")), "user_id", "seen").select("event_id", "seen")


def interval_meetings(spark, d):
    e = load(spark, d, "events")
    return relational.meetings(e.where("event_type = 'view'"), e.where("event_type = 'purchase'"), 2)


def session_positions(spark, d):
    return relational.sessions(load(spark, d, "events"), 24 * 60)


def json_props(spark, d):
    return load(spark, d, "events").select(F.from_json("props", "k long").getField("k").alias("k")).groupBy("k").agg(F.count(F.lit(1)).alias("n"))


def set_ops_pairs(spark, d):
    p = prepare(spark, d, "interstate")
    wide, near = (distance_join(p.net, p.r, p.s, t, hierarchy=p.tree) for t in (150, 100))
    return wide.exceptAll(near).unionByName(wide.intersect(near.where("d <= 10")))


def sql_table_function(spark, d):
    """Leaf pairs through SQL over a table function that runs one leaf for each partition."""
    from netjoin.plans.table_functions import register

    register(spark)
    net, tree, r, s = _given(spark, d)
    null = F.lit(None).cast("long")
    rows = tree.arcs.select("gp", F.lit("arc").alias("role"), "a", "b", "w")
    for role, ids in (("r", r), ("s", s)):
        rows = rows.unionByName(tree.assign.join(ids, "id", "left_semi").select("gp", F.lit(role).alias("role"), F.col("id").alias("a"), null.alias("b"), null.alias("w")))
    rows.createOrReplaceTempView("leaf_rows")
    return spark.sql("SELECT u, v, d FROM leaf_pairs(TABLE(leaf_rows) PARTITION BY (gp), 1000)")


def ranked(spark, d):
    return relational.ranked_pairs(_pairs(spark, d))


def chains(spark, d):
    """Running value of every user's events."""
    return relational.chain_lengths(load(spark, d, "events").select(F.col("user_id").alias("chain"), F.col("event_id").alias("pos"), F.floor(F.abs("value")).cast("long").alias("w")))


def pivot_events(spark, d):
    return relational.pivot_counts(load(spark, d, "events"), "user_id", "event_type", ["view", "purchase"])


def queries() -> dict[str, Query]:
    q: dict[str, Query] = {f"net_{n}_edges": _edges(n) for n in networks.NETWORKS}
    q |= {"net_degree_profile": degree_profile, "net_weight_quantiles": weight_quantiles, "ops_hash_sets": _hash_sets, "ops_attr_sets": _attr_sets, "ops_disjoint_check": _disjoint}
    q |= {f"dj_{n}": _dj(n, t) for n, t in NAMES.items()}
    q |= {"dj_directed_lines": dj_directed_lines, "dj_trade": dj_trade, "dj_swapped": dj_swapped, "dj_frontier": _dj("interstate", 200, engine="frontier"), "dj_urban_800": _dj("urban", 800)}
    q |= {f"kcp_{n}": _kcp(n) for n in NAMES}
    q |= {"kcp_theta": _kcp("urban", theta=100), "kcp_attr": kcp_attr, "kcp_trajectory": kcp_trajectory}
    q |= {f"dj_{n}_theta_{t}": _dj(n, t) for n, ts in THETAS.items() for t in ts}
    for prefix, n in (("kcp", "urban"), ("kcp_interstate", "interstate")):
        q |= {f"{prefix}_alpha_{int(a * 100)}": _kcp(n, alpha=a) for a in SWEEPS["alpha"]}
        q |= {f"{prefix}_p_{p}": _kcp_parallel(p, n) for p in SWEEPS["parallelism"]}
        q |= {f"{prefix}_k_{k}": _kcp(n, k=k) for k in SWEEPS["k"]}
        q |= {f"{prefix}_r_{p}": _kcp(n, r=p) for p in SWEEPS["r"]} | {f"{prefix}_s_{p}": _kcp(n, s=p) for p in SWEEPS["s"]}
    q |= {f"kcp_bound_{name}_{n}": _kcp("urban", leaves=n, threshold=t) for n in BOUND_LEAVES for name, t in (("local", "local"), ("shared", "wave"))}
    q |= {"kcp_p_1": _kcp_parallel(1), "kcp_local_bound": _kcp("urban", threshold="local"), "kcp_auto_bound": _kcp("urban", threshold="auto"), "kcp_auto_bound_2": _kcp("urban", threshold="auto", leaves=2), "kcp_pool": _kcp("urban", schedule="pool"), "kcp_frontier": _kcp("urban", engine="frontier"),
          "kcp_task": _kcp("urban", engine="task"), "kcp_per_level": _kcp("urban", crossings="per_level"), "kcp_interstate_per_level": _kcp("interstate", crossings="per_level"), "kcp_per_level_pool": _kcp("urban", crossings="per_level", schedule="pool", parallelism=3),
          "kcp_unbounded_k": _kcp("urban", k=None, theta=200), "kcp_many": _kcp("mesh", k=2000, theta=6000), "kcp_mesh_frontier": _kcp("mesh", engine="frontier")}
    for option, name in (("reuse_routes", "no_reuse"), ("stop_by_weight", "no_stop")):
        q |= {f"kcp_{name}": _kcp("mesh", **{option: False}), f"dj_{name}_one": _dj("urban", 1000, crossings="one", **{option: False}), f"dj_{name}_per_level": _dj("urban", 1000, crossings="per_level", **{option: False})}
    q |= {"mst_mesh": mst_mesh, "bisect_sep_urban": bisect_sep_urban, "bisect_sep_forest": bisect_sep_forest, "given_cross": given_cross, "given_border": given_border, "given_routes": given_routes, "given_local_pairs": _given_pairs("none"),
          "given_one_cross": _given_pairs("one"), "given_per_level": _given_pairs("per_level"), "given_closure": _given_pairs("closure"), "given_table_function": sql_table_function, "bisect_alpha": bisect_alpha,
          "hierarchy_nodes": hierarchy_nodes, "hierarchy_schedule": lambda s, d: schedule_plan(_given(s, d, 8)[1], 3), "hierarchy_borders": lambda s, d: measures.border_profile(_given(s, d, 8)[1]),
          "hierarchy_balance": lambda s, d: measures.split_balance(_given(s, d, 8)[1])}
    q |= {f"seeds_{h}": _seeds(h) for h in ("double_sweep", "random", "best_of", "longest_tree_edge")}
    q |= {"naive_pairs": _kcp("interstate", leaves=None), "euclid_pairs": euclid, "all_pairs_mesh": lambda s, d: baselines.all_pairs(prepared_network(s, d, "mesh"), 3500),
          "all_pairs_recursive": lambda s, d: baselines.all_pairs_recursive(prepared_network(s, d, "mesh"), 3500), "balanced_assign_cut": balanced_cut, "balanced_hash_cut": balanced_hash}
    q |= {"recall_modes": recall_modes, "imbalance": lambda s, d: measures.imbalance(_given(s, d, 8)[1]), "work_counters": work_counters, "bound_trace": bound_trace, "idle_slots": idle_slots}
    q |= {f.__name__: f for f in (objects_latest, objects_closest, objects_embedded, objects_by_parts, rollup_pairs_by_region, cube_gp_pairs, grouping_sets_pairs, knn_per_u, asof_position, interval_meetings, session_positions, json_props, set_ops_pairs)}
    q |= {"ranked_pairs": ranked, "pairs_nearby": lambda s, d: relational.pairs_nearby(_pairs(s, d), 10), "chain_lengths": chains, "pivot_events": pivot_events, "paged_pairs": lambda s, d: relational.page_of(_pairs(s, d), 1, 10)}
    return q | {"page_links": networks.page_links}


def oracle_sql() -> dict[str, str]:
    return sql.oracles(NAMES, SWEEPS, THETAS, BOUND_LEAVES)
