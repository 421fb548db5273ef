import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from netjoin.operators import kernels, measures, partition
from netjoin.operators.components import connected_components
from netjoin.operators.network import make_network, scale_weight, swap_operands
from netjoin.operators.relax import distances_from, relax
from netjoin.plans import joins
from netjoin.plans.joins import JoinReport, closest_pairs, distance_join
from netjoin.plans.schedule import cut_hierarchy, schedule_plan
from tests import reference

import numpy as np

# detour: 1 and 2 share a part but are closest over 3; zigzag crosses three times
DETOUR = [(1, 2, 100), (1, 3, 10), (3, 2, 10), (3, 4, 5)]
ZIGZAG = [(1, 11, 3), (11, 2, 3), (2, 12, 3), (1, 2, 50), (11, 12, 60)]


def net_of(spark, edges, directed=False, vertices=None):
    links = spark.createDataFrame(edges, "src long, dst long, w long")
    return make_network(links, spark.createDataFrame([(v,) for v in vertices], "id long") if vertices else None, directed=directed)


def ids(spark, values):
    return spark.createDataFrame([(v,) for v in values], "id long")


def rows(df):
    return [tuple(r) for r in df.select("u", "v", "d").orderBy("d", "u", "v").collect()]


def random_edges(n, m, seed):
    r = random.Random(seed)
    out = {}
    for i in range(1, n):
        j = r.randrange(i)
        out[(j, i)] = r.randint(1, 60)
    for _ in range(m):
        a, b = sorted(r.sample(range(n), 2))
        out.setdefault((a, b), r.randint(1, 60))
    return [(a, b, w) for (a, b), w in out.items()]


@pytest.fixture(scope="module")
def world(spark):
    edges = random_edges(80, 45, 3)
    r, s = set(range(0, 80, 6)), set(range(3, 80, 7)) - set(range(0, 80, 6))
    net = net_of(spark, edges)
    return edges, net, ids(spark, r), ids(spark, s), r, s, partition.build_hierarchy(net, leaves=4, alpha=0.5)


def test_validation(spark):
    net = net_of(spark, [(1, 2, 5), (2, 1, 3), (1, 1, 4)])
    assert [tuple(r) for r in net.edges.select("src", "dst", "w").collect()] == [(1, 2, 3)]
    with pytest.raises(Exception, match="at least 1"):
        net_of(spark, [(1, 2, 0)]).edges.collect()
    with pytest.raises(ValueError):
        distance_join(net, ids(spark, [1]), ids(spark, [1, 2]), 5)
    with pytest.raises(ValueError):
        closest_pairs(net, ids(spark, [1]), ids(spark, [2]), None)
    assert scale_weight(spark.createDataFrame([(1, 2, 0.25)], "src long, dst long, w double"), 10).first()["w"] == 3


def test_unpartitioned_equals_sequential(spark, world):
    edges, net, r, s, rs, ss, _ = world
    assert rows(distance_join(net, r, s, 60)) == reference.pairs(edges, rs, ss, 60)
    assert rows(closest_pairs(net, r, s, 15)) == reference.pairs(edges, rs, ss, k=15)


@pytest.mark.parametrize("options", [{}, {"engine": "frontier"}, {"schedule": "pool", "parallelism": 2}])
def test_closure_is_exact(spark, world, options):
    edges, net, r, s, rs, ss, tree = world
    assert rows(distance_join(net, r, s, 70, hierarchy=tree, **options)) == reference.pairs(edges, rs, ss, 70)
    assert rows(closest_pairs(net, r, s, 20, hierarchy=tree, **options)) == reference.pairs(edges, rs, ss, k=20)


@pytest.mark.parametrize("threshold", ["wave", "pilot+wave", "local", "auto"])
def test_bounds_never_change_the_answer(spark, world, threshold):
    edges, net, r, s, rs, ss, tree = world
    report = JoinReport()
    got = closest_pairs(net, r, s, 12, 90, hierarchy=tree, threshold=threshold, report=report)
    want = reference.pairs(edges, rs, ss, 90, 12)
    assert rows(got) == want
    assert report.trace == sorted(report.trace, reverse=True) and report.trace[-1] >= want[-1][2]


def test_modes_nest_and_certify(spark, world):
    edges, net, r, s, rs, ss, tree = world
    exact, last = {(u, v): d for u, v, d in reference.pairs(edges, rs, ss, 80)}, None
    for mode in ("none", "one", "per_level", "closure"):
        report = JoinReport()
        got = {(u, v): d for u, v, d in rows(distance_join(net, r, s, 80, hierarchy=tree, crossings=mode, report=report))}
        assert all(d >= exact[p] for p, d in got.items() if p in exact) and set(got) <= set(exact)
        if last is not None:
            assert all(got[p] <= d for p, d in last.items())
        if report.certified:
            assert got == exact
        last = got
    assert last == exact
    sigma = tree.cross.agg(F.min("w")).first()[0]
    for mode in ("one", "per_level"):
        assert rows(distance_join(net, r, s, 2 * sigma - 1, hierarchy=tree, crossings=mode)) == reference.pairs(edges, rs, ss, 2 * sigma - 1)


@pytest.mark.parametrize("options", [{"sources_per_task": 2}, {"engine": "frontier"}, {"schedule": "pool", "parallelism": 2}, {"task_edges": 5}])
def test_per_level_equals_sequential(spark, options):
    """Three levels of merges against the sequential version, by every engine and schedule; parts beyond ``task_edges`` never meet a task."""
    edges = random_edges(70, 60, 21)
    net, r, s = net_of(spark, edges), set(range(0, 70, 5)), set(range(2, 70, 7)) - set(range(0, 70, 5))
    tree = partition.from_assignment(net, spark.createDataFrame([(i, 8 + i * 8 // 70) for i in range(70)], "id long, gp long"))
    report = JoinReport()
    got = rows(distance_join(net, ids(spark, r), ids(spark, s), 90, hierarchy=tree, crossings="per_level", report=report, **options))
    want = reference.per_level(edges, r, s, {i: 8 + i * 8 // 70 for i in range(70)}, 90)
    assert got == sorted(((u, v, d) for (u, v), d in want.items()), key=lambda x: (x[2], x[0], x[1]))
    if options.get("engine") == "frontier":
        assert not report.searches and report.settled > 0
    elif "task_edges" in options:
        assert all(w == 0 for w, *_ in report.searches)
    elif options.get("schedule") == "pool":
        assert all(len({s for w, s, *_ in report.searches if w == wave}) <= 2 for wave in range(4)) and 0 <= report.idle_share(2) < 1


def test_ablations_change_the_work_alone(spark, world):
    """Without route reuse the near side is searched twice, without the early stop every cross-edge is carried along, in every mode."""
    _, net, r, s, *_, tree = world
    for mode in ("one", "per_level", "closure"):
        seen = {}
        for name, options in (("full", {}), ("reuse", {"reuse_routes": False}), ("stop", {"stop_by_weight": False})):
            report = JoinReport()
            seen[name] = rows(distance_join(net, r, s, 40, hierarchy=tree, crossings=mode, report=report, **options)), report
        assert seen["full"][0] == seen["reuse"][0] == seen["stop"][0]
        assert seen["reuse"][1].settled > seen["full"][1].settled
        assert seen["stop"][1].bridges_live > seen["full"][1].bridges_live and seen["stop"][1].bridges_pruned == 0 < seen["full"][1].bridges_pruned
        assert seen["stop"][1].relaxed > seen["full"][1].relaxed
    for options in ({"reuse_routes": False}, {"stop_by_weight": False}):
        with pytest.raises(ValueError, match="hierarchy"):
            distance_join(net, r, s, 40, **options)
        with pytest.raises(ValueError, match="hierarchy"):
            distance_join(net, r, s, 40, hierarchy=tree, crossings="none", **options)
    for options in ({"engine": "x"}, {"crossings": "x"}, {"schedule": "x"}, {"threshold": "x"}, {"parallelism": 0}):
        with pytest.raises(ValueError):
            closest_pairs(net, r, s, 4, hierarchy=tree, **options)


def test_nothing_crosses_below_sigma(spark):
    """A bound below the lightest cross-edge ends the join with the leaves."""
    edges = [(i, i + 1, 2) for i in range(9)] + [(9, 10, 500)] + [(i, i + 1, 2) for i in range(10, 19)]
    net = net_of(spark, edges)
    tree = partition.build_hierarchy(net, leaves=2)
    report = JoinReport()
    got = rows(closest_pairs(net, ids(spark, range(0, 20, 2)), ids(spark, range(1, 20, 2)), 5, hierarchy=tree, report=report))
    assert got == reference.pairs(edges, range(0, 20, 2), set(range(1, 20, 2)), k=5)
    assert report.sigma == 500 and report.bridges_live + report.bridges_pruned == 0 and not report.rounds and len(report.searches) <= 2


def test_no_search_is_unlimited(spark):
    """Without a pilot the radius grows from the median weight: little is settled although no bound is known at first."""
    edges = [(i, i + 1, 3) for i in range(400)]
    net = net_of(spark, edges)
    tree = partition.build_hierarchy(net, leaves=4)
    for threshold in ("wave", "local"):
        report = JoinReport()
        got = closest_pairs(net, ids(spark, range(0, 400, 8)), ids(spark, range(4, 400, 8)), 6, hierarchy=tree, threshold=threshold, report=report)
        assert rows(got) == reference.pairs(edges, range(0, 400, 8), set(range(4, 400, 8)), k=6)
        assert report.limits[0] == 3 and report.trace[0] > 10**15 and report.settled < 50 * 40


def test_large_parts_are_split_by_joins(spark):
    """Parts beyond a task alone leave the task; the nodes say how each was split, and options that need a task raise."""
    edges = [(a, b, w) for (a, b, _), w in zip(random_edges(60, 40, 8), random.Random(1).sample(range(1, 900), 120))]
    net = net_of(spark, edges)
    for alpha, how in ((0.0, "forest"), (0.5, "coarse")):
        tree = partition.build_hierarchy(net, leaves=4, alpha=alpha, task_edges=60)
        by = {r["gp"]: r["method"] for r in tree.nodes.where("NOT leaf").collect()}
        assert by[1] == how and all(m == "task" for g, m in by.items() if tree.parts[g]["n_edges"] <= 60)
        assert tree.assign.count() == 60
    plain, joined = (partition.build_hierarchy(net, leaves=4, engine=e) for e in ("task", "joins"))
    assert {tuple(r) for r in plain.assign.select("id", "gp").collect()} == {tuple(r) for r in joined.assign.select("id", "gp").collect()}
    with pytest.raises(ValueError, match="inside tasks"):
        partition.build_hierarchy(net, leaves=2, seeds="random", task_edges=10)
    apart = net_of(spark, [(1, 2, 4), (2, 3, 1), (11, 12, 4), (12, 13, 2)])
    tree = partition.build_hierarchy(apart, leaves=2, attach="separate", engine="joins")
    assert tree.cross.count() == 0 and tree.parts[1]["method"] == "components"


def test_leaves_between_powers_of_two(spark, world):
    _, net, *_ = world
    for n in (1, 3, 5, 6):
        assert len(partition.build_hierarchy(net, leaves=n, alpha=0.5).leaves) == n


@pytest.mark.parametrize("edges, r, s, best", [(DETOUR, [1], [2], 20), (ZIGZAG, [1], [12], 9)])
def test_detours_need_closure(spark, edges, r, s, best):
    net = net_of(spark, edges)
    part = {v: 2 if v in (1, 2) else 3 for e in edges for v in e[:2]}
    tree = partition.from_assignment(net, spark.createDataFrame(list(part.items()), "id long, gp long"))
    closed = rows(distance_join(net, ids(spark, r), ids(spark, s), 200, hierarchy=tree))
    assert closed[0][2] == best
    report = JoinReport()
    level = rows(distance_join(net, ids(spark, r), ids(spark, s), 200, hierarchy=tree, crossings="per_level", report=report))
    assert (not level or level[0][2] > best) and not report.certified


def test_edge_cases(spark):
    islands = net_of(spark, [(1, 2, 4), (11, 12, 4)], vertices=[1, 2, 11, 12, 99])
    tree = partition.build_hierarchy(islands, leaves=4)
    assert tree.assign.count() == 5
    for t in (None, tree):
        assert rows(closest_pairs(islands, ids(spark, [1, 99]), ids(spark, [2, 12]), 10, hierarchy=t)) == [(1, 2, 4)]
        assert rows(distance_join(islands, ids(spark, []), ids(spark, [2]), 10, hierarchy=t)) == []
        assert rows(distance_join(islands, ids(spark, [1]), ids(spark, [2]), 0, hierarchy=t)) == []
    assert rows(closest_pairs(islands, ids(spark, [1]), ids(spark, [2]), 0)) == []
    ties = net_of(spark, [(0, i, 5) for i in range(1, 9)])
    assert rows(closest_pairs(ties, ids(spark, [0]), ids(spark, range(1, 9)), 3, hierarchy=partition.build_hierarchy(ties, leaves=2))) == [(0, 1, 5), (0, 2, 5), (0, 3, 5)]


def test_direction_and_order(spark):
    one_way = net_of(spark, [(1, 2, 1), (2, 3, 1), (3, 1, 1)], directed=True)
    assert rows(distance_join(one_way, ids(spark, [1]), ids(spark, [3]), 9)) == [(1, 3, 2)]
    assert rows(distance_join(one_way.reversed(), ids(spark, [1]), ids(spark, [3]), 9)) == [(1, 3, 1)]
    both = net_of(spark, [(1, 2, 1), (2, 3, 1)])
    assert rows(swap_operands(distance_join(both, ids(spark, [3]), ids(spark, [1]), 9))) == [(1, 3, 2)]


def test_prefix_and_monotony(spark, world):
    _, net, r, s, *_, tree = world
    small, large = (rows(closest_pairs(net, r, s, k, hierarchy=tree)) for k in (5, 15))
    assert large[:5] == small
    near, far = (set(rows(distance_join(net, r, s, t, hierarchy=tree))) for t in (40, 80))
    assert near <= far


@given(st.integers(0, 10_000), st.sampled_from([None, 1, 5, 40]), st.sampled_from([30, 90, 10**6]), st.sampled_from([1, 60, 10**6]))
@settings(max_examples=60, deadline=None)
def test_reach_equals_dijkstra(seed, k, theta, cells):
    """Batches of any size: exact costs within the bound, and with k the k least pairs whatever the bound has shrunk to."""
    edges = random_edges(25, 15, seed)
    a, b, w = (np.array(x, np.int64) for x in zip(*edges))
    g = kernels.LocalGraph(np.concatenate([a, b]), np.concatenate([b, a]), np.concatenate([w, w]))
    r, s, start = np.arange(0, 25, 3), np.arange(1, 25, 4), np.arange(0, 25, 3) % 4
    old, kernels.CELLS = kernels.CELLS, cells
    best, work = kernels.BestPairs(k, theta), kernels.Work()
    try:
        got = kernels.reach(g, g.local(r), start, {"pair": g.mask(s), "all": np.ones(25, bool)}, best, counted="pair", work=work)
    finally:
        kernels.CELLS = old
    adj = reference.adjacency(edges)
    want = sorted((c + d, u, v) for u, c in zip(r.tolist(), start.tolist()) for v, d in reference.distances(adj, u).items() if v in set(s.tolist()) and c + d <= theta)
    found = sorted(zip(got["pair"][2].tolist(), got["pair"][0].tolist(), got["pair"][1].tolist()))
    limit = best.limit
    assert limit == (theta if not k or len(want) < k else want[k - 1][0])
    assert found == [x for x in want if x[0] <= limit] and work.relaxed >= 0 and work.settled >= len(got["all"][2])


@given(st.integers(0, 10_000), st.sampled_from([0.0, 0.3, 1.0]))
@settings(max_examples=25, deadline=None)
def test_growth_kernel_equals_plain_growth(seed, alpha):
    r = random.Random(seed)
    edges = [(a, b, w) for (a, b, _), w in zip(random_edges(18, 14, seed), r.sample(range(1, 500), 60))]
    a, b, w = (np.array(x, np.int64) for x in zip(*edges))
    tail, head = np.concatenate([a, b]), np.concatenate([b, a])
    g = kernels.LocalGraph(tail, head, np.concatenate([w, w]))
    eids = np.concatenate([np.arange(len(w))] * 2)[g.order]
    side = kernels.grow(g, eids, 0, len(g.ids) - 1, alpha)
    assert dict(zip(g.ids.tolist(), side.tolist())) == reference.grow(edges, int(g.ids[0]), int(g.ids[-1]), alpha)


def test_forest_equals_growth_and_bottleneck(spark):
    edges = [(a, b, w) for (a, b, _), w in zip(random_edges(40, 25, 8), random.Random(1).sample(range(1, 900), 80))]
    net = net_of(spark, edges)
    task = {tuple(r) for r in partition.bisect(net, 0, 39).select("id", "side").collect()}
    forest = {tuple(r) for r in partition.bisect(net, 0, 39, engine="forest").select("id", "side").collect()}
    assert task == forest
    side = dict(task)
    assert min(w for a, b, w in edges if side[a] != side[b]) == reference.bottleneck(edges, 0, 39)
    with pytest.raises(ValueError):
        partition.bisect(net, 1, 1)
    with pytest.raises(ValueError):
        partition.bisect(net, 0, 1, alpha=0.5, engine="forest")
    coarse = partition.coarsen_then_bisect(net, alpha=0.5, max_task_edges=20)
    assert coarse.count() == 40 and coarse.select("side").distinct().count() == 2


def test_smoothing_end_points():
    assert kernels.smoothed_weight(7, 3, 9, 0.0) == 7
    assert kernels.smoothed_weight(8, 3, 9, 1.0) == 8 * 3 / 12
    assert all(kernels.smoothed_weight(5, 4, n, a) <= 5 for n in (1, 9) for a in (0.25, 0.5, 1.0))


@pytest.mark.parametrize("seeds", ["double_sweep", "random", "best_of", "longest_tree_edge"])
def test_hierarchy_invariants(spark, world, seeds):
    edges, net, *_ = world
    tree = partition.build_hierarchy(net, leaves=8, alpha=0.25, seeds=seeds)
    leaf = {r["id"]: r["gp"] for r in tree.assign.collect()}
    assert len(leaf) == 80 == tree.assign.count()
    cross = {(r["a"], r["b"]): r for r in tree.cross.collect()}
    assert all((b, a) in cross and leaf[a] != leaf[b] for a, b in cross)
    assert len(cross) == 2 * sum(leaf[a] != leaf[b] for a, b, _ in edges)
    for (a, b), r in cross.items():
        x, y = leaf[a], leaf[b]
        while x != y:
            x, y = (x // 2, y) if x > y else (x, y // 2)
        assert r["gp"] == x
        x = leaf[a]
        while x // 2 != r["gp"]:
            x //= 2
        assert r["a_side"] == x % 2
    seps = {r["gp"]: r["sep"] for r in measures.separation(tree).collect()}
    assert seps[1] == min(r["w"] for r in cross.values() if r["gp"] == 1)
    plan = {r["gp"]: r["wave"] for r in schedule_plan(tree, 3).collect()}
    assert all(plan[g // 2] > w for g, w in plan.items() if g > 1)
    assert cut_hierarchy(tree, net, 1).nodes.where("leaf").count() == 2
    assert measures.border_profile(tree).agg(F.sum("n_cross")).first()[0] == len(cross) // 2
    assert measures.imbalance(tree).first()["ratio"] >= 1


def test_leaf_size_guard(spark, world):
    _, net, *_ = world
    tree = partition.build_hierarchy(net, leaves=2, alpha=0.5, max_leaf_edges=20)
    assert tree.nodes.where("leaf").agg(F.max("n_edges")).first()[0] <= 20


def test_disconnected_parts(spark):
    net = net_of(spark, [(1, 2, 4), (2, 3, 1), (11, 12, 4), (12, 13, 2)])
    for attach, cross in (("smaller", None), ("separate", 0)):
        tree = partition.build_hierarchy(net, leaves=2, attach=attach, seeds="random")
        assert tree.assign.count() == 6 and tree.nodes.where("leaf").count() == 2
        if cross is not None:
            assert tree.cross.count() == cross and {r["gp"] for r in tree.assign.where("id < 10").collect()} == {2}


def test_components_and_relax(spark):
    e = spark.createDataFrame([(i, i + 1) for i in range(1, 40)] + [(100, 101), (101, 102), (7, 7), (None, 3)], "a long, b long")
    got = {r["id"]: r["component"] for r in connected_components(e).collect()}
    assert all(got[i] == 1 for i in range(1, 41)) and got[102] == 100 and len(got) == 43
    edges = random_edges(50, 30, 5)
    net = net_of(spark, edges)
    adj = reference.adjacency(edges)
    far = {(r["src"], r["node"]): r["d"] for r in distances_from(net.arcs, ids(spark, [0, 9])).collect()}
    assert far == {(s, x): d for s in (0, 9) for x, d in reference.distances(adj, s).items()}
    report = {}
    relax(net.arcs, spark.createDataFrame([(0, 0, 0)], "src long, node long, d long"), 30, report=report)
    assert report["rounds"] >= 1


def test_plans_push_down_and_trim(spark, sf):
    from netjoin.sources.tables import load

    plan = load(spark, sf, "orders").where("o_orderpriority = '1-URGENT'").select("o_orderkey")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(o_orderpriority)" in plan and "o_totalprice" not in plan
    from netjoin.plans.joins import top_pairs, trim_pairs

    p = spark.createDataFrame([(1, 1, 2, 3)], "gp long, u long, v long, d long")
    assert "TakeOrderedAndProject" in top_pairs(p, 3)._jdf.queryExecution().executedPlan().toString()
    assert "WindowGroupLimit" in trim_pairs(p, 3)._jdf.queryExecution().executedPlan().toString()


def test_parallelism_queries_run_in_pools(monkeypatch):
    """Every registered P is a pool of P: none runs the default schedule."""
    from types import SimpleNamespace

    from netjoin.plans import catalog

    asked = {}
    monkeypatch.setattr(catalog, "prepare", lambda *a, **b: SimpleNamespace(net=None, r=None, s=None, tree=None))
    monkeypatch.setattr(catalog, "cut_hierarchy", lambda tree, net, n: None)
    monkeypatch.setattr(catalog, "closest_pairs", lambda *a, **b: asked.setdefault(b["parallelism"], b["schedule"]))
    for n in catalog.SWEEPS["parallelism"]:
        catalog.queries()[f"kcp_p_{n}"](None, "")
    assert asked == {n: "pool" for n in catalog.SWEEPS["parallelism"]}


def test_wave_starts_without_the_pilot(spark, world):
    """The plain wave has no bound from direct edges; the pilot starts below it. Answers are equal."""
    edges, net, r, s, rs, ss, tree = world
    start = {}
    for threshold in ("wave", "pilot+wave"):
        report = JoinReport()
        assert rows(closest_pairs(net, r, s, 3, hierarchy=tree, threshold=threshold, report=report)) == reference.pairs(edges, rs, ss, k=3)
        start[threshold] = report.trace[0]
    from netjoin.plans.joins import UNBOUNDED

    assert start["wave"] == UNBOUNDED > start["pilot+wave"]


def test_relax_appends_and_merges(spark, monkeypatch):
    """Small merge period, and every round by the broadcast way: distances stay exact."""
    from netjoin.operators import relax as module

    monkeypatch.setattr(module, "MERGE_ROUNDS", 2)
    edges = random_edges(60, 30, 9)
    net, adj = net_of(spark, edges), reference.adjacency(edges)
    want = {(s, x): d for s in (0, 7) for x, d in reference.distances(adj, s, 150).items()}
    for few in (module.FEW_STATES, 0):
        monkeypatch.setattr(module, "FEW_STATES", few)
        assert {(r["src"], r["node"]): r["d"] for r in distances_from(net.arcs, ids(spark, [0, 7]), 150).collect()} == want


def test_relax_does_not_stop_silently(spark):
    net = net_of(spark, [(i, i + 1, 1) for i in range(6)])
    seed = spark.createDataFrame([(0, 0, 0)], "src long, node long, d long")
    with pytest.raises(RuntimeError, match="3 rounds"):
        relax(net.arcs, seed, None, max_rounds=3)
    assert {r["node"]: r["d"] for r in relax(net.arcs, seed, None, max_rounds=7).collect()} == {i: i for i in range(7)}


@pytest.mark.parametrize("slots", [1, 3])
def test_overlay_that_fits_a_task_needs_no_rounds(spark, world, monkeypatch, slots):
    """The closure over a small overlay is found inside tasks, from all routes of a source at once; larger overlays and the frontier engine take rounds of joins."""
    edges, net, r, s, rs, ss, tree = world
    exact = reference.pairs(edges, rs, ss, 150)
    monkeypatch.setattr(joins, "default_slots", lambda spark: slots)
    monkeypatch.setattr(joins, "OVERLAY_SOURCES", 3)
    report = JoinReport()
    assert rows(distance_join(net, r, s, 150, hierarchy=tree, report=report)) == exact and not report.rounds
    assert rows(closest_pairs(net, r, s, 25, hierarchy=tree, engine="task")) == reference.pairs(edges, rs, ss, k=25)
    monkeypatch.setattr(joins, "OVERLAY_EDGES", 0)
    report = JoinReport()
    assert rows(distance_join(net, r, s, 150, hierarchy=tree, report=report)) == exact and report.rounds["rounds"] > 0


def test_bound_decides_what_fits_a_task(spark):
    """A part of many heavy edges goes to a task when those that the bound leaves fit; one with as many light ones does not."""
    edges = [(i, i + 1, 2 if i % 4 else 900) for i in range(40)]
    net = net_of(spark, edges)
    tree = partition.from_assignment(net, spark.createDataFrame([(i, 2 + i // 39) for i in range(41)], "id long, gp long"))
    for theta, fits in ((50, True), (2000, False)):
        report = JoinReport()
        got = rows(distance_join(net, ids(spark, range(0, 41, 3)), ids(spark, range(1, 41, 3)), theta, hierarchy=tree, report=report, task_edges=32))
        assert got == reference.pairs(edges, set(range(0, 41, 3)), set(range(1, 41, 3)), theta) and bool(report.searches) == fits
