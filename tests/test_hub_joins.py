"""Distance joins of networks with hubs: paths over hubs meet from both sides, and nothing is kept or written for each pair."""

import numpy as np

from netjoin.operators import kernels, partition
from netjoin.plans import joins
from netjoin.plans.joins import JoinReport, distance_join
from tests import reference
from tests.test_network_joins import ids, net_of, random_edges, rows


def star(arms, length):
    """Two linked hubs (0, 1), arms of a few vertices hung on them in turn, every fifth arm tied to the other hub too."""
    out, n = [(0, 1, 7)], 2
    for arm in range(arms):
        last = arm % 2
        for k in range(length):
            out.append((last, n, 1 + (arm * 7 + k * 5) % 9))
            last, n = n, n + 1
        if arm % 5 == 0:
            out.append((last, 1 - arm % 2, 1 + arm % 6))
    return out, n


def test_pairs_over_hubs_equal_the_reference(spark, monkeypatch):
    """Hubs in R and in S, linked hubs, paths with none, one and several hubs, R and S dealt to many tasks: the pairs, once each, at their least distance."""
    edges, n = star(24, 3)
    edges += [(a + 1000, b + 1000, w) for a, b, w in random_edges(20, 10, 2)] + [(1000, 5, 4)]
    for name, value in {"HUB_EDGES": 0, "HUB_ARCS": 5, "HUBS": 4, "MEET_SOURCES": 3, "MEET_ROWS": 10}.items():
        monkeypatch.setattr(joins, name, value)
    net, r, s = net_of(spark, edges), {0, *range(2, n, 3), *range(1000, 1020, 4)}, {1, *range(3, n, 3), *range(1001, 1020, 3)}
    r -= s
    tree = partition.build_hierarchy(net, leaves=4, alpha=0.5)
    spec = joins._spec(net, ids(spark, r), ids(spark, s), None, tree)
    assert {0, 1} <= set(joins.hub_vertices(spec, 40)) and len(joins.hub_vertices(spec, 40)) <= 4
    adj = reference.adjacency(edges)
    want = sorted((d, u, v) for u in r for v, d in reference.distances(adj, u).items() if v in s and d <= 24)
    assert [(d, u, v) for u, v, d in rows(distance_join(net, ids(spark, r), ids(spark, s), 24, hierarchy=tree))] == want and len(want) > 100


def test_searches_do_not_pass_hubs(spark, monkeypatch):
    """Work of the searches is in proportion to the vertices, where going over hubs every source would settle every vertex."""
    edges, n = star(200, 3)
    monkeypatch.setattr(joins, "HUB_EDGES", 0, raising=False)
    monkeypatch.setattr(joins, "HUB_ARCS", 50, raising=False)
    net, report = net_of(spark, edges), JoinReport()
    tree = partition.build_hierarchy(net, leaves=2, alpha=0.5)
    pairs = distance_join(net, ids(spark, range(2, n, 2)), ids(spark, range(3, n, 2)), 1000, hierarchy=tree, report=report)
    assert pairs.count() == 300 * 300 and report.settled < 20 * n


def test_a_search_hands_on_batches(monkeypatch):
    """Without k what is found leaves batch by batch; a source takes the cells of its component alone."""
    monkeypatch.setattr(kernels, "CELLS", 40)
    a = np.array([x for x in range(400) if x % 4 != 3])
    g = kernels.LocalGraph(np.concatenate([a, a + 1]), np.concatenate([a + 1, a]), np.ones(2 * len(a), np.int64))
    got = list(kernels.reach_batches(g, np.arange(400), np.zeros(400, np.int64), {"all": np.ones(400, bool)}, kernels.BestPairs(None, 9)))
    assert len(got) == 40 and {len(x["all"][0]) for x in got} == {40}
    assert all((abs(x - y) == d).all() and (x // 4 == y // 4).all() for x, y, d in (b["all"] for b in got))
