"""Plan and size checks: what must hold at any scale."""

import ast
from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

from netjoin.operators import kernels, partition
from netjoin.operators.relax import relax
from netjoin.sources.networks import NETWORKS
from tests.test_network_joins import ids, net_of, random_edges

ROOT = Path(__file__).resolve().parents[1]


def test_core_never_imports_the_text_subpackage():
    for f in (ROOT / "netjoin").rglob("*.py"):
        if "llm" in f.relative_to(ROOT).parts:
            continue
        for node in ast.walk(ast.parse(f.read_text())):
            names = [a.name for a in node.names] if isinstance(node, ast.Import) else [node.module or ""] if isinstance(node, ast.ImportFrom) else []
            assert not any(n.startswith(("netjoin.llm", "corpus_pipeline")) for n in names), f


def test_no_local_checkpoint_no_rdd():
    for f in (ROOT / "netjoin").rglob("*.py"):
        text = f.read_text()
        assert "localCheckpoint" not in text and ".rdd" not in text and "toPandas" not in text, f


def test_builders_prune_columns(spark, sf):
    plan = NETWORKS["interstate"](spark, sf).edges._jdf.queryExecution().executedPlan().toString()
    assert "o_totalprice" not in plan and "c_name" not in plan


def test_relaxation_does_not_broadcast_state(spark):
    """With broadcasts off, a round is one join, one partial and one final minimum, and one outer join."""
    net = net_of(spark, random_edges(30, 20, 1))
    got = relax(net.arcs, ids(spark, [0]).select(F.col("id").alias("src"), F.col("id").alias("node"), F.lit(0).cast("long").alias("d")), 40)
    assert "Scan parquet" in got._jdf.queryExecution().executedPlan().toString()


def test_cross_edges_by_joins(spark):
    net = net_of(spark, random_edges(40, 20, 4))
    tree = partition.build_hierarchy(net, leaves=4, alpha=0.5)
    for df in (partition.placed_arcs(net, tree.assign), partition.cross_edges(net, tree.assign)):
        plan = df._jdf.queryExecution().executedPlan().toString()
        assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan


def test_large_smoothed_parts_need_no_sweep_over_the_network(spark, monkeypatch):
    """A path of many hops beyond a task is contracted, not swept hop by hop; every vertex has a leaf and the contraction joins what its edges join."""
    monkeypatch.setattr(partition, "double_sweep", lambda *a: (_ for _ in ()).throw(AssertionError("swept by joins")))
    edges = [(i, i + 1, 1 + i * 7919 % 97) for i in range(400)]
    net = net_of(spark, edges)
    tree = partition.build_hierarchy(net, leaves=4, alpha=0.5, task_edges=150)
    assert len(tree.leaves) == 4 and tree.assign.count() == 401 and tree.parts[1]["method"] == "coarse"
    label, links = partition.contract(net, 150)
    of = {r["id"]: r["c"] for r in label.collect()}
    assert len(of) == 401 and links.count() == len(set(of.values())) - 1 <= 150
    assert {(of[r["src"]], of[r["dst"]]) for r in net.edges.collect() if of[r["src"]] != of[r["dst"]]} == {(a, b) if (a, b) in {(of[x], of[y]) for x, y, _ in edges} else (b, a) for a, b in ((r["src"], r["dst"]) for r in links.collect())}


@pytest.mark.parametrize("task_edges", [1000, 12, 0])
def test_forests_take_no_rounds_of_components(spark, monkeypatch, task_edges):
    """A spanning forest and a forest split end in a task once they fit it; no round labels components by joins. Ties, islands and lone vertices included."""
    monkeypatch.setattr(partition, "connected_components", lambda *a: (_ for _ in ()).throw(AssertionError("components by joins")))
    edges = [(a, b, 1 + w % 9) for a, b, w in random_edges(50, 40, 5)] + [(100, 101, 3), (101, 102, 3), (100, 102, 3)]
    net = net_of(spark, edges, vertices=[*range(50), 100, 101, 102, 200])
    rows = sorted(net.edges.collect(), key=lambda r: (r["w"], r["eid"]))
    src, dst, w, eid = (np.array([r[c] for r in rows]) for c in ("src", "dst", "w", "eid"))
    want = {rows[i]["eid"] for i in kernels.spanning_edges(src, dst, w, eid, 201)}
    got = partition.spanning_forest(net, task_edges=task_edges).collect()
    assert len(got) == len(want) == 51 and {r["eid"] for r in got} == want
    whole = partition.build_hierarchy(net, leaves=2, explicit={1: (3, 47)}, engine="task").assign.collect()
    side = {r["id"]: r["side"] for r in partition.bisect_forest(net, 3, 47, task_edges=task_edges).collect()}
    assert side == {r["id"]: r["gp"] % 2 for r in whole} and len(side) == 54
    assert partition.spanning_forest(net_of(spark, [(1, 1, 5)]), task_edges=task_edges).count() == 0


def test_unsmoothed_large_parts_need_no_sweep_either(spark, monkeypatch):
    """At alpha 0 a part beyond a task is split on the contracted network: no sweep hop by hop, and the cut is the heaviest edge between two vertices of the seeds."""
    monkeypatch.setattr(partition, "double_sweep", lambda *a: (_ for _ in ()).throw(AssertionError("swept by joins")))
    weights = [1 + i * 7919 % 997 for i in range(400)]
    net = net_of(spark, [(i, i + 1, w) for i, w in enumerate(weights)])
    tree = partition.build_hierarchy(net, leaves=4, task_edges=150)
    assert tree.parts[1]["method"] == "forest" and tree.assign.count() == 401 and len(tree.leaves) == 4
    low, high = sorted((tree.parts[1]["seed_l"], tree.parts[1]["seed_r"]))
    assert max(weights[low:high]) >= tree.parts[1]["sep"] >= sorted(weights)[-150]
    assert tree.arcs.count() + tree.cross.count() == 800 and sum(r["n_edges"] for r in tree.leaves) == 400 - tree.cross.count() // 2
