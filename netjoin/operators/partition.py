"""Separation-first bisection, the hierarchy it builds, and the spanning-forest form of the unsmoothed case.

Parts that fit a task are split by growth inside it (all parts of a level in one job). A part beyond a task is split by joins: with alpha 0, growth from two
seeds equals the minimum spanning forest with both seeds fused, un-fused again; with smoothing, the part is contracted until it fits. A hierarchy is
stored as an index: arcs by leaf, cross-edges by lowest common part, and what every part's row says of it.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Row
from pyspark.sql import functions as F

from netjoin.functions.expressions import BUCKETS, bucket
from netjoin.functions.workspace import counted, drop_tables, materialise
from netjoin.operators import kernels
from netjoin.operators.components import connected_components
from netjoin.operators.network import Network
from netjoin.operators.relax import double_sweep

#: Most edges of a part that one task splits or searches. Splitting 2 million edges takes a worker 0.9 GB and 30 s (measured on a grid).
TASK_EDGES = 2_000_000
#: Edges to which a network with parts beyond a task is contracted: a hundred times the vertices of a few dozen parts, and seconds for a task.
COARSE_EDGES = 250_000


@dataclass(frozen=True)
class Hierarchy:
    """A binary tree of parts: root 1, children 2g and 2g + 1.

    nodes(gp, parent, side, level, height, n_vertices, n_edges, seed_l, seed_r, sep, leaf, method), assign(id, gp, path from root to leaf),
    cross(gp = lowest common part, eid, a, b, w, a_side, leaf_a, leaf_b) in both directions, border(gp, id), arcs(gp, a, b, w) inside leaves.
    """

    nodes: DataFrame
    assign: DataFrame
    cross: DataFrame
    border: DataFrame
    arcs: DataFrame

    @cached_property
    def parts(self) -> dict[int, Row]:
        """The rows of ``nodes`` by part: a row for each part of the tree, read once."""
        return {r["gp"]: r for r in self.nodes.collect()}

    @property
    def leaves(self) -> list[Row]:
        return [r for r in self.parts.values() if r["leaf"]]

    @property
    def sigma(self) -> int | None:
        """Weight of the lightest cross-edge; None without any."""
        return min((r["sep"] for r in self.parts.values() if r["sep"] is not None), default=None)


def path_of(gp: Column) -> Column:
    """Ancestors of a part from the root down to itself."""
    return F.reverse(F.transform(F.sequence(F.lit(0), F.floor(F.log2(gp)).cast("int")), lambda k: F.floor(gp / F.pow(F.lit(2.0), k)).cast("long")))


def placed_arcs(net: Network, assign: DataFrame) -> DataFrame:
    """Arcs with the leaves and paths of both ends."""
    at = assign.select("id", "gp", "path")
    return net.arcs.join(at.select(F.col("id").alias("a"), F.col("gp").alias("leaf_a"), F.col("path").alias("path_a")), "a").join(at.select(F.col("id").alias("b"), F.col("gp").alias("leaf_b"), F.col("path").alias("path_b")), "b")


def cross_edges(net: Network, assign: DataFrame) -> DataFrame:
    """Arcs between different leaves, with their lowest common part and the side of the tail."""
    return _common(placed_arcs(net, assign).where("leaf_a <> leaf_b"))


def _common(placed: DataFrame) -> DataFrame:
    common = F.array_max(F.array_intersect("path_a", "path_b"))
    side = F.element_at("path_a", F.floor(F.log2(common)).cast("int") + 2) % 2
    return placed.select(common.alias("gp"), "eid", "a", "b", "w", side.cast("int").alias("a_side"), "leaf_a", "leaf_b")


def _both_ways(edges: DataFrame, directed: bool) -> DataFrame:
    """Placed edges as arcs a, b with their leaves, in both directions if undirected."""
    names = {"src": "a", "dst": "b", "leaf_src": "leaf_a", "leaf_dst": "leaf_b"}
    back = {"src": "b", "dst": "a", "leaf_src": "leaf_b", "leaf_dst": "leaf_a"}
    out = edges.withColumnsRenamed(names)
    return out if directed else out.unionByName(edges.withColumnsRenamed(back))


def border_of(cross: DataFrame) -> DataFrame:
    """(gp, id): end points of the cross-edges of a part."""
    return cross.select("gp", F.explode(F.array("a", "b")).alias("id")).distinct()


def from_assignment(net: Network, assign: DataFrame, info: DataFrame | None = None, *, renumber: bool = False) -> Hierarchy:
    """The hierarchy of a given leaf for each vertex: assign(id, gp).

    ``gp`` are tree numbers, or any labels if ``renumber``: then leaves get the numbers of a complete tree by label.
    """
    spark = assign.sparkSession
    if renumber:
        labels = sorted(r[0] for r in assign.select("gp").distinct().collect())  # a label for each leaf
        first = 1 << max(0, (len(labels) - 1).bit_length())
        mapping = F.create_map(*(F.lit(x) for i, g in enumerate(labels) for x in (int(g), first + i)))
        assign = assign.select("id", mapping[F.col("gp")].cast("long").alias("gp"))
    assign = materialise(assign.select("id", F.col("gp").cast("long")).withColumn("path", path_of(F.col("gp"))), "assign")
    # both ends of an edge are looked up once; arcs, common parts and sides follow from the leaves
    leaf = lambda c: assign.select(F.col("id").alias(c), F.col("gp").alias(f"leaf_{c}"))
    placed = materialise(net.edges.select("eid", "src", "dst", "w").join(leaf("src"), "src").join(leaf("dst"), "dst"), "placed")
    inside = placed.where("leaf_src = leaf_dst").select(F.col("leaf_src").alias("gp"), "src", "dst", "w")
    arcs, between = (_both_ways(df, net.directed) for df in (inside, placed.where("leaf_src <> leaf_dst").select("eid", "src", "dst", "w", "leaf_src", "leaf_dst")))
    cross = materialise(_common(between.withColumns({"path_a": path_of(F.col("leaf_a")), "path_b": path_of(F.col("leaf_b"))})), "cross")
    seps = cross.groupBy("gp").agg(F.min("w").alias("sep"))
    depth = F.floor(F.log2("gp"))
    members = assign.select("gp", F.explode("path").alias("node")).groupBy("node").agg(F.count(F.lit(1)).alias("n_vertices"), F.min(depth).alias("shallow"), F.max(F.col("gp") == F.col("node")).alias("leaf"))
    # every edge counts for the parts that hold both its ends: the ancestors of its leaf, or of its lowest common part
    held = inside.groupBy("gp").agg(F.count(F.lit(1)).alias("n")).unionByName(cross.groupBy("gp").agg(F.count_distinct("eid").alias("n")))
    inside = held.select(F.explode(path_of(F.col("gp"))).alias("node"), "n").groupBy("node").agg(F.sum("n").alias("n_edges"))
    seeds = info if info is not None else spark.createDataFrame([], _INFO)
    level = F.floor(F.log2("node")).cast("int")
    nodes = members.join(inside, "node", "left").join(seps.withColumnRenamed("gp", "node"), "node", "left").join(seeds.withColumnRenamed("gp", "node"), "node", "left")
    nodes = nodes.select(F.col("node").alias("gp"), F.expr("node div 2").alias("parent"), (F.col("node") % 2).cast("int").alias("side"), level.alias("level"), (F.col("shallow") - level).cast("int").alias("height"),
                         "n_vertices", F.coalesce("n_edges", F.lit(0)).cast("long").alias("n_edges"), "seed_l", "seed_r", "sep", "leaf", "method")
    return Hierarchy(materialise(nodes, "nodes"), assign, cross, border_of(cross), arcs)


_INFO = "gp long, seed_l long, seed_r long, method string"
_SPLIT = "kind string, gp long, x long, y long, w long, eid long"


def _graph_of(rows: pa.Table) -> tuple[kernels.LocalGraph, np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """The graph of a part's rows, the edge ids of its arcs, and its edges a, b, w, eid."""
    is_edge = pc.equal(rows.column("kind"), "e").to_numpy(zero_copy_only=False)
    of_edges = rows.filter(pa.array(is_edge))
    vertices = rows.filter(pa.array(~is_edge)).column("x").to_numpy().astype(np.int64)
    a, b, w, eid = (of_edges.column(c).to_numpy().astype(np.int64) for c in ("x", "y", "w", "eid"))
    g = kernels.LocalGraph(np.concatenate([a, b]), np.concatenate([b, a]), np.concatenate([w, w]), vertices)
    return g, np.concatenate([eid, eid])[g.order], a, b, w, eid


def _split_part(alpha: float, how: str, min_share: float, explicit: dict[int, tuple[int, int]], attach: str):
    def table(kind: str, gp, x, y=None, w=None, eid=None) -> pa.Table:
        n = len(x)
        columns = [pa.array(c, pa.int64()) if c is not None else pa.nulls(n, pa.int64()) for c in (gp, x, y, w, eid)]
        return pa.table([pa.array([kind] * n, pa.string()), *columns], names=["kind", "gp", "x", "y", "w", "eid"])

    def run(key: tuple, rows: pa.Table) -> pa.Table:
        gp = key[0].as_py()
        g, eids, a, b, w, eid = _graph_of(rows)
        n, seeds, side = len(g.ids), None, None
        if n >= 2:
            seeds = tuple(g.local(explicit[gp]).tolist()) if gp in explicit else kernels.pick_seeds(g, a, b, w, eid, how, alpha, min_share=min_share, eids=eids)
        if attach == "separate" and n >= 2:
            apart = np.ones(n, np.int8)
            apart[[x for _, x in g.search(0)]] = 0
            if apart.any():
                side, seeds = apart, (0, int(np.flatnonzero(apart)[0]))
        if not seeds or len(set(seeds)) < 2:
            return table("leaf", np.full(n, gp), g.ids)
        if side is None:
            side = kernels.grow(g, eids, seeds[0], seeds[1], alpha)
        i, j = side[np.searchsorted(g.ids, a)], side[np.searchsorted(g.ids, b)]
        same = i == j
        return pa.concat_tables([
            table("node", [gp], g.ids[[seeds[0]]], g.ids[[seeds[1]]]), table("v", 2 * gp + side.astype(np.int64), g.ids),
            table("e", 2 * gp + i[same].astype(np.int64), a[same], b[same], w[same], eid[same]),
        ])

    return run


def _rows_of(vertices: DataFrame, edges: DataFrame) -> DataFrame:
    """A whole network as the rows of part 1 that splits work on."""
    none, root = F.lit(None).cast("long"), F.lit(1).cast("long").alias("gp")
    start = vertices.select(F.lit("v").alias("kind"), root, F.col("id").alias("x"), none.alias("y"), none.alias("w"), none.alias("eid"))
    return start.unionByName(edges.select(F.lit("e").alias("kind"), root, F.col("src").alias("x"), F.col("dst").alias("y"), "w", "eid"))


def _carried(parts: DataFrame, label: DataFrame, cut: DataFrame, method: str, *, edges: bool) -> DataFrame:
    """The split of contracted parts carried over to their own vertices and edges, in the rows of ``_split_part`` and the method; without ``edges`` the vertices alone, for parts that are not split again."""
    to = materialise(label.join(cut.where("kind IN ('v', 'leaf')").select(F.col("x").alias("c"), "gp", "kind"), "c").select("kind", "gp", "id"), "carried")
    none, end = F.lit(None).cast("long"), lambda x: to.where("kind = 'v'").select(F.col("id").alias(x), F.col("gp").alias(f"to_{x}"))
    inside = parts.where("kind = 'e'").drop("gp").join(end("x"), "x").join(end("y"), "y").where("to_x = to_y").select("kind", F.col("to_x").alias("gp"), "x", "y", "w", "eid")
    vertices = to.select("kind", "gp", F.col("id").alias("x"), none.alias("y"), none.alias("w"), none.alias("eid"))
    rows = vertices.unionByName(inside) if edges else vertices
    return rows.unionByName(cut.where("kind = 'node'")).withColumn("method", F.lit(method))


def build_hierarchy(net: Network, *, leaves: int = 8, alpha: float = 0.0, seeds: str = "double_sweep", explicit: dict[int, tuple[int, int]] | None = None, min_share: float = 0.1, max_leaf_edges: int | None = None, attach: str = "smaller", engine: str = "auto", task_edges: int = TASK_EDGES) -> Hierarchy:
    """Recursive bisection to ``leaves`` parts (parts of one vertex stay whole). Between two powers of two, the last level splits the parts with the most edges.

    ``seeds``: double_sweep, random, best_of, longest_tree_edge; ``explicit`` gives seeds for single parts. ``alpha`` smooths by population.
    ``attach``: where vertices that no seed reaches go: to the smaller side, or (``separate``) a disconnected part is first split into the component of its lowest id and the rest.
    ``max_leaf_edges`` splits on until no leaf has more edges. engine: ``task`` splits every part in a task; ``joins`` none; ``auto`` splits by joins
    those parts alone that have more than ``task_edges`` edges. For ``auto`` without explicit seeds that means growth over the network contracted once for all such parts, seeds found there, down to parts of COARSE_EDGES edges: approximate
    with smoothing; at alpha 0 exact, as contraction takes forest edges alone (from vertices of the two contracted seeds). Else spanning forests at alpha 0 (the same split as in a task). Column ``method`` of the nodes says which. Seeds other than double_sweep and explicit ones are found inside tasks only: a larger part raises.
    """
    if engine not in ("auto", "task", "joins"):
        raise ValueError(f"unknown engine {engine!r}")
    depth, explicit = max(0, (leaves - 1).bit_length()), explicit or {}
    todo = materialise(_rows_of(net.vertices, net.edges), "split-0")
    done, info, tables, level, coarse, label = [], [], [todo], 0, None, None
    while level < depth or max_leaf_edges:
        sizes = {r["gp"]: r["n"] for r in todo.groupBy("gp").agg(F.count_if(F.col("kind") == "e").alias("n")).collect()}  # a row for each part
        last = level >= depth - 1
        splits = sorted(sizes, key=lambda g: (-sizes[g], g))
        if level >= depth:
            splits = [g for g in splits if sizes[g] > max_leaf_edges] if level <= 40 else []
        elif last:
            splits = splits[: max(0, leaves - (1 << level))]
        if not splits:
            break
        most = min(task_edges, COARSE_EDGES) if coarse is not None else task_edges
        large = [g for g in splits if engine == "joins" or (engine == "auto" and sizes[g] > most)]
        small = [g for g in splits if g not in set(large)]
        if large and seeds != "double_sweep" and not set(large) <= set(explicit):
            raise ValueError(f"seeds {seeds!r} are found inside tasks; parts {large} have more than {task_edges} edges")
        if len(splits) < len(sizes):
            done.append(todo.where(~F.col("gp").isin(splits) & (F.col("kind") == "v")).select(F.col("x").alias("id"), "gp"))
        out = None
        if small:
            out = todo.where(F.col("gp").isin(small)).groupBy("gp").applyInArrow(_split_part(alpha, seeds, min_share, explicit, attach), _SPLIT).withColumn("method", F.lit("task"))
        if large and not explicit and (alpha or engine == "auto"):
            if coarse is None:
                label, links = contract(net, min(task_edges, COARSE_EDGES))
                coarse = _rows_of(label.select(F.col("c").alias("id")).distinct(), links)
            cut = materialise(coarse.where(F.col("gp").isin(large)).groupBy("gp").applyInArrow(_split_part(alpha, seeds, min_share, {}, attach), _SPLIT), f"coarse-split-{level + 1}")
            one, coarse, large = _carried(todo.where(F.col("gp").isin(large)), label, cut, "coarse" if alpha else "forest", edges=not last or bool(max_leaf_edges)), cut.where("kind IN ('v', 'e')"), []
            tables.append(cut)
            out = one if out is None else out.unionByName(one)
        for g in large:
            one = _split_by_joins(todo.where(F.col("gp") == g), g, alpha, explicit.get(g), attach, task_edges)
            out = one if out is None else out.unionByName(one)
        out = materialise(out, f"split-{level + 1}")
        tables.append(out)
        done.append(out.where("kind = 'leaf'").select(F.col("x").alias("id"), "gp"))
        info.append(out.where("kind = 'node'").select("gp", F.col("x").alias("seed_l"), F.col("y").alias("seed_r"), "method"))
        todo = out.where("kind IN ('v', 'e')")
        level += 1
    assign = todo.where("kind = 'v'").select(F.col("x").alias("id"), "gp")
    for d in done:
        assign = assign.unionByName(d)
    seeds_df = None
    for d in info:
        seeds_df = d if seeds_df is None else seeds_df.unionByName(d)
    tree = from_assignment(net, assign, seeds_df)
    drop_tables(*tables)
    return tree


def _split_by_joins(part: DataFrame, gp: int, alpha: float, explicit: tuple[int, int] | None, attach: str, task_edges: int) -> DataFrame:
    """One part's split without a task that holds it, in the rows of ``_split_part`` and the method."""
    net = Network(part.where("kind = 'v'").select(F.col("x").alias("id")), part.where("kind = 'e'").select("eid", F.col("x").alias("src"), F.col("y").alias("dst"), "w"))
    none = F.lit(None).cast("long")
    side, method = None, "forest"
    if attach == "separate":
        parts = connected_components(net.edges.select(F.col("src").alias("a"), F.col("dst").alias("b")))
        label = materialise(net.vertices.join(parts, "id", "left").select("id", F.coalesce("component", "id").alias("c")), "split-components")
        low, high = label.agg(F.min("c"), F.max("c")).first()
        if low != high:
            side, method, left, right = label.select("id", F.when(F.col("c") == low, 0).otherwise(1).alias("side")), "components", low, high
    if side is None:
        left, right = explicit or double_sweep(net.arcs, net.vertices)
        if left == right:
            return net.vertices.select(F.lit("leaf").alias("kind"), F.lit(gp).cast("long").alias("gp"), F.col("id").alias("x"), none.alias("y"), none.alias("w"), none.alias("eid"), F.lit(method).alias("method"))
        if alpha:
            side, method = coarsen_then_bisect(net, alpha=alpha, max_task_edges=task_edges, ends=(left, right)), "coarse"
        else:
            side = bisect_forest(net, left, right, task_edges=task_edges)
    side = materialise(side, "split-side")
    vertices = side.select(F.lit("v").alias("kind"), (2 * gp + F.col("side")).cast("long").alias("gp"), F.col("id").alias("x"), none.alias("y"), none.alias("w"), none.alias("eid"))
    kept = net.edges.join(side.select(F.col("id").alias("src"), F.col("side").alias("s1")), "src").join(side.select(F.col("id").alias("dst"), F.col("side").alias("s2")), "dst").where("s1 = s2")
    edges = kept.select(F.lit("e").alias("kind"), (2 * gp + F.col("s1")).cast("long").alias("gp"), F.col("src").alias("x"), F.col("dst").alias("y"), "w", "eid")
    node = part.sparkSession.range(1).select(F.lit("node").alias("kind"), F.lit(gp).cast("long").alias("gp"), F.lit(left).cast("long").alias("x"), F.lit(right).cast("long").alias("y"), none.alias("w"), none.alias("eid"))
    return vertices.unionByName(edges).unionByName(node).withColumn("method", F.lit(method))


def _cheapest(edges: DataFrame) -> DataFrame:
    """(c, o, eid): the lightest edge (src, dst, w, eid) of every end."""
    both = edges.select("eid", "w", F.col("src").alias("c"), F.col("dst").alias("o")).unionByName(edges.select("eid", "w", F.col("dst").alias("c"), F.col("src").alias("o")))
    return both.groupBy("c").agg(F.min(F.struct("w", "eid", "o")).alias("m")).select("c", "m.o", "m.eid")


def _joined(edges: DataFrame, merged: DataFrame) -> DataFrame:
    """Edges between merged ends, of parallel ones the lightest."""
    to = lambda n: merged.select(F.col("id").alias(n), F.col("component").alias(f"{n}_c"))
    moved = edges.join(to("src"), "src", "left").join(to("dst"), "dst", "left").select("eid", F.coalesce("src_c", "src").alias("src"), F.coalesce("dst_c", "dst").alias("dst"), "w").where("src <> dst")
    return moved.groupBy(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).agg(F.min(F.struct("w", "eid")).alias("m")).select("m.eid", "src", "dst", "m.w")


def _task_forest(key: tuple, rows: pa.Table) -> pa.Table:
    src, dst, w, eid = (rows.column(c).to_numpy().astype(np.int64) for c in ("src", "dst", "w", "eid"))
    ends, at = np.unique(np.concatenate([src, dst]), return_inverse=True)
    return pa.table([pa.array(eid[kernels.spanning_edges(at[: len(src)], at[len(src) :], w, eid, len(ends))])], names=["eid"])


def spanning_forest(net: Network, *, task_edges: int = TASK_EDGES) -> DataFrame:
    """Edges (eid, src, dst, w) of the minimum spanning forest under (w, eid): rounds of cheapest outgoing edges by joins until the edges between
    what they join fit a task, which ends the forest; at most ``task_edges`` edges meet in it."""
    edges, n = counted(net.edges.where("src <> dst").select("eid", "src", "dst", "w"), "msf-edges")
    forest, n = [], n["n"]
    while n > task_edges:
        picks = materialise(_cheapest(edges), "msf-picks")
        forest.append(picks.select("eid"))
        merged = _hooked(picks.select(F.col("c").alias("a"), F.col("o").alias("b")))
        done, (edges, seen) = edges, counted(_joined(edges, merged), "msf-edges")
        n = seen["n"]
        drop_tables(done, merged)
    last = edges.withColumn("one", F.lit(1)).groupBy("one").applyInArrow(_task_forest, "eid long")
    for picked in forest:
        last = last.unionByName(picked)
    return net.edges.join(last.distinct(), "eid", "left_semi").select("eid", "src", "dst", "w")


def hierarchy_from_forest(net: Network, *, leaves: int = 8, **options) -> Hierarchy:
    """The unsmoothed hierarchy from one spanning forest: a side's forest is the parent's restricted to it, so every level below the first
    pass over all edges works on fewer edges than vertices. Seeds by distance are those of the forest."""
    forest = materialise(spanning_forest(net), "forest")
    tree = build_hierarchy(Network(net.vertices, forest), leaves=leaves, alpha=0.0, **options)
    return from_assignment(net, tree.assign.select("id", "gp"), tree.nodes.where("seed_l IS NOT NULL").select("gp", "seed_l", "seed_r", "method"))


def bisect_forest(net: Network, left: int, right: int, *, task_edges: int = TASK_EDGES) -> DataFrame:
    """(id, side): the unsmoothed split from two seeds, as the spanning forest with the seeds fused: by rounds everything but the seeds joins along its cheapest edge,
    which is an edge of that forest, until what is left fits a task. Unreached components join the smaller side."""
    if left == right:
        raise ValueError("the two seeds are the same vertex")
    label, edges = contract(net, task_edges, (left, right), absorb=True)
    grown = _rows_of(label.select(F.col("c").alias("id")).distinct(), edges).groupBy("gp").applyInArrow(_task_sides(left, right), "c long, side int")
    sides = materialise(label.join(grown, "c").select("id", "side"), "bisect-sides")
    counts = {r["side"]: r["count"] for r in sides.groupBy("side").count().collect()}
    rest = 0 if counts[0] <= counts[1] else 1
    return sides.select("id", F.when(F.col("side") < 0, rest).otherwise(F.col("side")).alias("side"))


def _task_sides(left: int, right: int):
    """Sides of the unsmoothed growth from two seeds in a task; -1 where neither comes."""

    def run(key: tuple, rows: pa.Table) -> pa.Table:
        g, eids, *_ = _graph_of(rows)
        l, r = g.local([left, right]).tolist()
        return pa.table([pa.array(g.ids), pa.array(kernels.grow(g, eids, l, r, 0.0, rest=False).astype(np.int32))], names=["c", "side"])

    return run


def bisect(net: Network, left: int, right: int, *, alpha: float = 0.0, engine: str = "task") -> DataFrame:
    """(id, side) of one split from given seeds; ``task`` grows both clusters in one task, ``forest`` computes the alpha 0 split by joins."""
    if left == right:
        raise ValueError("the two seeds are the same vertex")
    if engine == "forest":
        if alpha:
            raise ValueError("population smoothing depends on the order of growth; coarsen the network or use the task engine")
        return bisect_forest(net, left, right)
    tree = build_hierarchy(net, leaves=2, alpha=alpha, explicit={1: (left, right)}, engine="task")
    return tree.assign.select("id", (F.col("gp") % 2).cast("int").alias("side"))


def _hooked(picks: DataFrame) -> DataFrame:
    """(id, component) from (a, b), each vertex on its cheapest neighbour: the only cycles are pairs that pick each other, whose lower id is the root; others jump to it."""
    back = picks.select(F.col("a").alias("b"), F.col("b").alias("back"))
    own = F.when((F.col("back") == F.col("a")) & (F.col("a") < F.col("b")), F.col("a")).otherwise(F.col("b"))
    at, moved = materialise(picks.join(back, "b", "left").select("a", own.alias("p")), "hooked"), {"moved": 1}
    while moved.get("moved"):
        up = at.select(F.col("a").alias("p"), F.col("p").alias("q"))
        done, (at, moved) = at, counted(at.join(up, "p", "left").select("a", F.coalesce("q", "p").alias("p"), (F.coalesce("q", "p") != F.col("p")).alias("m")), "hooked", moved=F.count_if("m"))
        drop_tables(done)
    return at.select(F.col("a").alias("id"), F.col("p").alias("component"))


def contract(net: Network, max_edges: int, ends: tuple[int, int] | None = None, *, absorb: bool = False) -> tuple[DataFrame, DataFrame]:
    """(id, c) and edges (eid, src, dst, w) between the c: the network with vertices joined along cheapest edges, round by round, until so many edges are left.
    ``ends`` are never joined with each other; with ``absorb`` others join them (they pick no edge themselves), else nothing does."""
    edges, seen = net.edges.select("eid", "src", "dst", "w"), {"n": net.edges.count()}
    maps: list[DataFrame] = []
    while seen["n"] > max_edges:
        picks = _cheapest(edges).select(F.col("c").alias("a"), F.col("o").alias("b"))
        if ends:
            picks = picks.where(~F.col("a").isin(*ends))
            picks = picks if absorb else picks.where(~F.col("b").isin(*ends))
        picks, n = counted(picks, "coarse-picks")
        if not n["n"]:
            break
        maps.append(_hooked(picks))
        done = [picks, edges] if len(maps) > 1 else [picks]  # the first edges are the caller's
        edges, seen = counted(_joined(edges, maps[-1]), "coarse-edges")
        drop_tables(*done)
    # the last rounds' maps are small: they are joined first
    up = None
    for now in reversed(maps):
        up = now if up is None else now.join(up.select(F.col("id").alias("component"), F.col("component").alias("top")), "component", "left").select("id", F.coalesce("top", "component").alias("component"))
    if up is None:
        return net.vertices.select("id", F.col("id").alias("c")), edges
    label = materialise(net.vertices.join(up, "id", "left").select("id", F.coalesce("component", "id").alias("c")), "coarse-labels")
    drop_tables(*maps)
    return label, edges


def coarsen_then_bisect(net: Network, *, alpha: float, max_task_edges: int = TASK_EDGES, seeds: str = "double_sweep", ends: tuple[int, int] | None = None) -> DataFrame:
    """(id, side) of a smoothed split of a network beyond a task: contract along cheapest edges until it fits, then grow from the contracted
    seeds (``ends``, or found by ``seeds``). Approximate. The two ends are never contracted into one."""
    label, edges = contract(net, max_task_edges, ends)
    small = Network(label.select(F.col("c").alias("id")).distinct(), edges)
    sides = build_hierarchy(small, leaves=2, alpha=alpha, seeds=seeds, explicit={1: ends} if ends else None, engine="task").assign.select(F.col("id").alias("c"), (F.col("gp") % 2).cast("int").alias("side"))
    return label.join(sides, "c").select("id", "side")


def balanced_assign(net: Network, leaves: int, *, objective: str = "size", rounds: int = 8) -> DataFrame:
    """(id, gp 0..leaves-1): parts of equal size by bands of the operand hash (``size``), or by label propagation over light edges from such parts,
    under a capacity of 1.1 times the mean (``cut``): the edge-cut partitioning that separation is contrasted with."""
    at = net.vertices.select("id", F.floor(bucket(F.col("id")) * leaves / BUCKETS).cast("long").alias("gp"))
    if objective == "size":
        return at
    room = net.vertices.count() * 1.1 / leaves
    at = materialise(at, "balanced")
    for turn in range(rounds):
        votes = net.arcs.join(at.select(F.col("id").alias("b"), F.col("gp").alias("g")), "b").groupBy(F.col("a").alias("id"), "g").agg(F.sum(1.0 / F.col("w")).alias("pull"))
        wish = votes.groupBy("id").agg(F.max_by("g", F.struct("pull", "g")).alias("g"))
        sizes = at.groupBy(F.col("gp").alias("g")).agg(F.count(F.lit(1)).alias("n"))
        movers = wish.join(at, "id").where(F.col("g") != F.col("gp")).where(F.pmod(F.xxhash64("id", F.lit(turn)), F.lit(2)) == 0)
        demand = movers.groupBy("g").agg(F.count(F.lit(1)).alias("m")).join(sizes, "g").select("g", F.least(F.lit(1.0), F.greatest(F.lit(0.0), (room - F.col("n")) / F.col("m"))).alias("p"))
        moved = movers.join(F.broadcast(demand), "g").where(F.pmod(F.xxhash64("id", F.lit(99 + turn)), F.lit(1000)) < 1000 * F.col("p")).select("id", "g")
        done, at = at, materialise(at.join(moved, "id", "left").select("id", F.coalesce("g", "gp").alias("gp")), "balanced")
        drop_tables(done)
    return at
