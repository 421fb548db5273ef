"""The two joins: all pairs within a distance, and the k closest pairs, alone or combined.

A join runs as waves: leaf searches first, then what crosses between parts, under a bound that is refreshed between waves. Where the refreshed bound is
below the lightest cross-edge, nothing can cross and the join ends with the leaves.
``crossings`` says which paths count:

none       paths inside one leaf
one        at most one cross-edge in total
per_level  at each merge of siblings at most one cross-edge of that part, near side from kept routes, far side inside the sibling
closure    all paths (default): leaf-internal border distances and cross-edges form an overlay that is closed to a fixed point

The first three are exact where the bound is below the certificate (sigma for none, 2 sigma for the others; sigma: lightest cross-edge); closure always is.
"""

from __future__ import annotations

import time
from collections.abc import Iterator, Sequence
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from netjoin.functions.workspace import counted, materialise, passing
from netjoin.operators import kernels
from netjoin.operators.network import Network, assert_disjoint
from netjoin.operators.partition import TASK_EDGES, Hierarchy
from netjoin.operators.relax import relax
from netjoin.plans.schedule import default_slots, plan_steps

UNBOUNDED = 1 << 58
#: Most sources that one task searches from in a part; the sources of larger parts are dealt to several tasks.
SOURCES_PER_TASK = 20_000
#: Most parts whose places in a schedule are broadcast; more are shuffled.
BROADCAST_PARTS = 500_000
#: Most edges of an overlay of borders that is closed inside tasks, a copy in each; a larger one is closed by joins.
OVERLAY_EDGES = 500_000
#: Sources whose distances over the overlay a task finds before it hands them on.
OVERLAY_SOURCES = 5_000
#: Networks of more edges are looked through for hubs: vertices with so many arcs within the bound, at most so many of them, those with the most.
HUB_EDGES, HUB_ARCS, HUBS = 250_000, 1_000, 256
#: Most sources that one task searches from in a part without its hubs, where a search ends early.
HUBLESS_SOURCES = 500_000
#: Vertices of R, and vertices of S with their hubs, that meet over hubs in one task.
MEET_SOURCES, MEET_ROWS = 10_000, 500_000
#: Rows that a task hands on at once.
HANDED = 200_000


@dataclass
class JoinReport:
    """What a join did: bounds after each wave, radii tried while no bound was known, certificate, and machine-independent work.

    ``settled`` and ``relaxed`` count vertices reached within the bound and arcs looked at, summed over sources; ``searches`` has
    (search, slot, start, end) of every task in microseconds, searches numbered as they ran; ``pruned`` counts rows that a refreshed bound dropped.
    """

    trace: list[int] = field(default_factory=list)
    limits: list[int] = field(default_factory=list)
    rounds: dict = field(default_factory=dict)
    sigma: int | None = None
    certified: bool = True
    crossings: str = "closure"
    refreshes: int = 0
    bridges_live: int = 0
    bridges_pruned: int = 0
    settled: int = 0
    relaxed: int = 0
    pruned: int = 0
    searches: list[tuple[int, int, int, int]] = field(default_factory=list)
    searched: int = 0

    def search_seconds(self) -> float:
        """Time from the first task's start to the last one's end, summed over searches."""
        spans = [[s[2:] for s in self.searches if s[0] == n] for n in range(self.searched)]
        return sum(max(end for _, end in x) - min(start for start, _ in x) for x in spans if x) / 1e6

    def idle_share(self, parallelism: int) -> float:
        """Share of slot time that waits for the slowest task of its search, from the tasks' own clocks."""
        busy = span = 0
        for wave in {s[0] for s in self.searches}:
            times = [end - start for w, _, start, end in self.searches if w == wave]
            busy, span = busy + sum(times), span + max(times) * parallelism
        return 1 - busy / span if span else 0.0


@dataclass(frozen=True)
class Spec:
    """A join's operands and options."""

    net: Network
    r: DataFrame
    s: DataFrame
    k: int | None
    tree: Hierarchy | None
    crossings: str
    threshold: str
    engine: str
    schedule: str
    parallelism: int
    reuse_routes: bool
    stop_by_weight: bool
    report: JoinReport
    detailed: bool
    task_edges: int
    sources_per_task: int


def top_pairs(pairs: DataFrame, k: int | None) -> DataFrame:
    """Distinct pairs at their least distance; with k the first k by (d, u, v)."""
    best = pairs.groupBy("u", "v").agg(F.min("d").alias("d"))
    return best.orderBy("d", "u", "v").limit(k) if k is not None else best


def trim_pairs(pairs: DataFrame, k: int, by: str = "gp") -> DataFrame:
    """The first k distinct pairs of every part."""
    best = pairs.groupBy(by, "u", "v").agg(F.min("d").alias("d"))
    return best.withColumn("n", F.row_number().over(Window.partitionBy(by).orderBy("d", "u", "v"))).where(F.col("n") <= k).drop("n")


def kth_distance(pairs: DataFrame, k: int | None, *, distinct: bool = False) -> int | None:
    """The k-th least distance of distinct pairs, None if there are fewer: an upper bound of the answer's."""
    if not k:
        return None
    first = pairs.select("d").orderBy("d").limit(k) if distinct else top_pairs(pairs, k)
    row = first.agg(F.count(F.lit(1)).alias("n"), F.max("d").alias("d")).first()
    return row["d"] if row["n"] == k else None


def pilot_bound(net: Network, r: DataFrame, s: DataFrame, k: int | None) -> int | None:
    """k-th lightest direct edge from R to S: the length of k real paths, hence a valid bound."""
    direct = net.arcs.join(r.select(F.col("id").alias("a")), "a", "left_semi").join(s.select(F.col("id").alias("b")), "b", "left_semi")
    return kth_distance(direct.select(F.col("a").alias("u"), F.col("b").alias("v"), F.col("w").alias("d")), k)


def unpartitioned_pairs(net: Network, r: DataFrame, s: DataFrame, bound: int, report: JoinReport | None = None) -> DataFrame:
    """Baseline without parts: the frontier grows from every vertex of R within the bound."""
    seeds = r.select(F.col("id").alias("src"), F.col("id").alias("node"), F.lit(0).cast("long").alias("d"))
    best = relax(net.arcs, seeds, bound, report=report.rounds if report else None)
    return best.join(s.select(F.col("id").alias("node")), "node", "left_semi").select(F.col("src").alias("u"), F.col("node").alias("v"), "d")


# Searches inside parts

#: Roles of a row: an arc (a, b, w), a target in S, a border vertex to report, a source (its start cost in w).
ARC, IN_S, BORDER, SOURCE = range(4)
_FOUND = "gp long, kind string, x long, y long, d long"


Columns = dict[int, tuple[np.ndarray, ...]]


def _by_turn(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, int, Columns]]:
    """Part, slot and rows by role, of one part and chunk after another; they come sorted by turn. What is handed on is kept nowhere here."""
    held, now = {}, None
    for batch in batches:
        turns = batch.column("turn").to_numpy()
        cuts = np.concatenate([[0], np.flatnonzero(turns[1:] != turns[:-1]) + 1, [len(turns)]]) if len(turns) else []
        for at, end in zip(cuts[:-1], cuts[1:]):
            if now is not None and turns[at] != now[0]:
                yield now[1], now[2], _joined_columns(held)
            now = turns[at], batch.column("gp")[int(at)].as_py(), batch.column("slot")[int(at)].as_py()
            _add_columns(held, batch.slice(int(at), int(end - at)), "a", "b", "w")
    if held:
        yield now[1], now[2], _joined_columns(held)


def _add_columns(held: dict[int, list], rows: pa.RecordBatch, *columns: str) -> None:
    """Copies of the columns of the rows of each role that has rows, nulls as 0."""
    role = rows.column("role").to_numpy()
    every = [pc.fill_null(rows.column(c), 0).to_numpy() for c in columns]
    for r in np.unique(role):
        on = role == r
        held.setdefault(int(r), []).append([c[on] for c in every])


def _joined_columns(held: dict[int, list]) -> Columns:
    """One array for each column of a role, pieces dropped as they are joined; ``held`` is empty afterwards."""
    out = {}
    while held:
        role, pieces = held.popitem()
        columns = [list(c) for c in zip(*pieces)]
        del pieces
        for n in range(len(columns)):
            columns[n] = np.concatenate(columns[n])
        out[role] = tuple(columns)
    return out


def _handed(gp: int, kind: str, x: np.ndarray, y: np.ndarray, d: np.ndarray) -> Iterator[pa.RecordBatch]:
    for at in range(0, len(d), HANDED):
        n = len(some := d[at : at + HANDED])
        yield pa.RecordBatch.from_arrays([pa.array(np.full(n, gp)), pa.repeat(kind, n), pa.array(x[at : at + n]), pa.array(y[at : at + n]), pa.array(some)], names=_SCHEMA.names)


def _kernel(kinds: tuple[str, str], k: int | None, bound: int, shared: bool):
    """Search part after part of a slot. ``kinds`` name hits in S and at the border; with k the hits in S shrink the bound, over all parts of the slot if ``shared``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best, started, slot = kernels.BestPairs(k, bound), time.time_ns() // 1000, 0
        for gp, slot, of in _by_turn(batches):
            if SOURCE not in of:
                continue
            if not shared:
                best = kernels.BestPairs(k, bound)
            none = (np.empty(0, np.int64),) * 3
            named, _, costs = of[SOURCE]
            g, work = kernels.LocalGraph(*of.pop(ARC, none), named), kernels.Work()
            g.order, order = None, np.argsort(named, kind="stable")
            marks = {kind: g.mask(of.get(role, none)[0]) for kind, role in zip(kinds, (IN_S, BORDER))}
            search = kernels.reach if k else kernels.reach_batches
            got = search(g, g.local(named[order]), costs[order], marks, best, counted=kinds[0] if k else None, work=work)
            for found in [got] if k else got:  # without k what is found is handed on batch by batch
                for kind, (x, y, d) in found.items():
                    yield from _handed(gp, kind, g.ids[x], g.ids[y], d)
            yield pa.RecordBatch.from_pylist([{"gp": gp, "kind": "work", "x": work.settled, "y": work.relaxed, "d": 0}], schema=_SCHEMA)
        yield pa.RecordBatch.from_pylist([{"gp": slot, "kind": "slot", "x": started, "y": time.time_ns() // 1000, "d": slot}], schema=_SCHEMA)

    return run


_SCHEMA = pa.schema([("gp", pa.int64()), ("kind", pa.string()), ("x", pa.int64()), ("y", pa.int64()), ("d", pa.int64())])


def _places(spec: Spec, parts: list[int], sources: DataFrame, of_slot: dict[int, tuple[int, int]] | None) -> tuple[DataFrame, int]:
    """(gp, chunk, chunks, slot, turn) of every part to search, and the number of slots. Parts with many sources are dealt in chunks, each with a copy of the part.

    In the pool, a part has the slot of its step in the schedule; else parts go round all slots, the largest first.
    """
    nodes, limit = spec.tree.parts, spec.sources_per_task
    chunks = dict.fromkeys(parts, 1)
    if max((nodes[g]["n_vertices"] for g in parts), default=0) > limit:
        for row in sources.groupBy("gp").agg(F.count(F.lit(1)).alias("n")).collect():  # a row for each part
            chunks[row["gp"]] = -(-row["n"] // limit)
    units = [(g, c) for g in sorted(parts, key=lambda g: (-nodes[g]["n_edges"], g)) for c in range(chunks.get(g, 1))]
    if of_slot is not None:
        slots = spec.parallelism
        units.sort(key=lambda u: (of_slot[u[0]][1], u))
        where = [(of_slot[g][0] + c) % slots for g, c in units]
    else:
        slots = max(1, min(len(units), default_slots(spec.net.vertices.sparkSession)))
        where = [i % slots for i in range(len(units))]
    rows = [(g, c, chunks.get(g, 1), slot, turn) for turn, ((g, c), slot) in enumerate(zip(units, where))]
    return spec.net.vertices.sparkSession.createDataFrame(rows, "gp long, chunk int, chunks int, slot int, turn int"), slots


def search_parts(spec: Spec, parts: list[int], arcs: DataFrame, targets: DataFrame, sources: DataFrame, kinds: tuple[str, str], bound: int, *, k: int | None = None, of_slot: dict[int, tuple[int, int]] | None = None) -> DataFrame:
    """(gp, kind, x, y, d): least costs within the bound inside parts, from sources to vertices of S and border vertices; written.

    ``arcs`` (gp, a, b, w), ``targets`` (gp, role, id), ``sources`` (gp, id, cost). One shuffle brings the parts of a slot together; its task holds one part at a time.
    Where the bound leaves more than ``task_edges`` edges in a part the frontier engine relaxes all parts by joins instead.
    """
    report = spec.report
    report.searched += 1
    if spec.stop_by_weight:
        arcs = arcs.where(F.col("w") <= bound)
    largest = max((spec.tree.parts[g]["n_edges"] for g in parts), default=0)
    if spec.engine == "auto" and largest > spec.task_edges and spec.stop_by_weight:  # what the bound leaves of a part may fit
        largest = (arcs.groupBy("gp").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] or 0) / (1 if spec.net.directed else 2)
    if spec.engine == "frontier" or (spec.engine == "auto" and largest > spec.task_edges):
        best = relax(arcs.select("a", "b", "w"), sources.select(F.col("id").alias("src"), F.col("id").alias("node"), F.col("cost").alias("d")), bound, report=report.rounds, early_stop=spec.stop_by_weight)
        hit = best.join(sources.select(F.col("id").alias("src"), "gp"), "src").join(targets.select(F.col("id").alias("node"), "role"), "node")
        kind = F.when(F.col("role") == IN_S, kinds[0]).otherwise(kinds[1])
        report.settled += report.rounds.pop("settled", 0)
        return materialise(hit.select("gp", kind.alias("kind"), F.col("src").alias("x"), F.col("node").alias("y"), "d"), f"found-{kinds[0]}")
    plan, slots = _places(spec, parts, sources, of_slot)
    near = F.broadcast(plan) if len(parts) <= BROADCAST_PARTS else plan
    null = F.lit(None).cast("long")
    own = F.pmod(F.xxhash64("id"), F.col("chunks")) == F.col("chunk")
    columns = lambda role, a, b, w: ["slot", "turn", "gp", F.lit(role).cast("tinyint").alias("role"), a.alias("a"), b.alias("b"), w.alias("w")]
    rows = arcs.join(near, "gp").select(*columns(ARC, F.col("a"), F.col("b"), F.col("w")))
    rows = rows.unionByName(targets.join(near, "gp").select("slot", "turn", "gp", F.col("role").cast("tinyint").alias("role"), F.col("id").alias("a"), null.alias("b"), null.alias("w")))
    rows = rows.unionByName(sources.join(near, "gp").where(own).select(*columns(SOURCE, F.col("id"), null, F.col("cost"))))
    dealt = rows.repartitionById(slots, F.col("slot")).sortWithinPartitions("turn")
    found = dealt.mapInArrow(_kernel(kinds, k, bound, spec.threshold != "local"), _FOUND)
    on = lambda c, kind: F.sum(F.when(F.col("kind") == kind, F.col(c)))
    kept, seen = counted(found, f"found-{kinds[0]}", settled=on("x", "work"), relaxed=on("y", "work"))
    report.settled, report.relaxed = report.settled + seen.get("settled", 0), report.relaxed + seen.get("relaxed", 0)
    if spec.detailed:
        report.searches += [(report.searched - 1, r["gp"], r["x"], r["y"]) for r in kept.where("kind = 'slot'").collect()]  # a row for each task
    return kept


def _kind(found: DataFrame, kind: str, x: str, y: str) -> DataFrame:
    return found.where(F.col("kind") == kind).select("gp", F.col("x").alias(x), F.col("y").alias(y), "d")


def leaf_members(tree: Hierarchy, ids: DataFrame) -> DataFrame:
    """(gp, id) of those vertices in their leaves."""
    return tree.assign.select("gp", "id").join(ids.select("id"), "id", "left_semi")


def rim(tree: Hierarchy) -> DataFrame:
    """(gp, id): border vertices of every leaf."""
    return tree.cross.select(F.col("leaf_a").alias("gp"), F.col("a").alias("id")).distinct()


def _steps(spec: Spec) -> dict[int, tuple[int, int]] | None:
    """Slot and turn of every part in the pool."""
    return {s.gp: (s.slot, s.turn) for s in plan_steps(spec.tree, spec.parallelism)} if spec.schedule == "pool" else None


def leaf_search(spec: Spec, bound: int, *, sources: str, k: int | None, paths: bool) -> DataFrame:
    """All leaves: from R, pairs and (with ``paths``) routes to the border; from the border, distances to S (bs) and to each other (bb)."""
    tree = spec.tree
    targets = leaf_members(tree, spec.s).withColumn("role", F.lit(IN_S))
    if paths:
        targets = targets.unionByName(rim(tree).withColumn("role", F.lit(BORDER)))
    start = (leaf_members(tree, spec.r) if sources == "r" else rim(tree)).withColumn("cost", F.lit(0).cast("long"))
    kinds = ("pair", "route") if sources == "r" else ("bs", "bb")
    found = search_parts(spec, [r["gp"] for r in tree.leaves], tree.arcs, targets, start, kinds, bound, k=k, of_slot=_steps(spec))
    return found if sources == "r" else found.where("kind <> 'bb' OR x <> y")


def leaf_tables(net: Network, tree: Hierarchy, r: DataFrame, s: DataFrame, bound: int) -> DataFrame:
    """gp, kind (pair, route, bs, bb), x, y, d: everything the leaves know within a bound."""
    spec = _spec(net, r, s, None, tree)
    rows = leaf_search(spec, bound, sources="r", k=None, paths=True).unionByName(leaf_search(spec, bound, sources="border", k=None, paths=True))
    return rows.where("kind IN ('pair', 'route', 'bs', 'bb')")


# What crosses between parts


def _live(spec: Spec, cross: DataFrame, bound: int) -> DataFrame:
    """Cross-edges that the bound leaves alive; all of them in the ablation without the early stop."""
    if spec.detailed:
        n, m = cross.agg(F.count(F.lit(1)), F.count_if(F.col("w") <= bound)).first()
        m = m if spec.stop_by_weight else n
        spec.report.bridges_live, spec.report.bridges_pruned = spec.report.bridges_live + m, spec.report.bridges_pruned + n - m
    return cross.where(F.col("w") <= bound) if spec.stop_by_weight else cross


def closed_pairs(spec: Spec, routes: DataFrame, border: DataFrame, bound: int) -> DataFrame:
    """Pairs over any number of cross-edges: routes relax over the overlay of border distances and cross-edges, then meet the border-S table."""
    live = _live(spec, spec.tree.cross, bound).select("a", "b", "w")
    overlay, seen = counted(_kind(border, "bb", "a", "b").select("a", "b", F.col("d").alias("w")).unionByName(live).groupBy("a", "b").agg(F.min("w").alias("w")), "overlay")
    if spec.engine != "frontier" and seen["n"] <= min(OVERLAY_EDGES, spec.task_edges):
        return _meet(_overlay_search(spec, overlay, routes, bound), _kind(border, "bs", "node", "v"), bound)
    reached = relax(overlay, routes.select(F.col("u").alias("src"), F.col("border").alias("node"), "d"), bound, report=spec.report.rounds, early_stop=spec.stop_by_weight)
    spec.report.settled += spec.report.rounds.pop("settled", 0)
    return _meet(reached.select(F.col("src").alias("u"), "node", "d"), _kind(border, "bs", "node", "v"), bound)


def _overlay_search(spec: Spec, overlay: DataFrame, routes: DataFrame, bound: int) -> DataFrame:
    """(u, node, d): what R reaches over an overlay that fits a task: every task has a copy and a share of R, whose routes are where its searches start; written."""
    slots = default_slots(overlay.sparkSession)
    copies = overlay.select(F.explode(F.sequence(F.lit(0), F.lit(slots - 1))).alias("slot"), F.lit(ARC).cast("tinyint").alias("role"), "a", "b", "w")
    starts = routes.select(F.pmod(F.xxhash64("u"), F.lit(slots)).cast("int").alias("slot"), F.lit(SOURCE).cast("tinyint").alias("role"), F.col("u").alias("a"), F.col("border").alias("b"), F.col("d").alias("w"))
    found = copies.unionByName(starts).repartitionById(slots, F.col("slot")).mapInArrow(_overlay_kernel(bound), _FOUND)
    on = lambda c: F.sum(F.when(F.col("kind") == "work", F.col(c)))
    kept, seen = counted(found, "reached", settled=on("x"), relaxed=on("y"))
    spec.report.settled, spec.report.relaxed = spec.report.settled + seen["settled"], spec.report.relaxed + seen["relaxed"]
    return _kind(kept, "over", "u", "node").drop("gp")


def _overlay_kernel(bound: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = {}
        for batch in batches:
            _add_columns(held, batch, "a", "b", "w")
        if SOURCE not in held:
            return
        of = _joined_columns(held)
        named, borders, costs = of[SOURCE]
        g, work = kernels.LocalGraph(*of.pop(ARC, (np.empty(0, np.int64),) * 3), borders), kernels.Work()
        ids, row = np.unique(named, return_inverse=True)
        order = np.argsort(row, kind="stable")
        row, start, cost = row[order], np.searchsorted(g.ids, borders[order]), costs[order]
        for at in range(0, len(ids), OVERLAY_SOURCES):
            low, high = np.searchsorted(row, [at, at + OVERLAY_SOURCES])
            for found in kernels.reach_batches(g, start[low:high], cost[low:high], {"over": np.ones(len(g.ids), bool)}, kernels.BestPairs(None, bound), work=work, rows=row[low:high] - at):
                x, y, d = found["over"]
                yield from _handed(0, "over", ids[at + x], g.ids[y], d)
        yield pa.RecordBatch.from_pylist([{"gp": 0, "kind": "work", "x": work.settled, "y": work.relaxed, "d": 0}], schema=_SCHEMA)

    return run


def one_cross_pairs(spec: Spec, routes: DataFrame, border: DataFrame, bound: int) -> DataFrame:
    """Pairs over exactly one cross-edge, far side inside the leaf of its head."""
    live = _live(spec, spec.tree.cross, bound).select("a", "b", "w")
    seeds = routes.select("u", F.col("border").alias("a"), "d").join(live, "a").select("u", F.col("b").alias("node"), (F.col("d") + F.col("w")).alias("d")).where(F.col("d") <= bound).groupBy("u", "node").agg(F.min("d").alias("d"))
    return _meet(seeds, _kind(border, "bs", "node", "v"), bound)


def _meet(near: DataFrame, far: DataFrame, bound: int) -> DataFrame:
    both = near.join(far.select("node", "v", F.col("d").alias("d2")), "node").where(F.col("d") + F.col("d2") <= bound)
    return both.groupBy("u", "v").agg(F.min(F.col("d") + F.col("d2")).alias("d"))


def level_pairs(spec: Spec, routes: DataFrame, pairs: DataFrame, bound: int, refresh) -> DataFrame:
    """The faithful merge: the parts of a wave at once, children before parents.

    At a part, near-side routes reach its cross-edges' tails; from the heads the sibling is searched with the least cost so far as a start; hits in S
    combine with every route at the tail. Routes are lifted to borders that parents need. A wave whose parts are all separated by more than the bound is skipped.
    """
    tree, at = spec.tree, spec.tree.assign.select("id", "gp")
    spark = spec.net.vertices.sparkSession
    steps = plan_steps(tree, spec.parallelism)
    known = routes.select("border", "u", "d").groupBy("border", "u").agg(F.min("d").alias("d"))
    last = max(s.wave for s in steps)
    for wave in sorted({s.wave for s in steps} - {0}):
        mine = [s for s in steps if s.wave == wave and (not spec.stop_by_weight or (tree.parts[s.gp]["sep"] or UNBOUNDED) <= bound) and tree.parts[s.gp]["sep"] is not None]
        if not mine:
            continue
        kids = [c for s in mine for c in (2 * s.gp, 2 * s.gp + 1) if c in tree.parts]
        # which child of this wave holds a leaf or a lowest common part: rows of the tree, not of the network
        child = set(kids)
        held = []
        for g in tree.parts:
            up = g
            while up and up not in child:
                up //= 2
            if up:
                held.append((g, up))
        members = spark.createDataFrame(held, "gp long, part long")
        members = F.broadcast(members) if len(held) <= BROADCAST_PARTS else members
        here = tree.cross.where(F.col("gp").isin([s.gp for s in mine])) if len(mine) <= 1000 else tree.cross.join(spark.createDataFrame([(s.gp,) for s in mine], "gp long"), "gp", "left_semi")
        live = _live(spec, here, bound).select("a", "b", "w", F.col("leaf_b").alias("gp")).join(members, "gp").select("part", "a", "b", "w")
        over = known.withColumnRenamed("border", "a").join(live, "a").select("part", "u", "b", (F.col("d") + F.col("w")).alias("d")).where(F.col("d") <= bound).groupBy("part", "u", "b").agg(F.min("d").alias("d"))
        over = materialise(over, "level-over")
        heads = over.groupBy("part", "b").agg(F.min("d").alias("cost")).select(F.col("part").alias("gp"), F.col("b").alias("id"), "cost")
        inside = lambda df: df.join(members, "gp").drop("gp").withColumnRenamed("part", "gp")  # noqa: E731, B023
        arcs = inside(tree.arcs).unionByName(inside(tree.cross.select("gp", "a", "b", "w")))
        upper = tree.border.where(~F.col("gp").isin([s.gp for s in steps if s.wave <= wave])) if len(steps) <= 1000 else tree.border
        targets = inside(at.join(spec.s.select("id"), "id", "left_semi")).withColumn("role", F.lit(IN_S)).unionByName(inside(at.join(upper.select("id").distinct(), "id", "left_semi")).withColumn("role", F.lit(BORDER)))
        of_slot = {c: (s.slot, s.turn) for s in mine for c in (2 * s.gp, 2 * s.gp + 1)} if spec.schedule == "pool" else None
        far = search_parts(spec, kids, arcs, targets, heads, ("hs", "hb"), bound, of_slot=of_slot)
        far = far.where("kind IN ('hs', 'hb')").join(heads.select(F.col("id").alias("x"), "cost"), "x").select("kind", F.col("x").alias("b"), "y", (F.col("d") - F.col("cost")).alias("d2"))
        hits = over.join(far.where("kind = 'hs'").select("b", F.col("y").alias("v"), "d2"), "b").select("u", "v", (F.col("d") + F.col("d2")).alias("d")).where(F.col("d") <= bound)
        pairs = pairs.unionByName(hits)
        if spec.k is not None:
            pairs = materialise(top_pairs(pairs, spec.k), "level-pairs")
            bound = refresh(pairs)
        if wave == last:
            break
        lifted = over.join(far.where("kind = 'hb'").select("b", F.col("y").alias("border"), "d2"), "b").select("border", "u", (F.col("d") + F.col("d2")).alias("d"))
        known = materialise(known.unionByName(lifted).where(F.col("d") <= bound).groupBy("border", "u").agg(F.min("d").alias("d")), "level-routes")
    return pairs.groupBy("u", "v").agg(F.min("d").alias("d"))


# What passes hubs

#: Roles of a row that meets over hubs: hub to hub, R to hub, hub to S, R to S without hubs.
BETWEEN, NEAR, FAR, OWN = range(4)


def hub_vertices(spec: Spec, bound: int) -> list[int]:
    """The vertices with the most arcs within the bound, HUB_ARCS at least; at most HUBS rows to the driver. Any choice is right: hubs decide where paths are cut, not which count."""
    ends = spec.net.edges.where(F.col("w") <= bound).select(F.explode(F.array("src", "dst")).alias("id"))
    most = ends.groupBy("id").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= HUB_ARCS)
    return [r["id"] for r in most.orderBy(F.desc("n"), "id").limit(HUBS).collect()]


def hub_pairs(spec: Spec, bound: int, hubs: list[int]) -> DataFrame:
    """All pairs within the bound where hubs have many arcs: a shortest path passes none, and is found without them, or has a first and a last one.

    One join on the network without hubs, from R and the vertices behind hubs to S and the vertices before hubs, gives the pairs of the first kind and all distances
    of R to first hubs, between hubs, and of last hubs to S. These meet in tasks that own pairs (u, v), where a hub's S are sorted by distance; nothing is written or shuffled for each pair.
    """
    is_hub = lambda c: F.col(c).isin(hubs)
    free = lambda df, *ends: df.where(~is_hub(ends[0])) if len(ends) == 1 else df.where(~is_hub(ends[0]) & ~is_hub(ends[1]))
    tree, arcs = spec.tree, spec.net.arcs.where(F.col("w") <= bound).groupBy("a", "b").agg(F.min("w").alias("w"))
    touching = materialise(arcs.where(is_hub("a") | is_hub("b")), "hub-arcs")
    into = free(touching, "a").select(F.col("a").alias("v"), F.col("b").alias("hub"), "w")
    out = free(touching, "b").select(F.col("b").alias("u"), F.col("a").alias("hub"), "w")
    r, s = spec.r.select("id"), spec.s.select("id")
    starts = materialise(free(r, "id").withColumn("own", F.lit(True)).unionByName(out.select(F.col("u").alias("id"), F.lit(False).alias("own"))).groupBy("id").agg(F.max("own").alias("own")), "hub-starts")
    ends = materialise(free(s, "id").withColumn("own", F.lit(True)).unionByName(into.select(F.col("v").alias("id"), F.lit(False).alias("own"))).groupBy("id").agg(F.max("own").alias("own")), "hub-ends")
    bare = replace(tree, arcs=free(tree.arcs, "a", "b"), cross=free(tree.cross, "a", "b"))
    found = _within(replace(spec, r=starts.select("id"), s=ends.select("id"), tree=bare, sources_per_task=max(spec.sources_per_task, HUBLESS_SOURCES)), bound, hubs=())
    found = found.join(starts.select(F.col("id").alias("u"), F.col("own").alias("in_r")), "u").join(ends.select(F.col("id").alias("v"), F.col("own").alias("in_s")), "v")
    found = materialise(found, "hubless")
    least = lambda df, a, b: df.where(F.col("d") <= bound).groupBy(F.col(a).alias("a"), F.col(b).alias("b")).agg(F.min("d").alias("d"))
    itself = lambda df: df.where(is_hub("id")).select(F.col("id").alias("a"), F.col("id").alias("b"), F.lit(0).cast("long").alias("d"))
    length = F.col("d") + F.col("w")
    near = least(found.where("in_r").join(into, "v").select("u", "hub", length.alias("d")), "u", "hub").unionByName(itself(r))
    far = least(found.where("in_s").join(out, "u").select("hub", "v", length.alias("d")), "hub", "v").unionByName(itself(s))
    near, nears = counted(near, "hub-near")
    far, fars = counted(far, "hub-far")
    # hub to hub: what comes from a hub goes into the next one
    heads = found.join(out, "u").select("v", F.col("hub").alias("a"), length.alias("d")).groupBy("v", "a").agg(F.min("d").alias("d"))
    between = heads.join(into, "v").select("a", F.col("hub").alias("b"), length.alias("d")).where("a <> b")
    between = least(between.unionByName(touching.where(is_hub("a") & is_hub("b")).select("a", "b", F.col("w").alias("d"))), "a", "b")
    across, down = max(default_slots(r.sparkSession), -(-nears["n"] // MEET_SOURCES)), max(1, -(-fars["n"] // MEET_ROWS))
    of_u, of_v = F.pmod(F.xxhash64("a"), F.lit(across)), F.pmod(F.xxhash64("b"), F.lit(down))
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("at")
    row = lambda df, role, slot: df.select(slot.cast("int").alias("slot"), F.lit(role).cast("tinyint").alias("role"), "a", "b", "d")
    rows = row(between.select("*", every(across * down)), BETWEEN, F.col("at"))
    rows = rows.unionByName(row(near.select("*", every(down)), NEAR, of_u * down + F.col("at")))
    rows = rows.unionByName(row(far.select("*", every(across)), FAR, F.col("at") * down + of_v))
    rows = rows.unionByName(row(found.where("in_r AND in_s").select(F.col("u").alias("a"), F.col("v").alias("b"), "d"), OWN, of_u * down + of_v))
    return rows.repartitionById(across * down, F.col("slot")).mapInArrow(_meet_kernel(bound), "u long, v long, d long")


def _meet_kernel(bound: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, none = {}, (np.empty(0, np.int64),) * 3
        for batch in batches:
            _add_columns(held, batch, "a", "b", "d")
        rows = _joined_columns(held)
        between, near, far, own = (rows.get(role, none) for role in (BETWEEN, NEAR, FAR, OWN))
        hubs = np.unique(np.concatenate([between[0], between[1], near[1], far[0]]))
        at = lambda ids: np.searchsorted(hubs, ids)
        known = kernels.all_distances(len(hubs), at(between[0]), at(between[1]), between[2])
        some, n = [], 0
        for u, v, d in kernels.meet((near[0], at(near[1]), near[2]), (at(far[0]), far[1], far[2]), own, known, bound):
            some.append((u, v, d))
            n += len(d)
            if n >= HANDED:
                yield from _pair_batches(some)
                some, n = [], 0
        yield from _pair_batches(some)

    return run


def _pair_batches(some: list[tuple[int, np.ndarray, np.ndarray]]) -> Iterator[pa.RecordBatch]:
    if some:
        u = np.repeat(np.array([x[0] for x in some], np.int64), [len(x[2]) for x in some])
        v, d = (np.concatenate([x[i] for x in some]) for i in (1, 2))
        for at in range(0, len(u), HANDED):
            yield pa.RecordBatch.from_arrays([pa.array(c[at : at + HANDED]) for c in (u, v, d)], names=["u", "v", "d"])


# The joins


def _within(spec: Spec, bound: int, hubs: Sequence[int] | None = None) -> DataFrame:
    """The answer among paths of at most ``bound``. ``hubs``: those to cut paths at, else they are looked for."""
    report, tree, k = spec.report, spec.tree, spec.k
    if tree is None:
        pairs = top_pairs(unpartitioned_pairs(spec.net, spec.r, spec.s, bound, report), k)
        report.settled += report.rounds.pop("settled", 0)
        return pairs
    report.sigma = tree.sigma
    if hubs is None and k is None and not spec.net.directed and spec.crossings == "closure" and spec.engine != "frontier" and spec.reuse_routes and spec.stop_by_weight and sum(r["n_edges"] for r in tree.parts.values() if r["gp"] == 1) > HUB_EDGES:
        hubs = hub_vertices(spec, bound)
    if hubs:
        return hub_pairs(spec, bound, hubs)

    def refresh(pairs: DataFrame, distinct: bool = False) -> int:
        nonlocal bound
        if k:
            report.refreshes += 1
            known = kth_distance(pairs, k, distinct=distinct)
            if spec.detailed and known is not None and known < bound:
                report.pruned += pairs.where(F.col("d") > known).count()
            bound = min(bound, known if known is not None else bound)
            report.trace.append(min(report.trace[-1], known if known is not None else report.trace[-1]))
        return bound

    def crosses() -> bool:
        return spec.crossings != "none" and tree.sigma is not None and (tree.sigma <= bound or not spec.stop_by_weight)

    found = leaf_search(spec, bound, sources="r", k=k, paths=crosses() and spec.reuse_routes)
    pairs = _kind(found, "pair", "u", "v").select("u", "v", "d")
    refresh(pairs, distinct=True)  # a pair has one leaf and one source there
    if not crosses():
        return _top(pairs.where(F.col("d") <= bound), k)
    near = found if spec.reuse_routes else leaf_search(spec, bound, sources="r", k=None, paths=True)  # ablation: search the near side once more
    routes, pairs = _kind(near, "route", "u", "border").where(F.col("d") <= bound), pairs.where(F.col("d") <= bound)
    if spec.crossings == "per_level":
        return _top(level_pairs(spec, routes, pairs, bound, refresh), k)
    border = leaf_search(spec, bound, sources="border", k=None, paths=True)
    over = closed_pairs if spec.crossings == "closure" else one_cross_pairs
    return top_pairs(pairs.unionByName(over(spec, routes, border, bound)), k)


def _top(distinct_pairs: DataFrame, k: int | None) -> DataFrame:
    return distinct_pairs.orderBy("d", "u", "v").limit(k) if k is not None else distinct_pairs


def _join(spec: Spec, theta: int | None) -> DataFrame:
    report, k = spec.report, spec.k
    bound = UNBOUNDED if theta is None else theta
    if k is not None and spec.threshold == "pilot+wave":
        known = pilot_bound(spec.net, spec.r, spec.s, k)
        bound = min(bound, known if known is not None else bound)
    report.trace.append(bound)
    report.crossings = spec.crossings
    if bound == UNBOUNDED and k is not None:
        result = _deepen(spec)
    else:
        result = _within(spec, bound)
    if spec.tree is not None and spec.crossings != "closure":
        reach = (kth_distance(result, k) if k else theta) or bound
        report.certified = report.sigma is None or reach < report.sigma * (1 if spec.crossings == "none" else 2)
    return result


def _deepen(spec: Spec) -> DataFrame:
    """Without a known bound: the radius grows until k pairs lie inside it or nothing more can be reached, so that no search runs unlimited."""
    limit, total = spec.net.edges.agg(F.percentile_approx("w", 0.5), F.sum("w")).first()
    limit, total = limit or 1, total or 1
    while limit < total:
        spec.report.limits.append(limit)
        with passing(spec.net.vertices.sparkSession) as keep:
            result, seen = counted(_within(spec, limit), "within")
            keep(result)
        if seen["n"] >= spec.k:
            return result
        limit *= 4
    spec.report.limits.append(total)
    return _within(spec, total)


def _spec(net: Network, r: DataFrame, s: DataFrame, k: int | None, hierarchy: Hierarchy | None, *, crossings: str = "closure", threshold: str = "none", engine: str = "auto", schedule: str = "waves", parallelism: int = 8, reuse_routes: bool = True,
          stop_by_weight: bool = True, report: JoinReport | None = None, task_edges: int = TASK_EDGES, sources_per_task: int = SOURCES_PER_TASK) -> Spec:
    for name, value, known in (("crossings", crossings, ("none", "one", "per_level", "closure")), ("threshold", threshold, ("none", "wave", "pilot+wave", "local", "auto")), ("engine", engine, ("auto", "task", "frontier")), ("schedule", schedule, ("waves", "pool"))):
        if value not in known:
            raise ValueError(f"unknown {name} {value!r}")
    if (hierarchy is None or crossings == "none") and not (reuse_routes and stop_by_weight):
        raise ValueError("routes and the early stop belong to merges: they need a hierarchy and crossings")
    if parallelism < 1:
        raise ValueError("parallelism must be at least 1")
    if threshold == "auto":
        threshold = "local" if hierarchy is not None and len(hierarchy.leaves) <= 3 else "pilot+wave"
    return Spec(net, r, s, k, hierarchy, crossings, threshold, engine, schedule, parallelism, reuse_routes, stop_by_weight, report or JoinReport(), report is not None, task_edges, sources_per_task)


def _checked(k: int | None, theta: int | None, r: DataFrame, s: DataFrame, allow_unbounded: bool) -> None:
    if k is None and theta is None and not allow_unbounded:
        raise ValueError("neither k nor theta given: that asks for all reachable pairs; pass allow_unbounded=True")
    if (k is not None and k < 0) or (theta is not None and theta < 0):
        raise ValueError("k and theta must not be negative")
    assert_disjoint(r, s)


def distance_join(net: Network, r: DataFrame, s: DataFrame, theta: int | None, *, hierarchy: Hierarchy | None = None, allow_unbounded: bool = False, **options) -> DataFrame:
    """All pairs (u of R, v of S, d) at network distance d <= theta, paths run from u to v.

    Options: ``crossings``; ``engine``: task (parts inside tasks), frontier (iterated joins), or auto: tasks unless a part is too large for one;
    ``schedule``: waves (all cores), or pool (at most ``parallelism`` tasks at once, by ``schedule_plan``); ``reuse_routes`` and
    ``stop_by_weight`` off are ablations: the near side is searched again, and cross-edges beyond the bound are carried along; ``report`` collects what was done.
    """
    _checked(None, theta, r, s, allow_unbounded)
    return within_at(net, r, s, theta, hierarchy=hierarchy, **options)


def closest_pairs(net: Network, r: DataFrame, s: DataFrame, k: int | None, theta: int | None = None, *, hierarchy: Hierarchy | None = None, threshold: str = "pilot+wave", allow_unbounded: bool = False, **options) -> DataFrame:
    """The k pairs (u of R, v of S, d) smallest by (d, u, v), within theta if given; without k, the distance join.

    Fewer pairs are returned where fewer are reachable. ``threshold``: ``wave`` refreshes one bound between waves and shares it inside a task, ``pilot+wave`` also starts
    from direct R-S edges, ``local`` keeps a bound for each part, ``auto`` is local for up to three leaves, else pilot+wave. Other options as in ``distance_join``.
    """
    _checked(k, theta, r, s, allow_unbounded)
    return closest_at(net, r, s, k, theta, hierarchy=hierarchy, threshold=threshold, **options)


def within_at(net: Network, r: DataFrame, s: DataFrame, theta: int | None, *, hierarchy: Hierarchy | None = None, **options) -> DataFrame:
    """``distance_join`` without its checks; operands may share places, which are at distance 0."""
    return _join(_spec(net, r, s, None, hierarchy, **options), theta)


def closest_at(net: Network, r: DataFrame, s: DataFrame, k: int | None, theta: int | None = None, *, hierarchy: Hierarchy | None = None, threshold: str = "pilot+wave", **options) -> DataFrame:
    """``closest_pairs`` without its checks; operands may share places, which are at distance 0."""
    spec = _spec(net, r, s, k, hierarchy, threshold=threshold, **options)
    if k == 0:
        return r.select(F.col("id").alias("u"), F.col("id").alias("v"), F.lit(0).cast("long").alias("d")).limit(0)
    return _join(replace(spec, threshold="none") if k is None else spec, theta)
