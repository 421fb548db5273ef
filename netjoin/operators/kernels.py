"""What runs inside one task on the part of a network that fits it: best-first search and two-seed growth.

Pure functions over arrays; Spark ships them groups of Arrow columns. Nothing here knows about Spark.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from functools import cached_property
from heapq import heappop, heappush

import numpy as np

INFINITE = 1 << 60


class LocalGraph:
    """Adjacency of a group of arcs over dense local numbers, in arrays: the arcs of x are start[x] to start[x + 1]."""

    def __init__(self, a: np.ndarray, b: np.ndarray, w: np.ndarray, extra: np.ndarray | None = None):
        # each end's distinct vertices first, and local numbers of four bytes, keep what a large part needs at once small
        every = [np.unique(a), np.unique(b)] + ([extra] if extra is not None else [])
        self.ids = np.unique(np.concatenate(every))
        del every
        small = np.int32 if len(self.ids) < 1 << 31 else np.int64
        i = np.searchsorted(self.ids, a).astype(small)
        self.order = np.argsort(i, kind="stable")
        self.start = np.concatenate([[0], np.cumsum(np.bincount(i, minlength=len(self.ids)))]).astype(np.int64)
        del i
        self.to = np.searchsorted(self.ids, b).astype(small)[self.order]
        self.w = w[self.order]

    @cached_property
    def components(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Component of every vertex, numbered from 0, its place there, and the vertices of each component; directions do not count."""
        n = len(self.ids)
        i, j, label = np.repeat(np.arange(n, dtype=self.to.dtype), np.diff(self.start)), self.to, np.arange(n, dtype=self.to.dtype)
        while len(i):
            x, y = label[i], label[j]
            apart = x != y
            i, j, x, y = i[apart], j[apart], x[apart], y[apart]
            np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
            while not np.array_equal(up := label[label], label):
                label = up
        label = np.unique(label, return_inverse=True)[1] if n else label
        size = np.bincount(label) if n else label
        place, order = np.empty(n, np.int64), np.argsort(label, kind="stable")
        place[order] = np.arange(n) - np.repeat(np.cumsum(size) - size, size)
        return label, place, size

    def local(self, ids: Iterable[int]) -> np.ndarray:
        """Local numbers of those ids that are in the group."""
        wanted = np.asarray(list(ids) if not isinstance(ids, np.ndarray) else ids, np.int64)
        if not len(self.ids):
            return np.empty(0, np.int64)
        at = np.minimum(np.searchsorted(self.ids, wanted), len(self.ids) - 1)
        return at[self.ids[at] == wanted]

    def mask(self, ids: np.ndarray) -> np.ndarray:
        out = np.zeros(len(self.ids), bool)
        out[self.local(ids)] = True
        return out

    def search(self, start: int) -> Iterator[tuple[int, int]]:
        """(distance, vertex) of everything reachable, nearest first."""
        first, to, weight = self.start.tolist(), self.to.tolist(), self.w.tolist()
        heap, known = [(0, start)], [INFINITE] * len(self.ids)
        known[start] = 0
        while heap:
            d, x = heappop(heap)
            if d > known[x]:
                continue
            yield d, x
            for at in range(first[x], first[x + 1]):
                y, cost = to[at], d + weight[at]
                if cost < known[y]:
                    known[y] = cost
                    heappush(heap, (cost, y))


class BestPairs:
    """The k smallest distances seen so far, as a shrinking bound; without k the bound stays."""

    def __init__(self, k: int | None, bound: int):
        self.k, self.limit, self.kept = k, bound, np.empty(0, np.int64)

    def least(self, more: np.ndarray) -> np.ndarray:
        every = np.concatenate([self.kept, more])
        return np.partition(every, self.k - 1)[: self.k] if len(every) > self.k else every

    def within(self, more: np.ndarray) -> int:
        """The bound if these distances, which may still shrink, were added."""
        if not self.k or len(self.kept) + len(more) < self.k:
            return self.limit
        return min(self.limit, int(self.least(more).max()))

    def add(self, more: np.ndarray) -> None:
        if self.k:
            self.limit = self.within(more)
            self.kept = self.least(more)


#: Cells of the distance table of a search (16 MB): for each source of a batch as many as its component has vertices.
CELLS = 1 << 21


@dataclass
class Work:
    settled: int = 0
    relaxed: int = 0


Reached = dict[str, tuple[np.ndarray, np.ndarray, np.ndarray]]


def reach(g: LocalGraph, sources: np.ndarray, costs: np.ndarray, marks: dict[str, np.ndarray], best: BestPairs, counted: str | None = None, work: Work | None = None, rows: np.ndarray | None = None) -> Reached:
    """All batches of ``reach_batches`` together, within the last bound."""
    got = list(reach_batches(g, sources, costs, marks, best, counted, work, rows))
    joined = {kind: tuple(np.concatenate(c) for c in zip(*(batch[kind] for batch in got))) if got else (np.empty(0, np.int64),) * 3 for kind in marks}
    return {kind: tuple(c[d <= best.limit] for c in (x, y, d)) for kind, (x, y, d) in joined.items()}


def reach_batches(g: LocalGraph, sources: np.ndarray, costs: np.ndarray, marks: dict[str, np.ndarray], best: BestPairs, counted: str | None = None, work: Work | None = None, rows: np.ndarray | None = None) -> Iterator[Reached]:
    """Least costs from every source to the marked vertices within the bound, batch after batch: kind -> (source, vertex, cost), local numbers.

    Sources start with ``costs``. With ``rows``, ascending numbers from 0, a source is a row that starts from all its vertices in ``sources``, and the result has the rows. A batch of sources is relaxed together over a table, all improved cells in one step, until
    nothing improves; a row has cells for the components it starts in alone, as it stays there. Costs of the kind ``counted`` shrink the bound, also before they are final: each is the length of a real path.
    """
    work = work or Work()
    label, place, size = g.components
    named, rows = (sources, np.arange(len(sources))) if rows is None else (None, rows)
    if not len(rows):
        return
    # a block: a row's cells in one component
    blocks, block = np.unique(rows * len(size) + label[sources], return_inverse=True)
    order = np.argsort(block, kind="stable")
    block, sources, costs = block[order], sources[order], costs[order]
    of_row, cells = blocks // len(size), size[blocks % len(size)]
    ends = np.cumsum(cells)
    table = np.full(int(max(min(CELLS, ends[-1]), cells.max())), INFINITE, np.int64)
    low = 0
    while low < len(blocks):
        base = int(ends[low] - cells[low])
        high = max(low + 1, int(np.searchsorted(ends, base + CELLS, "right")))
        first, last = np.searchsorted(block, [low, high])
        x = sources[first:last]
        front = ends[block[first:last]] - cells[block[first:last]] - base + place[x]
        table[front] = costs[first:last]
        touched, limit = [(front, x, block[first:last])], best.limit
        hits = [front[marks[counted][x]]] if counted else []
        at = block[first:last]
        while True:
            if counted and len(hits[-1]):
                limit = best.within(table[np.concatenate(hits)])
            near = table[front] <= limit
            front, x, at = front[near], x[near], at[near]
            if not len(front):
                break
            begin, count = g.start[x], g.start[x + 1] - g.start[x]
            total = int(count.sum())
            work.relaxed += total
            of = np.repeat(np.arange(len(front)), count)
            arc = np.arange(total) + np.repeat(begin - np.cumsum(count) + count, count)
            to, shift = g.to[arc], front - place[x]
            cost, cell = table[front][of] + g.w[arc], shift[of] + place[to]
            better = np.flatnonzero((cost <= limit) & (cost < table[cell]))
            cell, cost = cell[better], cost[better]
            order = np.lexsort((cost, cell))
            least = order[np.append(True, np.diff(cell[order]) != 0)] if len(cell) else order
            front, cost, better = cell[least], cost[least], better[least]
            x, at = to[better], at[of[better]]
            new = table[front] == INFINITE
            table[front] = cost
            touched.append((front[new], x[new], at[new]))
            if counted:
                hits.append(front[new & marks[counted][x]])
        cell, x, at = (np.concatenate(c) for c in zip(*touched))
        d = table[cell]
        table[cell] = INFINITE
        within = d <= limit
        x, at, d = x[within], of_row[at[within]], d[within]
        work.settled += len(d)
        out = {kind: ((named[at[on]] if named is not None else at[on]), x[on], d[on]) for kind, on in ((kind, mark[x]) for kind, mark in marks.items())}
        if counted:
            best.add(out[counted][2])
        yield out
        low = high


def all_distances(n: int, i: np.ndarray, j: np.ndarray, d: np.ndarray) -> np.ndarray:
    """Least distances between all of n vertices from arcs (i, j, d), 0 to themselves."""
    out = np.full((n, n), INFINITE, np.int64)
    np.minimum.at(out, (i, j), d)
    out[np.arange(n), np.arange(n)] = 0
    for k in range(n):
        np.minimum(out, out[:, k, None] + out[None, k], out=out)
    return out


def meet(near: tuple[np.ndarray, np.ndarray, np.ndarray], far: tuple[np.ndarray, np.ndarray, np.ndarray], own: tuple[np.ndarray, np.ndarray, np.ndarray], between: np.ndarray, bound: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(u, its v, their distances) for one u after another: the least of ``own`` (u, v, d) and of the ways over hubs, ``near`` (u, hub, d), ``between`` hubs, ``far`` (hub, v, d); hubs by number.

    A hub's v are sorted by distance, so that what lies within the bound is a prefix: the work is that of the pairs found.
    """
    ids = np.unique(np.concatenate([far[1], own[1]]))
    order = np.lexsort((far[2], far[0]))
    cut = np.searchsorted(far[0][order], np.arange(len(between) + 1))
    vs, ds = np.searchsorted(ids, far[1])[order], far[2][order]
    order = np.argsort(own[0], kind="stable")
    own_u, own_v, own_d = own[0][order], np.searchsorted(ids, own[1])[order], own[2][order]
    order = np.argsort(near[0], kind="stable")
    near_u, near_h, near_d = (c[order] for c in near)
    us, table = np.union1d(near_u, own_u), np.full(len(ids), INFINITE, np.int64)
    for at in range(0, len(us), 1000):
        some = us[at : at + 1000]
        low, high = np.searchsorted(near_u, some[0]), np.searchsorted(near_u, some[-1], "right")
        cost = np.full((len(some), len(between)), INFINITE, np.int64)
        np.minimum.at(cost, np.searchsorted(some, near_u[low:high]), near_d[low:high, None] + between[near_h[low:high]])
        many = np.stack([np.searchsorted(ds[cut[h] : cut[h + 1]], bound - cost[:, h], "right") for h in range(len(between))], axis=1) if len(between) else np.zeros((len(some), 0), np.int64)
        begin, end = np.searchsorted(own_u, some), np.searchsorted(own_u, some, "right")
        for i, u in enumerate(some.tolist()):
            ways = [(vs[cut[h] : cut[h] + many[i, h]], ds[cut[h] : cut[h] + many[i, h]] + cost[i, h]) for h in np.flatnonzero(many[i]).tolist()]
            if end[i] > begin[i]:
                ways.append((own_v[begin[i] : end[i]], own_d[begin[i] : end[i]]))
            if len(ways) == 1:
                yield u, ids[ways[0][0]], ways[0][1]
            elif ways:
                found = []
                for v, d in ways:
                    old = table[v]
                    found.append(v[old == INFINITE])
                    table[v] = np.minimum(old, d)
                v = np.concatenate(found)
                d = table[v]
                table[v] = INFINITE
                yield u, ids[v], d


def smoothed_weight(w: float, own: int, other: int, alpha: float) -> float:
    """The weight of a frontier edge scaled by the relative population of its cluster."""
    return w * own / (own + alpha * other)


def grow(g: LocalGraph, eids: np.ndarray, left: int, right: int, alpha: float, *, rest: bool = True) -> np.ndarray:
    """Side (0 or 1) of every local vertex when two clusters grow from their seeds by the lightest frontier edge.

    ``eids`` are the arcs' edge ids in the graph's order: weight, then edge id, make a total order. Vertices that no seed reaches join the smaller
    cluster at the end, or stay -1 without ``rest``.
    """
    side = [-1] * len(g.ids)
    start, to, weight, edge = g.start.tolist(), g.to.tolist(), g.w.tolist(), eids.tolist()
    heaps: tuple[list, list] = ([], [])
    size = [0, 0]

    def admit(x: int, c: int) -> None:
        side[x] = c
        size[c] += 1
        for at in range(start[x], start[x + 1]):
            if side[to[at]] < 0:
                heappush(heaps[c], (weight[at], edge[at], to[at]))

    admit(left, 0)
    admit(right, 1)
    while True:
        for h in heaps:
            while h and side[h[0][2]] >= 0:
                heappop(h)
        if not heaps[0] and not heaps[1]:
            break
        if not heaps[0] or not heaps[1]:
            c = 0 if heaps[0] else 1
        else:
            first, second = heaps[0][0], heaps[1][0]
            key = (smoothed_weight(first[0], size[0], size[1], alpha), first[0], first[1]), (smoothed_weight(second[0], size[1], size[0], alpha), second[0], second[1])
            c = 0 if key[0] <= key[1] else 1
        admit(heappop(heaps[c])[2], c)
    out = np.array(side, np.int8)
    if rest:
        out[out < 0] = 0 if size[0] <= size[1] else 1
    return out


def farthest(g: LocalGraph, start: int) -> int:
    """The vertex at the largest distance, the smallest id of equals."""
    far = (0, start)
    for d, x in g.search(start):
        if d > far[0]:
            far = d, x
    return far[1]


def spanning_edges(i: np.ndarray, j: np.ndarray, w: np.ndarray, eid: np.ndarray, n: int) -> list[int]:
    """Positions of the minimum spanning forest's edges under the total order (w, eid)."""
    parent = list(range(n))

    def root(x: int) -> int:
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    kept, one, two = [], i.tolist(), j.tolist()
    for e in np.lexsort((eid, w)).tolist():
        p, q = root(one[e]), root(two[e])
        if p != q:
            parent[p] = q
            kept.append(e)
    return kept


def pick_seeds(g: LocalGraph, a: np.ndarray, b: np.ndarray, w: np.ndarray, eid: np.ndarray, how: str, alpha: float, *, tries: int = 4, min_share: float = 0.1, eids: np.ndarray | None = None) -> tuple[int, int] | None:
    """Two different local vertices to grow from, or None if the part has fewer than two vertices.

    double_sweep: farthest from the lowest id, then farthest from that. random: by a hash of the id. best_of: of several random pairs the one
    with the largest separation, then the better balance. longest_tree_edge: the ends of the heaviest spanning edge with at least
    ``min_share`` of the vertices on either side.
    """
    n = len(g.ids)
    if n < 2:
        return None
    mixed = (g.ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(20)
    order = np.argsort(mixed, kind="stable")
    if how == "random":
        return int(order[0]), int(order[1])
    if how == "best_of":
        best = None
        i, j = np.searchsorted(g.ids, a), np.searchsorted(g.ids, b)
        for t in range(min(tries, n // 2)):
            l, r = int(order[2 * t]), int(order[2 * t + 1])
            side = grow(g, eids, l, r, alpha)
            cross = side[i] != side[j]
            key = (int(w[cross].min()) if cross.any() else INFINITE, -abs(int((side == 0).sum()) * 2 - n), -t)
            best = max(best, (key, l, r)) if best else (key, l, r)
        return best[1], best[2]
    if how == "longest_tree_edge":
        i, j = np.searchsorted(g.ids, a), np.searchsorted(g.ids, b)
        tree = spanning_edges(i, j, w, eid, n)
        near: list[list[tuple[int, int]]] = [[] for _ in range(n)]
        for e in tree:
            near[i[e]].append((int(j[e]), e))
            near[j[e]].append((int(i[e]), e))
        below, seen, best = np.ones(n, np.int64), np.zeros(n, bool), None
        for top in range(n):
            if seen[top]:
                continue
            stack, walk, above = [top], [], {top: -1}
            while stack:
                x = stack.pop()
                seen[x] = True
                walk.append(x)
                for y, e in near[x]:
                    if not seen[y]:
                        above[y] = e
                        stack.append(y)
            for x in reversed(walk):
                e = above[x]
                if e >= 0:
                    up = int(i[e]) if int(j[e]) == x else int(j[e])
                    below[up] += below[x]
                    if min(below[x], n - below[x]) >= min_share * n:
                        key = (int(w[e]), int(eid[e]))
                        best = max(best, (key, x, up)) if best else (key, x, up)
        if best:
            return best[1], best[2]
    first = farthest(g, 0)
    second = farthest(g, first)
    return (first, second) if first != second else (int(order[0]), int(order[1]))
