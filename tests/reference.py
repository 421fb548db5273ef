"""Plain sequential versions that the engine is held against."""

import heapq
from collections import defaultdict


def adjacency(edges, directed=False):
    out = defaultdict(list)
    for a, b, w in edges:
        out[a].append((b, w))
        if not directed:
            out[b].append((a, w))
    return out


def distances(adj, start, bound=float("inf")):
    best, heap = {start: 0}, [(0, start)]
    while heap:
        d, x = heapq.heappop(heap)
        if d > best[x]:
            continue
        for y, w in adj[x]:
            if d + w <= bound and d + w < best.get(y, float("inf")):
                best[y] = d + w
                heapq.heappush(heap, (d + w, y))
    return best


def pairs(edges, r, s, theta=float("inf"), k=None, directed=False):
    adj = adjacency(edges, directed)
    found = sorted((d, u, v) for u in r for v, d in distances(adj, u, theta).items() if v in s)
    return [(u, v, d) for d, u, v in (found[:k] if k is not None else found)]


def bottleneck(edges, a, b):
    """Least possible heaviest edge on a path from a to b."""
    parent = {}

    def root(x):
        while parent.setdefault(x, x) != x:
            x = parent[x]
        return x

    for x, y, w in sorted(edges, key=lambda e: e[2]):
        parent[root(x)] = root(y)
        if root(a) == root(b):
            return w
    return None


def grow(edges, left, right, alpha=0.0):
    """Two-seed growth by scanning all frontier edges at each step; weights must differ for a unique answer."""
    adj, side = adjacency(edges), {left: 0, right: 1}
    size = [1, 1]
    vertices = {x for e in edges for x in e[:2]}
    while len(side) < len(vertices):
        best = None
        for x, c in side.items():
            for y, w in adj[x]:
                if y not in side:
                    key = (w * size[c] / (size[c] + alpha * size[1 - c]), w)
                    best = min(best, (key, c, y)) if best else (key, c, y)
        if best is None:
            break
        side[best[2]] = best[1]
        size[best[1]] += 1
    return side


def per_level(edges, r, s, leaf, theta):
    """The faithful merge, part by part from the deepest: {(u, v): d}. ``leaf`` gives each vertex its leaf in a binary tree of numbers."""
    def part_at(x, depth):
        return leaf[x] >> (leaf[x].bit_length() - depth) if leaf[x].bit_length() >= depth else None

    def common(a, b):
        x, y = leaf[a], leaf[b]
        while x != y:
            x, y = (x // 2, y) if x > y else (x, y // 2)
        return x

    def inside(part):
        depth = part.bit_length()
        return adjacency([e for e in edges if part_at(e[0], depth) == part == part_at(e[1], depth)])

    cross = defaultdict(list)
    for a, b, w in edges:
        if leaf[a] != leaf[b]:
            cross[common(a, b)] += [(a, b, w), (b, a, w)]
    border = {x for found in cross.values() for e in found for x in e[:2]}
    best, routes = {}, defaultdict(dict)

    def keep(table, key, d):
        if d <= theta:
            table[key] = min(d, table.get(key, d))

    for u in r:
        for x, d in distances(inside(leaf[u]), u, theta).items():
            if x in s:
                keep(best, (u, x), d)
            if x in border:
                keep(routes[x], u, d)
    for part in sorted(cross, reverse=True):
        over = defaultdict(dict)
        for a, b, w in cross[part]:
            for u, d in routes[a].items():
                keep(over[b], u, d + w)
        above = {x for p in cross if p < part for e in cross[p] for x in e[:2]}
        lifted = []
        for b, reached in over.items():
            for y, d2 in distances(inside(part_at(b, part.bit_length() + 1)), b, theta).items():
                for u, d in reached.items():
                    if y in s:
                        keep(best, (u, y), d + d2)
                    if y in above:
                        lifted.append((y, u, d + d2))
        for y, u, d in lifted:
            keep(routes[y], u, d)
    return best
