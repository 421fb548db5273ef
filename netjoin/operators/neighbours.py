"""Exact straight-line neighbours of vectors, block against block.

Vectors are dealt into blocks by a hash of their id, and every two blocks meet in a task. There one matrix product gives all squared distances up to rounding (nearest
vectors: in tiles of single precision that serve both blocks); what lies within the rounding of the wanted ones is computed again as the plain sum of squares in the order
of the components, so results equal a comparison of all pairs. A task holds two blocks at a time; the work grows with the square of the vectors, the rows written with vectors times blocks.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Vectors in a block, rows of a block compared at once, and most tasks of a comparison.
BLOCK, STRIP, MOST_TASKS = 4096, 512, 2000
#: For nearest vectors: most in a block (a task holds two, some 250 MB at 64 components), and blocks that smaller tables have, so that there is work for several tasks.
LARGE_BLOCK, LEAST_BLOCKS = 65_536, 6


def _vectors(rows: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """Ids and vectors of a block by id; vectors must be finite and of one length."""
    order = np.argsort(rows.column("id").to_numpy(), kind="stable")
    e = rows.column("e").combine_chunks()
    values, n = e.flatten(), len(e)
    wide = len(values) // n if n else 0
    if e.null_count or values.null_count or wide * n != len(values) or not (np.diff(e.offsets.to_numpy()) == wide).all():
        raise ValueError("vectors must be whole and of one length")
    x = values.to_numpy(zero_copy_only=False).astype(np.float64).reshape(n, wide)[order]
    if not np.isfinite((x * x).sum(axis=1)).all():
        raise ValueError("vectors must be finite")
    return rows.column("id").to_numpy()[order], x


def _products(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
    """Two matrices whose product with one transposed holds the squared distances, and a bound of the rounding, also of squares that all but vanish."""
    nx, ny = (x * x).sum(axis=1), (y * y).sum(axis=1)
    left = np.column_stack([x, np.ones(len(x)), nx])
    right = np.column_stack([-2 * y, ny, np.ones(len(y))])
    return left, right, 16 * (x.shape[1] + 8) * np.finfo(float).eps * float(nx.max(initial=0) + ny.max(initial=0)) + 1e-300


def _distance(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """L2 of matching rows, squares summed in the order of the components."""
    total = np.zeros(len(x))
    for c in range(x.shape[1]):
        step = x[:, c] - y[:, c]
        total += step * step
    return np.sqrt(total)


def _first_copies(x: np.ndarray, n: int) -> np.ndarray:
    """Rows that are among the first ``n`` of equal vectors; rows come by id."""
    if not x.size:
        return np.arange(len(x))[:n]
    _, group = np.unique(np.ascontiguousarray(x + 0.0).view(np.dtype((np.void, x.shape[1] * 8))).reshape(-1), return_inverse=True)
    order = np.argsort(group.reshape(-1), kind="stable")
    of = group.reshape(-1)[order]
    place = np.arange(len(x)) - np.searchsorted(of, of)
    return np.sort(order[place < n])


def _thinned(near: np.ndarray, groups: int) -> np.ndarray:
    """Minima of fewer than twice ``groups`` disjoint groups of columns, by halving."""
    while near.shape[1] >= 2 * groups:
        half, odd = divmod(near.shape[1], 2)
        least = np.minimum(near[:, :half], near[:, half : 2 * half])
        if odd:
            np.minimum(least[:, 0], near[:, -1], out=least[:, 0])
        near = least
    return near


def _lowered(known: np.ndarray, near: np.ndarray, groups: int) -> np.ndarray:
    """The least values of each row, known ones and those of groups of columns: its last one bounds the row's n-th least from above."""
    n = known.shape[1]
    every = np.concatenate([known, _thinned(near, max(groups, n))], axis=1)
    every.partition(n - 1, axis=1)
    return every[:, :n]


def _found(close: np.ndarray) -> np.ndarray:
    """``np.flatnonzero`` of a tile with few of them: eight cells are looked at together first."""
    if close.size % 8:
        return np.flatnonzero(close)
    eights = close.reshape(-1, 8)
    some = np.flatnonzero(eights.view(np.uint64) != 0)
    place, cell = np.nonzero(eights[some])
    return 8 * some[place] + cell


def _lower(known: np.ndarray, i: np.ndarray, d: np.ndarray) -> None:
    """Let the values ``d`` of rows ``i`` take their places among the least known ones, in place."""
    n, order = known.shape[1], np.lexsort((d, i))
    i, d = i[order], d[order]
    place = np.arange(len(i)) - np.searchsorted(i, i)
    i, d, place = i[place < n], d[place < n], place[place < n]
    rows, at = np.unique(i, return_inverse=True)
    every = np.full((len(rows), 2 * n), np.inf, known.dtype)
    every[:, :n], every[at, n + place] = known[rows], d
    every.partition(n - 1, axis=1)
    known[rows] = every[:, :n]


class _Halves:
    """The matrices of ``_products``, in single precision too: vectors moved to a common centre and scaled, so that neither overflows nor loses differences to an offset."""

    def __init__(self, x: np.ndarray, y: np.ndarray):
        self.left, right, self.slack = _products(x, y)
        self.right = right.T
        centre = x.mean(axis=0) if len(x) else 0.0
        near_x, near_y = x - centre, y - centre
        scale = max(np.abs(near_x).max(initial=0), np.abs(near_y).max(initial=0))
        left, right, slack = _products(near_x / (scale or 1.0), near_y / (scale or 1.0))
        self.left32, self.right32 = left.astype(np.float32), np.ascontiguousarray(right.T.astype(np.float32))
        self.slack32 = np.float32(slack * (np.finfo(np.float32).eps / np.finfo(float).eps))
        self.single = not 0 < scale < 1e-100  # where squares vanish, ids decide

    def tile(self, rows: slice, columns: slice, single: bool) -> np.ndarray:
        return self.left32[rows] @ self.right32[:, columns] if single else self.left[rows] @ self.right[:, columns]


#: Tiles in which distances are compared; candidates held before only the nearest of them are; candidates for each wanted neighbour at which single precision is given up.
TILE_ROWS, TILE_COLUMNS, HELD, LOOSE = 512, 2048, 4_000_000, 16


class _Way:
    """One way of a comparison: the nearest of some vectors to each of others."""

    def __init__(self, p: np.ndarray, u: np.ndarray, q: np.ndarray, v: np.ndarray, n: int, kind: type):
        self.p, self.u, self.q, self.v, self.n = p, u, q, v, n
        self.bounds, self.kept, self.held = np.full((len(p), n), np.inf, kind), [], 0

    def meet(self, rows: slice, left: int, near: np.ndarray, groups: int, slack: float) -> None:
        """Keep what of a tile, whose columns begin at ``left``, lies within the rounding of the bounds met so far.

        The first tile gives bounds from groups of its columns; from then on only what lies within them can lower them.
        """
        fresh = not (self.bounds[rows, -1] < np.inf).all()
        if fresh:
            self.bounds[rows] = _lowered(self.bounds[rows], near, groups)
        close = near <= (self.bounds[rows, -1] + slack)[:, None]
        if near.flags.c_contiguous:
            i, j = np.divmod(_found(close), near.shape[1])
        else:
            j, i = np.divmod(_found(close.T), near.shape[0])
        if not len(i):
            return
        d = near[i, j]
        if not fresh:
            _lower(self.bounds[rows], i, d)
        self.kept.append((rows.start + i, left + j, d))
        self.held += len(i)

    def nearest(self, slack: float) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Rows, columns, squares up to rounding and distances of the nearest of what is kept, by (distance, id)."""
        i, j, d = (np.concatenate(c) for c in zip(*self.kept)) if self.kept else (np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0))
        stay = (d <= self.bounds[i, -1] + slack) & (d < np.inf)
        i, j, d = i[stay], j[stay], d[stay]
        dist = _distance(self.u[i], self.v[j])
        order = np.lexsort((self.q[j], dist, i))
        order = order[np.arange(len(i)) - np.searchsorted(i[order], i[order]) < self.n]
        return i[order], j[order], d[order], dist[order]

    def thin(self, slack: float) -> None:
        self.kept = [self.nearest(slack)[:3]]
        self.held = len(self.kept[0][0])

    def rows(self, slack: float) -> pa.RecordBatch:
        i, j, _, dist = self.nearest(slack)
        return pa.RecordBatch.from_arrays([pa.array(self.p[i]), pa.array(self.q[j]), pa.array(dist)], names=["id", "id2", "dist"])


def _ranked(a: np.ndarray, x: np.ndarray, b: np.ndarray, y: np.ndarray, n: int, *, apart: np.ndarray | None = None, both: bool = False) -> Iterator[pa.RecordBatch]:
    """The ``n`` nearest of b to each of a and, with ``both``, of a to each of b. ``apart``: the row of a that each column must not meet, if any.

    One product of a tile serves both ways. With ``apart`` and ``both`` a is b, and what lies below the diagonal is not multiplied.
    Single precision only tells what is out of the question; where it leaves too much the tiles are of double precision.
    """
    at, alone = _Halves(x, y), both and apart is not None
    for single in (True, False) if at.single else (False,):
        slack = 2 * (at.slack32 if single else at.slack)
        ways = [_Way(*side, n, np.float32 if single else float) for side in ((a, x, b, y), (b, y, a, x))[: 1 + both - alone]]
        if _met(at, ways, apart, single, slack, alone):
            break
    for way in ways:
        yield way.rows(slack)


def _tiles(many: int, wide: int, alone: bool) -> Iterator[tuple[slice, slice]]:
    """Rows and columns of all tiles; of a block alone the squares on the diagonal and what lies right of them."""
    for low in range(0, many, TILE_ROWS):
        high = min(low + TILE_ROWS, many)
        if alone:
            yield slice(low, high), slice(low, high)
        for left in range(high if alone else 0, wide, TILE_COLUMNS):
            yield slice(low, high), slice(left, min(left + TILE_COLUMNS, wide))


def _met(at: _Halves, ways: list[_Way], apart: np.ndarray | None, single: bool, slack: float, alone: bool) -> bool:
    """Let all tiles meet; False if single precision leaves too many candidates."""
    many, wide, seen = len(at.left), at.right.shape[1], 0
    for rows, columns in _tiles(many, wide, alone):
        near, before = at.tile(rows, columns, single), sum(way.held for way in ways)
        if apart is not None:
            j = np.flatnonzero((apart[columns] >= rows.start) & (apart[columns] < rows.stop))
            near[apart[columns][j] - rows.start, j] = np.inf
        ways[0].meet(rows, columns.start, near, 16, slack)
        if len(ways) > 1 or alone and columns.start > rows.start:
            ways[-1].meet(columns, rows.start, near.T, 8, slack)
        seen += sum(way.held for way in ways) - before
        if single and seen > LOOSE * ways[0].n * (many + wide):
            return False
        for way in ways:
            if way.held > HELD:
                way.thin(slack)
    return True


def _nearest(n: int) -> Callable:
    def run(left: pa.Table, right: pa.Table | None) -> Iterator[pa.RecordBatch]:
        a, x = _vectors(left)
        few = _first_copies(x, n + 1)
        if right is None:
            yield from _ranked(a, x, a[few], x[few], n, apart=few, both=len(few) == len(a))
            return
        b, y = _vectors(right)
        other = _first_copies(y, n + 1)
        if len(few) == len(a) and len(other) == len(b):
            yield from _ranked(a, x, b, y, n, both=True)
            return
        yield from _ranked(a, x, b[other], y[other], n)
        yield from _ranked(b, y, a[few], x[few], n)

    return run


def _within(k: int | None, theta: int) -> Callable:
    def run(left: pa.Table, right: pa.Table) -> Iterator[pa.RecordBatch]:
        (a, x), (b, y) = _vectors(left), _vectors(right)
        near_to, far, slack = _products(x, y)
        held, limit = [], theta
        for at in range(0, len(a), STRIP):
            near = near_to[at : at + STRIP] @ far.T
            if k is not None and near.size > k:
                kth = max(float(np.partition(near, k - 1, axis=None)[k - 1]), 0.0) + slack
                limit = min(limit, int(np.floor(1000 * np.sqrt(kth))) + 1)
            i, j = np.nonzero(near <= ((limit + 1) / 1000) ** 2 + slack)
            d = np.floor(1000 * _distance(x[at + i], y[j])).astype(np.int64)
            u, v, d = (c[d <= limit] for c in (a[at + i], b[j], d))
            if k is None:
                yield pa.RecordBatch.from_arrays([pa.array(u), pa.array(v), pa.array(d)], names=["u", "v", "d"])
                continue
            u, v, d = (np.concatenate(c) for c in zip(*held, (u, v, d)))
            order = np.lexsort((v, u, d))[:k]
            held = [(u[order], v[order], d[order])]
            limit = min(limit, int(d[order[-1]])) if len(order) == k and k else limit
        if held:
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in held[0]], names=["u", "v", "d"])

    return run


def _meetings(work: Callable) -> Callable:
    """Run ``work`` on the two sides of one unit after another; rows come sorted by unit."""

    def of(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.Table | None, pa.Table | None]]:
        held, now = [], None
        for batch in batches:
            units = batch.column("unit").to_numpy()
            cuts = np.concatenate([[0], np.flatnonzero(units[1:] != units[:-1]) + 1, [len(units)]]) if len(units) else []
            for at, end in zip(cuts[:-1], cuts[1:]):
                if now is not None and units[at] != now:
                    yield pa.Table.from_batches(held)
                    held = []
                now = units[at]
                held.append(batch.slice(int(at), int(end - at)))
        if held:
            yield pa.Table.from_batches(held)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in of(batches):
            right = rows.column("right").to_numpy()
            one, two = rows.filter(pa.array(~right)), rows.filter(pa.array(right))
            if rows.column("alone")[0].as_py():
                yield from work(one, None)
            elif one.num_rows and two.num_rows:
                yield from work(one, two)

    return run


def _dealt(rows: DataFrame, units: int) -> DataFrame:
    tasks = min(units, MOST_TASKS)
    return rows.repartitionById(tasks, F.pmod("unit", F.lit(tasks)).cast("int")).sortWithinPartitions("unit")


def _block(blocks: int):
    return F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("long")


def nearest_vectors(points: DataFrame, n: int, *, block: int | None = None) -> DataFrame:
    """(id, id2, dist): the ``n`` nearest other vectors of each by (dist, id2): points(id, e array of numbers), ids unique.

    Equal vectors are at distance 0 and decided by id. Fewer others than ``n``: all of them. Null, unequally long and infinite vectors are refused.
    Every vector is sent to as many units as there are blocks, so blocks are as large as a task holds.
    """
    many = points.count()
    blocks = max(1, -(-many // (block or min(LARGE_BLOCK, max(1024, -(-many // LEAST_BLOCKS))))))
    own, other = F.col("i"), F.col("j")
    rows = points.select("id", "e", _block(blocks).alias("i")).withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)).cast("array<bigint>")))
    rows = rows.select((F.least(own, other) * blocks + F.greatest(own, other)).alias("cell"), (own > other).alias("right"), (own == other).alias("alone"), "id", "e")
    low, high = F.floor(F.col("cell") / blocks).cast("long"), F.col("cell") % blocks
    rows = rows.select((low * blocks - (low * (low + 1) / 2).cast("long") + high).cast("long").alias("unit"), "right", "alone", "id", "e")
    near = _dealt(rows, blocks * (blocks + 1) // 2).mapInArrow(_meetings(_nearest(n)), "id long, id2 long, dist double")
    if blocks == 1:
        return near
    return near.withColumn("place", F.row_number().over(Window.partitionBy("id").orderBy("dist", "id2"))).where(F.col("place") <= n).drop("place")


def vector_pairs(r: DataFrame, s: DataFrame, k: int | None, theta: int, *, block: int = BLOCK) -> DataFrame:
    """(u, v, d) with d = floor(1000 * L2) <= theta, of all of r(id, e) against all of s(id, e); with k the first k by (d, u, v)."""
    left, right = (max(1, -(-side.count() // block)) for side in (r, s))
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)).cast("array<bigint>"))
    a = r.select("id", "e", _block(left).alias("i"), every(right).alias("j"), F.lit(False).alias("right"))
    b = s.select("id", "e", every(left).alias("i"), _block(right).alias("j"), F.lit(True).alias("right"))
    rows = a.unionByName(b).select((F.col("i") * right + F.col("j")).alias("unit"), "right", F.lit(False).alias("alone"), "id", "e")
    near = _dealt(rows, left * right).mapInArrow(_meetings(_within(k, theta)), "u long, v long, d long")
    return near.orderBy("d", "u", "v").limit(k) if k is not None else near
