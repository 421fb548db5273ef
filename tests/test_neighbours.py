"""Neighbours of vectors block against block, and all pairs by rounds, against plain versions."""

import math

import numpy as np
import pyarrow as pa
import pytest

from netjoin.operators import baselines, neighbours
from netjoin.operators.neighbours import nearest_vectors, vector_pairs
from netjoin.sources.networks import embedding_mesh
from tests.test_network_joins import net_of


def vectors(n: int, copies: int, seed: int = 3) -> dict[int, list[float]]:
    """Random vectors, ``copies`` equal ones and some that differ in the last place only."""
    r = np.random.default_rng(seed)
    out = {i: r.normal(size=6).astype(np.float32).tolist() for i in range(n)}
    for i in range(copies):
        out[n + i] = list(out[0])
    out[n + copies] = [float(np.nextafter(np.float32(x), np.float32(9))) for x in out[0]]
    return out


def plain(x: list[float], y: list[float]) -> float:
    total = 0.0
    for a, b in zip(x, y):
        total += (a - b) * (a - b)
    return math.sqrt(total)


def points(spark, v: dict) -> object:
    return spark.createDataFrame([(i, e) for i, e in v.items()], "id long, e array<float>")


@pytest.mark.parametrize("block", [5, 1000])
def test_nearest_equals_all_pairs_compared(spark, block):
    v = vectors(40, 9)
    want = {(i, *x) for i in v for x in [(j, d) for d, j in sorted((plain(v[i], v[j]), j) for j in v if j != i)[:3]]}
    got = [(r["id"], r["id2"], r["dist"]) for r in nearest_vectors(points(spark, v), 3, block=block).collect()]
    assert len(got) == 3 * len(v) and set(got) == want


def test_nearest_of_few(spark):
    assert nearest_vectors(points(spark, {}), 3).count() == 0
    assert nearest_vectors(points(spark, {7: [1.0, 2.0]}), 3).count() == 0
    assert {(r["id"], r["id2"]) for r in nearest_vectors(points(spark, {7: [1.0], 8: [1.0], 9: [5.0]}), 3, block=1).collect()} == {(7, 8), (7, 9), (8, 7), (8, 9), (9, 7), (9, 8)}
    with pytest.raises(Exception, match="one length"):
        nearest_vectors(points(spark, {7: [1.0], 8: [1.0, 2.0]}), 3).collect()


def table_of(ids: np.ndarray, x: np.ndarray) -> pa.Table:
    return pa.table({"id": ids, "e": list(x)})


def shapes() -> dict[str, tuple[np.ndarray, np.ndarray]]:
    """Two blocks each: what single precision tells apart, what it cannot, and what even squares in double precision do not."""
    r = np.random.default_rng(5)
    x, y, one = r.normal(size=(90, 5)), r.normal(size=(110, 5)), r.normal(size=5)
    outlier, cluster = x.copy(), np.concatenate([y[:40], y[0] + 1e-10 * r.normal(size=(70, 5))])
    outlier[3] *= 1e9
    return {"plain": (x, y), "offset": (1e9 + x, 1e9 + y), "huge": (1e150 * x, 1e150 * y), "tiny": (1e-160 * x, 1e-160 * y), "outlier": (outlier, y), "cluster": (x, cluster),
            "near copies": (one + 1e-7 * x, one + 1e-7 * y), "copies": (np.tile(one, (90, 1)), np.concatenate([np.tile(one, (60, 1)), y[:50]])), "ties": (np.rint(x), np.rint(y)), "few": (x[:1], y[:2])}


@pytest.mark.parametrize("held", [neighbours.HELD, 100])
@pytest.mark.parametrize("shape", shapes())
def test_two_blocks_meet_once_for_both(monkeypatch, shape, held):
    """Each block's nearest in the other and in itself, whatever single precision can tell and in however many tiles."""
    monkeypatch.setattr(neighbours, "HELD", held)
    if held == 100:
        monkeypatch.setattr(neighbours, "TILE_ROWS", 16)
        monkeypatch.setattr(neighbours, "TILE_COLUMNS", 33)
    x, y = shapes()[shape]
    ids = np.random.default_rng(6).permutation(len(x) + len(y))
    a, b = ids[: len(x)], ids[len(x) :]

    def near(p, u, q, v):
        for i, e in zip(p.tolist(), u.tolist()):
            yield from ((i, j, d) for d, j in sorted((plain(e, f), j) for j, f in zip(q.tolist(), v.tolist()) if j != i)[:3])

    rows = lambda batches: sorted(row for got in batches for row in zip(*(c.to_pylist() for c in got.columns)))
    assert rows(neighbours._nearest(3)(table_of(a, x), table_of(b, y))) == sorted([*near(a, x, b, y), *near(b, y, a, x)])
    assert rows(neighbours._nearest(3)(table_of(a, x), None)) == sorted(near(a, x, a, x))


def test_a_pair_of_blocks_is_multiplied_once(monkeypatch):
    """One product has the nearest of both blocks: that is most of the time of the mesh and of the joins on it."""
    cells, product = [], neighbours._Halves.tile
    monkeypatch.setattr(neighbours._Halves, "tile", lambda at, *part: cells.append((near := product(at, *part)).size) or near)
    r = np.random.default_rng(7)
    x, y = r.normal(size=(700, 16)), r.normal(size=(2300, 16))
    got = list(neighbours._nearest(3)(table_of(np.arange(700), x), table_of(np.arange(700, 3000), y)))
    assert sum(cells) == 700 * 2300 and sum(b.num_rows for b in got) == 3 * 3000


def test_a_block_alone_is_multiplied_above_its_diagonal_and_ranked_where_new(monkeypatch):
    """Half of the square serves both ways, and only the first tile that a vector meets is searched for bounds."""
    cells, ranked, product, lowered = [], [], neighbours._Halves.tile, neighbours._lowered
    monkeypatch.setattr(neighbours._Halves, "tile", lambda at, *part: cells.append((near := product(at, *part)).size) or near)
    monkeypatch.setattr(neighbours, "_lowered", lambda known, near, groups: ranked.append(near.size) or lowered(known, near, groups))
    r = np.random.default_rng(8)
    x, y = r.normal(size=(3001, 12)), r.normal(size=(2600, 12))
    got = pa.Table.from_batches(list(neighbours._nearest(3)(table_of(np.arange(3001), x), None)))
    assert sum(cells) <= 3001 * (3001 + neighbours.TILE_ROWS) / 2 and sum(ranked) <= 3001 * neighbours.TILE_ROWS
    far = np.square(x[:, None, :] - x[None]).sum(axis=2)
    np.fill_diagonal(far, np.inf)
    near = np.argsort(far, axis=1)[:, :3]
    assert got.column("id2").to_numpy().reshape(-1, 3).tolist() == near.tolist() and got.column("id").to_numpy().tolist() == np.repeat(np.arange(3001), 3).tolist()
    ranked.clear()
    list(neighbours._nearest(3)(table_of(np.arange(3001), x), table_of(np.arange(3001, 5601), y)))
    assert sum(ranked) <= 3001 * neighbours.TILE_COLUMNS + 2600 * neighbours.TILE_ROWS


def test_values_found_later_lower_the_bounds():
    known = np.array([[1.0, 4.0], [2.0, np.inf], [0.5, 0.6]])
    neighbours._lower(known, np.array([1, 0, 1, 1, 0]), np.array([9.0, 3.0, 1.0, 1.5, 0.5]))
    assert np.sort(known, axis=1).tolist() == [[0.5, 1.0], [1.0, 1.5], [0.5, 0.6]] and known[:, -1].tolist() == [1.0, 1.5, 0.6]


@pytest.mark.parametrize("n, copies", [(900, 1), (10_000, 6), (60_000, 6), (400_000, 7)])
def test_vectors_are_sent_to_few_blocks(spark, monkeypatch, n, copies):
    seen = []
    monkeypatch.setattr(neighbours, "_dealt", lambda rows, units, deal=neighbours._dealt: (seen.append((units, rows.count())), deal(rows, units))[1])
    nearest_vectors(spark.range(n).selectExpr("id", "array(cast(id AS float)) AS e"), 3)
    assert seen == [(copies * (copies + 1) // 2, n * copies)]


@pytest.mark.parametrize("k", [None, 0, 1, 25, 10_000])
def test_vector_pairs_equal_all_compared(spark, k):
    v = vectors(30, 6)
    r, s = ({i: e for i, e in v.items() if i % 2 == m} for m in (0, 1))
    want = sorted((math.floor(1000 * plain(r[i], s[j])), i, j) for i in r for j in s)
    want = [x for x in want if x[0] <= 2500][:k]
    got = [(x["d"], x["u"], x["v"]) for x in vector_pairs(points(spark, r), points(spark, s), k, 2500, block=4).collect()]
    assert sorted(got) == want


def test_mesh_makes_no_rows_of_pairs(spark, sf):
    plan = embedding_mesh(spark, sf).edges._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan and "Join" not in plan


def test_recursive_pairs_pass_light_edges_to_and_fro(spark):
    """Paths within theta over a clique of weight 1 are beyond number; pairs are not."""
    edges = [(i, j, 1) for i in range(6) for j in range(i)] + [(5, 6, 40), (6, 7, 30)]
    net = net_of(spark, edges)
    got = {(r["u"], r["v"]): r["d"] for r in baselines.all_pairs_recursive(net, 60).collect()}
    assert got == {(r["u"], r["v"]): r["d"] for r in baselines.all_pairs(net, 60).collect()}
    assert baselines.all_pairs_recursive(net_of(spark, [(1, 1, 5)]), 60).count() == 0
    assert got[0, 6] == 41 and (0, 7) not in got and got[6, 7] == 30 and len(got) == 6 * 5 + 2 * 6 + 2
