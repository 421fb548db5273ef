"""SQL (DuckDB dialect) that the registered queries must equal, on the same Parquet tables."""

from __future__ import annotations

URBAN = """o AS (SELECT o_orderkey AS id, o_custkey, CAST(round(o_totalprice * 100) AS BIGINT) AS c FROM orders),
 g AS (SELECT CAST(floor(sqrt(count(*))) AS BIGINT) AS width FROM orders),
 e AS (SELECT a.id AS src, b.id AS dst, 1 + abs(a.c - b.c) % 1000 AS w FROM o a, g, o b WHERE b.id = a.id + 1 AND a.id % width <> width - 1
       UNION ALL SELECT a.id, b.id, 1 + abs(a.c - b.c) % 1000 FROM o a, g, o b WHERE b.id = a.id + width AND (a.id * 7919 + a.o_custkey) % 100 < 30),
 v AS (SELECT id FROM o)"""
INTERSTATE = """o AS (SELECT o_orderkey AS id, o_custkey, o_orderdate, lead(o_orderkey) OVER k AS nxt, lead(o_orderdate) OVER k AS d2, row_number() OVER k AS i, count(*) OVER (PARTITION BY o_custkey) AS n
       FROM orders WINDOW k AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)),
 c AS (SELECT c_custkey AS o_custkey, c_nationkey AS nk, CAST(round(abs(c_acctbal)) AS BIGINT) AS bal, c_mktsegment AS seg FROM customer),
 l AS (SELECT id AS a, nxt AS b, 1 + date_diff('day', CAST(o_orderdate AS DATE), CAST(d2 AS DATE)) AS w FROM o WHERE nxt IS NOT NULL
       UNION ALL SELECT id, -1 - nk, 1 + bal % 500 FROM o JOIN c USING (o_custkey) WHERE i = 1
       UNION ALL SELECT id, -1 - (nk + 1) % 25, 1 + bal % 700 FROM o JOIN c USING (o_custkey) WHERE i = n AND n > 1 AND seg = 'BUILDING'
       UNION ALL SELECT -1 - n_nationkey, -1 - (n_nationkey + 1) % 25, 1000 + 37 * n_nationkey FROM nation),
 e AS (SELECT CAST(least(a, b) AS BIGINT) AS src, CAST(greatest(a, b) AS BIGINT) AS dst, CAST(min(w) AS BIGINT) AS w FROM l GROUP BY 1, 2),
 v AS (SELECT id FROM o UNION ALL SELECT -1 - n_nationkey FROM nation)"""
TRADE = """e AS (SELECT -1 - l_suppkey AS src, l_partkey AS dst, greatest(1, min(CAST(trunc(l_quantity) AS BIGINT))) AS w FROM lineitem GROUP BY 1, 2),
 v AS (SELECT p_partkey AS id FROM part UNION ALL SELECT -1 - s_suppkey FROM supplier)"""
_LINKS = """l AS (SELECT event_id AS a, nxt AS b, 1 + (epoch_us(t2) - epoch_us(ts)) // 60000000 AS w
       FROM (SELECT event_id, ts, lead(event_id) OVER k AS nxt, lead(ts) OVER k AS t2 FROM events WINDOW k AS (PARTITION BY user_id ORDER BY ts, event_id)) WHERE nxt IS NOT NULL
       UNION ALL SELECT event_id, nxt, 30 + (epoch_us(t2) - epoch_us(ts)) // 60000000
       FROM (SELECT event_id, ts, lead(event_id) OVER k AS nxt, lead(ts) OVER k AS t2 FROM events WINDOW k AS (PARTITION BY event_type ORDER BY ts, event_id)) WHERE nxt IS NOT NULL AND event_id % 4 = 0)"""
LINES = _LINKS + """, e AS (SELECT least(a, b) AS src, greatest(a, b) AS dst, CAST(min(w) AS BIGINT) AS w FROM l GROUP BY 1, 2),
 v AS (SELECT event_id AS id FROM events)"""
_POINTS = "p AS (SELECT vec_id AS id, CAST(embedding AS DOUBLE[]) AS x FROM embeddings)"
_DIST = "sqrt(list_reduce(list_prepend(0::DOUBLE, list_transform(list_zip(a.x, b.x), lambda z: (z[1] - z[2]) * (z[1] - z[2]))), lambda s, z: s + z))"
MESH = f"""{_POINTS},
 n AS (SELECT a.id AS a, b.id AS b, {_DIST} AS dist FROM p a JOIN p b ON a.id <> b.id),
 t AS (SELECT a, b, dist, row_number() OVER (PARTITION BY a ORDER BY dist, b) AS i FROM n),
 e AS (SELECT least(a, b) AS src, greatest(a, b) AS dst, min(1 + CAST(floor(1000 * dist) AS BIGINT)) AS w FROM t WHERE i <= 3 GROUP BY 1, 2),
 v AS (SELECT id FROM p)"""
NETS = {"urban": URBAN, "interstate": INTERSTATE, "trade": TRADE, "lines": LINES, "mesh": MESH}
ARCS = "arc AS (SELECT src AS a, dst AS b, w FROM e UNION ALL SELECT dst, src, w FROM e)"


def _hash(x: str = "id") -> str:
    m = f"(({x} + 17) % 10007)"
    return f"({m} * {m} % 10007 * {m} % 10007)"


def _sets(r: float = 8, s: float = 8) -> str:
    return f"r AS (SELECT id FROM v WHERE id >= 0 AND {_hash()} < {r * 100.07!r}), s AS (SELECT id FROM v WHERE id >= 0 AND {_hash()} >= {10007 - s * 100.07!r})"


def _search(theta: int, start: str = "SELECT id, id, 0::BIGINT FROM r") -> str:
    return f"""q(u, x, d) USING KEY (u, x) AS ({start}
        UNION SELECT q.u, a.b, min(q.d + a.w) FROM q JOIN arc a ON a.a = q.x LEFT JOIN recurring.q o ON o.u = q.u AND o.x = a.b
        WHERE q.d + a.w <= {theta} AND (o.d IS NULL OR q.d + a.w < o.d) GROUP BY q.u, a.b)"""


def _pairs(net: str, theta: int, *, r: float = 8, s: float = 8, k: int | None = None, sets: str | None = None, arcs: str = ARCS) -> str:
    tail = f" ORDER BY d, u, v LIMIT {k}" if k is not None else ""
    return f"WITH RECURSIVE {NETS.get(net, net)}, {arcs}, {sets or _sets(r, s)}, {_search(theta)} SELECT u, x AS v, CAST(d AS BIGINT) AS d FROM q JOIN s ON s.id = q.x{tail}"


_CUT = "h AS (SELECT max(id) + 1 AS n FROM v), p AS (SELECT id, 2 + id * 2 // n AS gp FROM v, h)"


def _given(crossings: int, theta: int = 1000) -> str:
    """Pairs on the lines cut in two, with at most so many crossings (a big number: any)."""
    return f"""WITH RECURSIVE {LINES}, {ARCS}, {_sets()}, {_CUT},
     x AS (SELECT a, b, w, CASE WHEN pa.gp <> pb.gp THEN 1 ELSE 0 END AS c FROM arc JOIN p pa ON pa.id = a JOIN p pb ON pb.id = b),
     q(u, x, c, d) USING KEY (u, x, c) AS (SELECT id, id, 0, 0::BIGINT FROM r
        UNION SELECT q.u, t.b, q.c + t.c, min(q.d + t.w) FROM q JOIN x t ON t.a = q.x LEFT JOIN recurring.q o ON o.u = q.u AND o.x = t.b AND o.c = q.c + t.c
        WHERE q.d + t.w <= {theta} AND q.c + t.c <= {crossings} AND (o.d IS NULL OR q.d + t.w < o.d) GROUP BY q.u, t.b, q.c + t.c)
    SELECT u, x AS v, CAST(min(d) AS BIGINT) AS d FROM q JOIN s ON s.id = q.x GROUP BY u, x"""


_OBJECTS = f"""{URBAN}, cnt AS (SELECT count(*) AS n FROM orders),
 f AS (SELECT src, min(dst) AS dst FROM e GROUP BY src), fe AS (SELECT f.src, f.dst, e.w FROM f JOIN e ON e.src = f.src AND e.dst = f.dst),
 ev AS (SELECT event_id, ts, CASE WHEN event_type = 'view' THEN 'r' ELSE 's' END AS kind, user_id * 2 + CASE WHEN event_type = 'view' THEN 0 ELSE 1 END AS oid, (event_id * 37 + user_id) % n AS spot
        FROM events, cnt WHERE event_type IN ('view', 'purchase')),
 po AS (SELECT oid, kind, src, dst, w, event_id * 13 % (w + 1) AS off, row_number() OVER (PARTITION BY oid ORDER BY ts DESC, event_id DESC) AS i FROM ev JOIN fe ON fe.src = spot),
 ob AS (SELECT * FROM po WHERE i = 1)"""
_CLOSEST = f"""WITH RECURSIVE {_OBJECTS}, {ARCS}, {_search(1000, "SELECT oid, node, min(d)::BIGINT FROM (SELECT oid, src AS node, off AS d FROM ob WHERE kind = 'r' UNION ALL SELECT oid, dst, w - off FROM ob WHERE kind = 'r') WHERE d <= 1000 GROUP BY 1, 2")},
 fin AS (SELECT oid, src AS node, off AS d FROM ob WHERE kind = 's' UNION ALL SELECT oid, dst, w - off FROM ob WHERE kind = 's'),
 al AS (SELECT q.u, fin.oid AS v, q.d + fin.d AS d FROM q JOIN fin ON fin.node = q.x
        UNION ALL SELECT a.oid, b.oid, abs(a.off - b.off) FROM ob a JOIN ob b ON a.src = b.src AND a.dst = b.dst WHERE a.kind = 'r' AND b.kind = 's')
 SELECT u, v, CAST(min(d) AS BIGINT) AS d FROM al WHERE d <= 1000 GROUP BY u, v ORDER BY d, u, v LIMIT 40"""


#: The lines cut in eight: leaves 8 to 15 by spans of the event ids, their ancestors, edges by the leaves of both ends, and cross-edges by lowest common part.
_EIGHT = f"""{LINES}, pt AS (SELECT id, CAST(8 + id * 8 // n AS BIGINT) AS gp FROM v, (SELECT max(id) + 1 AS n FROM v)), lev(k) AS (VALUES (0), (1), (2), (3)),
 pe AS (SELECT e.*, a.gp AS ga, b.gp AS gb FROM e JOIN pt a ON a.id = e.src JOIN pt b ON b.id = e.dst),
 cr AS (SELECT *, CASE WHEN ga >> 1 = gb >> 1 THEN ga >> 1 WHEN ga >> 2 = gb >> 2 THEN ga >> 2 ELSE 1 END AS node FROM pe WHERE ga <> gb),
 nv AS (SELECT gp >> k AS node, count(*) AS n_vertices FROM pt, lev GROUP BY 1),
 ne AS (SELECT ga >> k AS node, count(*) AS n_edges FROM pe, lev WHERE ga >> k = gb >> k GROUP BY 1),
 sp AS (SELECT node, min(w) AS sep FROM cr GROUP BY 1),
 nodes AS (SELECT node AS gp, node // 2 AS parent, CAST(node % 2 AS INTEGER) AS side, CAST(floor(log2(node)) AS INTEGER) AS level, CAST(3 - floor(log2(node)) AS INTEGER) AS height, n_vertices,
                  coalesce(n_edges, 0) AS n_edges, sep, node >= 8 AS leaf FROM nv LEFT JOIN ne USING (node) LEFT JOIN sp USING (node)),
 plan AS (SELECT height AS wave, gp, height, row_number() OVER (PARTITION BY height ORDER BY n_edges DESC, gp) - 1 AS i FROM nodes)"""


def _recall() -> str:
    """Recall of the crossing modes on the lines cut in two, at theta 1000; per_level is one crossing at depth 1."""
    answers = {"none": _given(0), "one": _given(1), "per_level": _given(1), "closure": _pairs("lines", 1000)}
    sigma = f"(WITH {LINES}, {_CUT} SELECT min(w) AS sigma FROM e JOIN p pa ON pa.id = src JOIN p pb ON pb.id = dst WHERE pa.gp <> pb.gp)"
    rows = " UNION ALL ".join(
        f"""SELECT '{m}' AS crossings, count(*) AS n_exact, count(a.d) AS n_found, count(*) FILTER (a.d = x.d) AS n_equal, count(a.d) / count(*) AS recall, count(*) FILTER (a.d = x.d) / count(*) AS equal_share,
            round(avg(a.d / x.d), 9) AS mean_stretch, {'true' if m == 'closure' else f"1000 < {1 if m == 'none' else 2} * max(sigma)"} AS certified FROM exact x LEFT JOIN ans_{m} a USING (u, v), {sigma} sg""" for m in answers)
    return f"WITH exact AS ({_pairs('lines', 1000)}), {', '.join(f'ans_{m} AS ({q})' for m, q in answers.items())} {rows}"


def oracles(names: dict[str, int], sweeps: dict[str, tuple], thetas: dict[str, tuple], bound_leaves: tuple[int, ...]) -> dict[str, str]:
    near = _pairs("interstate", 100)
    out = {f"net_{n}_edges": f"WITH {c} SELECT src, dst, w FROM e" for n, c in NETS.items()}
    out |= {
        "net_degree_profile": f"WITH {URBAN}, {ARCS}, k AS (SELECT a, count(*) AS degree FROM arc GROUP BY a) SELECT degree, count(*) AS n FROM k GROUP BY degree",
        "net_weight_quantiles": f"WITH {URBAN} SELECT min(w) AS least, CAST(quantile_cont(w, 0.5) AS DOUBLE) AS median, max(w) AS most, count(*) AS n FROM e",
        "ops_hash_sets": f"WITH {URBAN}, {_sets()} SELECT id, 'r' AS role FROM r UNION ALL SELECT id, 's' FROM s",
        "ops_attr_sets": "SELECT event_id AS id, CASE WHEN event_type = 'view' THEN 'r' ELSE 's' END AS role FROM events WHERE event_type IN ('view', 'purchase')",
        "ops_disjoint_check": f"WITH {INTERSTATE}, {_sets(50, 50)} SELECT count(*) AS shared FROM r JOIN s USING (id)",
    }
    out |= {f"dj_{n}": _pairs(n, t) for n, t in names.items()}
    directed = "arc AS (SELECT a, b, CAST(min(w) AS BIGINT) AS w FROM l GROUP BY 1, 2)"
    out |= {"dj_directed_lines": _pairs("lines", 1000, arcs=directed), "dj_trade": _pairs("trade", 3), "dj_swapped": _pairs("interstate", 200), "dj_frontier": _pairs("interstate", 200), "dj_urban_800": _pairs("urban", 800)}
    out |= {f"kcp_{n}": _pairs(n, t, k=80) for n, t in names.items()}
    urban = _pairs("urban", 400, k=80)
    attr = "r AS (SELECT event_id AS id FROM events WHERE event_type = 'view'), s AS (SELECT event_id AS id FROM events WHERE event_type = 'purchase')"
    two = "us AS (SELECT user_id, row_number() OVER (ORDER BY count(*) DESC, user_id) AS i FROM events GROUP BY user_id), r AS (SELECT event_id AS id FROM events JOIN us USING (user_id) WHERE i = 1), s AS (SELECT event_id AS id FROM events JOIN us USING (user_id) WHERE i = 2)"
    out |= {"kcp_theta": _pairs("urban", 100, k=80), "kcp_attr": _pairs("lines", 60, sets=attr, k=80), "kcp_trajectory": _pairs("lines", 20000, sets=two, k=10)}
    out |= {f"dj_{n}_theta_{t}": _pairs(n, t) for n, ts in thetas.items() for t in ts}
    for prefix, n in (("kcp", "urban"), ("kcp_interstate", "interstate")):
        out |= dict.fromkeys([f"{prefix}_alpha_{int(a * 100)}" for a in sweeps["alpha"]] + [f"{prefix}_p_{p}" for p in sweeps["parallelism"]], _pairs(n, 400, k=80))
        out |= {f"{prefix}_k_{k}": _pairs(n, 400, k=k) for k in sweeps["k"]}
        out |= {f"{prefix}_r_{p}": _pairs(n, 1200, r=p, k=80) for p in sweeps["r"]} | {f"{prefix}_s_{p}": _pairs(n, 1200, s=p, k=80) for p in sweeps["s"]}
    out |= {f"kcp_bound_{name}_{n}": urban for n in bound_leaves for name in ("local", "shared")}
    out |= {f"kcp_{n}": urban for n in ("p_1", "local_bound", "auto_bound", "auto_bound_2", "pool", "frontier", "task", "per_level", "per_level_pool")}
    mesh = _pairs("mesh", 6000, k=80)
    out |= {"kcp_interstate_per_level": _pairs("interstate", 400, k=80), "kcp_no_reuse": mesh, "kcp_no_stop": mesh, "kcp_mesh_frontier": mesh}
    out |= {f"dj_{n}_{m}": _pairs("urban", 1000) for n in ("no_reuse", "no_stop") for m in ("one", "per_level")}
    out |= {"kcp_unbounded_k": _pairs("urban", 200), "kcp_many": _pairs("mesh", 6000, k=2000), "naive_pairs": _pairs("interstate", 400, k=80)}
    out["mst_mesh"] = f"""WITH RECURSIVE {MESH}, {ARCS}, ma AS (SELECT src AS a, dst AS b, w AS o FROM e UNION ALL SELECT dst, src, w FROM e),
        q(u, x, d) USING KEY (u, x) AS (SELECT id, id, 0::BIGINT FROM v UNION SELECT q.u, t.b, min(greatest(q.d, t.o)) FROM q JOIN ma t ON t.a = q.x LEFT JOIN recurring.q z ON z.u = q.u AND z.x = t.b
            WHERE z.d IS NULL OR greatest(q.d, t.o) < z.d GROUP BY q.u, t.b),
        total AS (SELECT count(*) AS n_all FROM v), comps AS (SELECT count(DISTINCT k) AS parts FROM (SELECT u, min(x) AS k FROM q GROUP BY u)),
        SELECT CAST(max(n_all) - max(parts) AS BIGINT) AS n_edges, CAST((SELECT sum(d) FROM (SELECT x, min(d) AS d FROM q WHERE u < x GROUP BY x)) AS BIGINT) AS weight FROM total, comps"""
    bottleneck = lambda net: f"""WITH RECURSIVE {NETS[net]}, {ARCS}, lo AS (SELECT min(id) AS a, max(id) AS b FROM v),
        q(x, d) USING KEY (x) AS (SELECT a, 0::BIGINT FROM lo UNION SELECT t.b, min(greatest(q.d, t.w)) FROM q JOIN arc t ON t.a = q.x LEFT JOIN recurring.q z ON z.x = t.b WHERE z.d IS NULL OR greatest(q.d, t.w) < z.d GROUP BY t.b)
        SELECT CAST(d AS BIGINT) AS sep FROM q, lo WHERE x = lo.b"""  # noqa: E731
    out |= {"bisect_sep_urban": bottleneck("urban"), "bisect_sep_forest": bottleneck("mesh")}
    cross = f"WITH {LINES}, {ARCS}, {_CUT}, x AS (SELECT a, b, w, pa.gp AS ga FROM arc JOIN p pa ON pa.id = a JOIN p pb ON pb.id = b WHERE pa.gp <> pb.gp)"
    out |= {"given_cross": f"{cross} SELECT 1::BIGINT AS gp, a, b, w, CAST(ga - 2 AS INTEGER) AS a_side FROM x", "given_border": f"{cross} SELECT DISTINCT 1::BIGINT AS gp, a AS id FROM x"}
    out["given_routes"] = f"""WITH RECURSIVE {LINES}, {_sets()}, {_CUT}, links AS (SELECT src AS a, dst AS b, w FROM e UNION ALL SELECT dst, src, w FROM e),
        bo AS (SELECT DISTINCT a AS id FROM links JOIN p pa ON pa.id = a JOIN p pb ON pb.id = b WHERE pa.gp <> pb.gp),
        arc AS (SELECT a, b, w FROM links JOIN p pa ON pa.id = a JOIN p pb ON pb.id = b WHERE pa.gp = pb.gp), {_search(1000)}
        SELECT CAST(p.gp AS BIGINT) AS gp, u, x AS border, CAST(d AS BIGINT) AS d FROM q JOIN bo ON bo.id = q.x JOIN p ON p.id = q.x"""
    out |= {"given_local_pairs": _given(0), "given_one_cross": _given(1), "given_per_level": _given(1), "given_closure": _pairs("lines", 1000), "given_table_function": _given(0)}
    out["euclid_pairs"] = f"WITH {_POINTS}, v AS (SELECT id FROM p), {_sets()} SELECT a.id AS u, b.id AS v, CAST(floor(1000 * {_DIST}) AS BIGINT) AS d FROM p a JOIN r ON r.id = a.id, p b JOIN s ON s.id = b.id ORDER BY d, u, v LIMIT 80"
    every = f"WITH RECURSIVE {MESH}, {ARCS}, {_search(3500, 'SELECT id, id, 0::BIGINT FROM v')} SELECT u, x AS v, CAST(d AS BIGINT) AS d FROM q WHERE u <> x"
    out |= {"all_pairs_mesh": every, "all_pairs_recursive": every}
    band = lambda c: f"CAST(floor({_hash(c)} * 4 / 10007) AS BIGINT)"
    differ = f"{band('src')} <> {band('dst')}"
    out["balanced_hash_cut"] = f"""WITH {URBAN}, z AS (SELECT {band('id')} AS g, count(*) AS n FROM v GROUP BY 1)
        SELECT count(*) FILTER ({differ}) AS n_cut, CAST(sum(w) FILTER ({differ}) AS BIGINT) AS cut_weight, min(w) FILTER ({differ}) AS sep, (SELECT max(n) / avg(n) FROM z) AS largest FROM e"""
    out |= {
        "hierarchy_nodes": f"WITH {_EIGHT} SELECT * FROM nodes", "hierarchy_schedule": f"WITH {_EIGHT} SELECT wave, gp, height, CAST(i % 3 AS INTEGER) AS slot, CAST(i // 3 AS INTEGER) AS turn FROM plan",
        "hierarchy_borders": f"""WITH {_EIGHT}, bo AS (SELECT DISTINCT node, x AS id FROM (SELECT node, src AS x FROM cr UNION ALL SELECT node, dst FROM cr)), nb AS (SELECT node, count(*) AS n_border FROM bo GROUP BY 1)
            SELECT node AS gp, count(*) AS n_cross, CAST(sum(w) AS BIGINT) AS cut_weight, n_border FROM cr JOIN nb USING (node) GROUP BY node, n_border""",
        "hierarchy_balance": f"WITH {_EIGHT} SELECT parent AS gp, CAST(sum(n_vertices) FILTER (side = 0) AS BIGINT) AS n_left, CAST(sum(n_vertices) FILTER (side = 1) AS BIGINT) AS n_right FROM nodes WHERE gp > 1 GROUP BY 1",
        "imbalance": f"WITH {_EIGHT} SELECT count(*) AS leaves, max(n_vertices) AS largest, min(n_vertices) AS smallest, max(n_vertices) / avg(n_vertices) AS ratio FROM nodes WHERE leaf",
        "idle_slots": f"""WITH {_EIGHT}, sl AS (SELECT wave, i % 3 AS slot, sum(n_vertices) AS busy FROM plan JOIN nodes USING (gp) GROUP BY 1, 2), wv AS (SELECT max(busy) AS span, sum(busy) AS work FROM sl GROUP BY wave)
            SELECT 1 - CAST(sum(work) AS DOUBLE) / (sum(span) * 3) AS idle FROM wv""",
        "recall_modes": _recall(),
    }
    out |= {"objects_latest": f"WITH {_OBJECTS} SELECT oid, src, dst, off, kind FROM ob", "objects_closest": _CLOSEST, "objects_embedded": _CLOSEST, "objects_by_parts": _CLOSEST}
    geo = "geo AS (SELECT o_orderkey AS id, r_name, n_name FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)"
    wrap = lambda body, q=near: f"WITH pr AS ({q}) {body}"
    out |= {
        "rollup_pairs_by_region": wrap(f", {geo} SELECT r_name, n_name, count(*) AS n, min(d) AS least FROM pr JOIN geo ON geo.id = u GROUP BY ROLLUP (r_name, n_name)"),
        "cube_gp_pairs": wrap("SELECT u % 4 AS gp_u, v % 4 AS gp_v, count(*) AS n FROM pr GROUP BY CUBE (u % 4, v % 4)"),
        "grouping_sets_pairs": wrap("SELECT ub, vb, CAST(grouping(ub, vb) AS BIGINT) AS g, count(*) AS n FROM (SELECT u % 3 AS ub, v % 3 AS vb FROM pr) GROUP BY GROUPING SETS ((ub), (vb), ())"),
        "knn_per_u": wrap("SELECT u, v, d, rank FROM (SELECT *, row_number() OVER (PARTITION BY u ORDER BY d, v) AS rank FROM pr) WHERE rank <= 2"),
        "set_ops_pairs": f"WITH wide AS ({_pairs('interstate', 150)}), pr AS ({near}) (SELECT * FROM wide EXCEPT ALL SELECT * FROM pr) UNION ALL (SELECT * FROM wide INTERSECT SELECT * FROM pr WHERE d <= 10)",
        "ranked_pairs": wrap("SELECT u, v, d, rank() OVER (PARTITION BY u ORDER BY d) AS rank, dense_rank() OVER (PARTITION BY u ORDER BY d) AS dense_rank, ntile(4) OVER (PARTITION BY u ORDER BY d, v) AS quartile FROM pr"),
        "pairs_nearby": wrap("SELECT u, v, d, count(*) OVER (PARTITION BY u ORDER BY d RANGE BETWEEN 10 PRECEDING AND 10 FOLLOWING) AS n FROM pr"),
        "paged_pairs": wrap("SELECT u, v, d FROM pr ORDER BY d, u, v LIMIT 10 OFFSET 10"),
        "chain_lengths": "SELECT user_id AS chain, event_id AS pos, CAST(sum(CAST(floor(abs(value)) AS BIGINT)) OVER (PARTITION BY user_id ORDER BY event_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS upto FROM events",
        "pivot_events": "SELECT user_id, count(*) FILTER (event_type = 'view') AS view, count(*) FILTER (event_type = 'purchase') AS purchase FROM events GROUP BY user_id",
        "asof_position": "SELECT q.event_id, (SELECT max_by(f.event_id, (f.ts, f.event_id)) FROM events f WHERE f.user_id = q.user_id AND f.event_type = 'view' AND f.ts <= q.ts) AS seen FROM events q WHERE q.event_type = 'purchase'",
        "interval_meetings": "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id <> b.user_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 120000000 WHERE a.event_type = 'view' AND b.event_type = 'purchase'",
        "session_positions": "WITH t AS (SELECT user_id, ts, event_id, CASE WHEN epoch_us(ts) - epoch_us(lag(ts) OVER k) > 86400000000 THEN 1 ELSE 0 END AS f FROM events WINDOW k AS (PARTITION BY user_id ORDER BY ts, event_id)), u AS (SELECT user_id, CAST(sum(f) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS session FROM t) SELECT user_id, session, count(*) AS n_events FROM u GROUP BY ALL",
        "json_props": "SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1",
        "page_links": """WITH l AS (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) AS href FROM pages) SELECT page_id, href, count(*) AS n FROM l GROUP BY ALL""",
    }
    return out
