import datetime as dt
import os

import pytest
from pyspark.sql import functions as F

from netjoin.operators import measures, objects, partition, relational
from netjoin.plans import workloads
from netjoin.plans.joins import JoinReport, distance_join, leaf_tables
from netjoin.plans.object_joins import closest_objects_by_parts
from netjoin.plans.table_functions import kth_distance_native, kth_distance_udaf
from netjoin.sources import tables
from netjoin.streaming import positions
from tests import reference
from tests.test_network_joins import ids, net_of, random_edges, rows


def placed(spark, net, where):
    """objects (oid, eid, off) from (oid, src, dst, off)."""
    df = spark.createDataFrame(where, "oid long, src long, dst long, off long")
    return df.join(net.edges, ["src", "dst"]).select("oid", "eid", "off")


def test_objects_beside_and_inside_agree(spark):
    edges = random_edges(30, 20, 2)
    net = net_of(spark, edges)
    spots = [(i, a, b, [0, w, w // 2, w // 3][i % 4]) for i, (a, b, w) in enumerate(edges)]
    r, s = placed(spark, net, spots[::2] + [(500, *edges[3][:2], 1)]), placed(spark, net, [(1000 + i, *x[1:]) for i, x in enumerate(spots[1::3])] + [(1500, *edges[3][:2], min(4, edges[3][2]))])
    beside, inside = (rows(f(net, r, s, None, 60)) for f in (objects.closest_objects, objects.closest_embedded))
    assert beside == inside
    adj, ends = reference.adjacency(edges), {e[:2]: e[2] for e in edges}
    every_r, every_s = ({x["oid"]: x for x in df.join(net.edges, "eid").collect()} for df in (r, s))
    want = []
    for u, p in every_r.items():
        a, b = reference.distances(adj, p["src"]), reference.distances(adj, p["dst"])
        for v, q in every_s.items():
            d = min(near + far[node] + rest for near, far in ((p["off"], a), (p["w"] - p["off"], b)) for node, rest in ((q["src"], q["off"]), (q["dst"], q["w"] - q["off"])))
            d = min(d, abs(p["off"] - q["off"])) if p["eid"] == q["eid"] else d
            if d <= 60:
                want.append((u, v, d))
    for leaves in (1, 4):
        tree = partition.build_hierarchy(net, leaves=leaves, alpha=0.5)
        assert beside == rows(closest_objects_by_parts(net, r, s, None, 60, tree))
        assert beside[:7] == rows(closest_objects_by_parts(net, r, s, 7, 60, tree))
    assert beside == sorted(want, key=lambda x: (x[2], x[0], x[1])) and ends
    assert rows(objects.closest_objects(net, r, s, 5, 60)) == beside[:5]


def test_latest_positions(spark):
    t = lambda m: dt.datetime(2024, 1, 1, 0, m)
    df = spark.createDataFrame([(1, t(1), 7, 1, 0, "r"), (2, t(3), 7, 2, 5, "r"), (3, t(3), 7, 3, 6, "r"), (4, t(2), 8, 4, 1, "s")], "event_id long, ts timestamp, oid long, eid long, off long, kind string")
    assert {r["oid"]: r["eid"] for r in objects.latest_positions(df).collect()} == {7: 3, 8: 4}


def test_large_leaves_are_dealt_to_tasks(spark):
    edges = random_edges(60, 40, 6)
    net = net_of(spark, edges)
    r, s = ids(spark, range(0, 60, 3)), ids(spark, range(1, 60, 3))
    tree = partition.build_hierarchy(net, leaves=2, alpha=0.5)
    for options in ({}, {"schedule": "pool", "parallelism": 3}):
        one, many = ({tuple(x) for x in distance_join(net, r, s, 80, hierarchy=tree, sources_per_task=n, **options).collect()} for n in (1000, 3))
        assert one == many and one
    assert leaf_tables(net, tree, r, s, 80).groupBy("kind").count().count() == 4


def test_forest_hierarchy(spark):
    edges = random_edges(40, 30, 12)
    net = net_of(spark, edges)
    r, s = ids(spark, range(0, 40, 4)), ids(spark, range(1, 40, 4))
    tree = partition.hierarchy_from_forest(net, leaves=4)
    assert tree.assign.count() == 40
    assert rows(distance_join(net, r, s, 70, hierarchy=tree)) == reference.pairs(edges, set(range(0, 40, 4)), set(range(1, 40, 4)), 70)
    by_forest = partition.build_hierarchy(net, leaves=2, engine="joins")
    assert by_forest.nodes.where("leaf").count() == 2


@pytest.mark.parametrize("fmt", ["parquet", "orc", "csv", "json", "text"])
def test_edge_formats(spark, tmp_path, fmt):
    df = spark.createDataFrame([(1, 2, 3), (2, 3, 4)], "src long, dst long, w long")
    path = str(tmp_path / fmt)
    (df.select(F.concat_ws(" ", "src", "dst", "w")).write.text(path) if fmt == "text" else df.write.format(fmt).save(path))
    assert sorted(map(tuple, tables.read_edges(spark, path, fmt).collect())) == [(1, 2, 3), (2, 3, 4)]


def test_stored_network(spark, tmp_path):
    net = net_of(spark, random_edges(20, 10, 1))
    tables.save_network(net, str(tmp_path / "net"), buckets=4, table="stored_arcs")
    again = tables.load_network(spark, str(tmp_path / "net"))
    assert again.edges.count() == net.edges.count() and spark.table("stored_arcs").count() == net.arcs.count()
    plan = spark.table("stored_arcs").groupBy("a").agg(F.min("w"))._jdf.queryExecution().executedPlan().toString()
    assert "Exchange hashpartitioning" not in plan
    tables.register_views(net, ids(spark, [1]), ids(spark, [2]))
    assert spark.sql("SELECT count(*) FROM net_edges").first()[0] == net.edges.count()
    tables.write_pairs(distance_join(net, ids(spark, [1]), ids(spark, [2]), 50), str(tmp_path / "pairs"), "csv")
    tables.write_pairs(net.edges, fmt="noop")


def test_stored_hierarchy(spark, tmp_path):
    edges = random_edges(50, 30, 4)
    net, r, s = net_of(spark, edges), ids(spark, range(0, 50, 4)), ids(spark, range(1, 50, 4))
    tree = partition.build_hierarchy(net, leaves=4, alpha=0.5)
    tables.save_hierarchy(tree, str(tmp_path / "tree"))
    again = tables.load_hierarchy(spark, str(tmp_path / "tree"))
    assert rows(distance_join(net, r, s, 70, hierarchy=again)) == rows(distance_join(net, r, s, 70, hierarchy=tree))
    leaf = again.leaves[0]["gp"]
    plan = again.arcs.where(F.col("gp") == leaf)._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(gp" in plan


def test_scratch_needs_a_shared_folder(spark, monkeypatch):
    from types import SimpleNamespace

    from netjoin.functions import workspace

    cluster = SimpleNamespace(conf=SimpleNamespace(get=lambda *a: None), sparkContext=SimpleNamespace(master="spark://a:7077", getCheckpointDir=lambda: None))
    with pytest.raises(RuntimeError, match="spark.checkpoint.dir"):
        workspace.shared_dir(cluster)
    kept, seen = workspace.counted(spark.range(5).where("id > 9"), "none", total=F.sum("id"))
    assert kept.count() == 0 and seen["n"] == 0 and seen["total"] == 0
    with workspace.passing(spark) as keep:
        gone, here = workspace.materialise(spark.range(3), "gone"), keep(workspace.materialise(spark.range(4), "here"))
        left = gone.inputFiles()[0].removeprefix("file://")
        assert os.path.exists(left)
    assert not os.path.exists(left) and here.count() == 4
    files = [f.removeprefix("file://") for f in here.inputFiles()]
    workspace.drop_tables(here)
    assert not any(map(os.path.exists, files))


def test_reports(spark):
    report = JoinReport(searches=[(0, 0, 0, 10), (0, 1, 0, 5), (1, 0, 20, 24)])
    assert report.idle_share(2) == 1 - 19 / 28


def test_relational_helpers(spark):
    pairs = spark.createDataFrame([(1, 5, 3), (1, 6, 2), (1, 7, 2), (2, 5, 9)], "u long, v long, d long")
    by_window = sorted((r["u"], r["v"], r["d"]) for r in relational.nearest_per_source(pairs, 2).collect())
    assert by_window == sorted(map(tuple, relational.nearest_lateral(ids(spark, [1, 2, 3]), pairs, 2).collect())) == [(1, 6, 2), (1, 7, 2), (2, 5, 9)]
    udaf = {r["u"]: r["x"] for r in pairs.groupBy("u").agg(kth_distance_udaf(2)("d").alias("x")).collect()}
    assert udaf == {r["u"]: r["x"] for r in pairs.groupBy("u").agg(kth_distance_native("d", 2).alias("x")).collect()} == {1: 3, 2: None}
    before = measures.shuffle_totals(spark)
    pairs.repartition(3, "u").count()
    assert measures.shuffle_totals(spark)["stages"] > before["stages"]


def test_recall(spark):
    exact = spark.createDataFrame([(1, 2, 4), (1, 3, 5)], "u long, v long, d long")
    row = measures.recall_report(exact.where("v = 2").withColumn("d", F.col("d") + 4), exact).first()
    assert (row["n_exact"], row["n_found"], row["n_equal"], row["recall"], row["mean_stretch"]) == (2, 1, 0, 0.5, 2.0)


# streams


@pytest.fixture(scope="module")
def event_files(spark, sf, tmp_path_factory):
    """The events in three files by time, so that a stream sees them in order."""
    folder = tmp_path_factory.mktemp("events")
    e = spark.read.parquet(f"{sf}/events.parquet")
    cuts = [r[0] for r in e.select("ts").orderBy("ts").collect()]
    bounds = [cuts[0], cuts[len(cuts) // 3], cuts[2 * len(cuts) // 3], cuts[-1] + dt.timedelta(days=1)]
    for i in range(3):
        part = e.where((F.col("ts") >= F.lit(bounds[i])) & (F.col("ts") < F.lit(bounds[i + 1]))).toPandas()
        part["ts"] = part["ts"].astype("datetime64[us]")
        part.to_parquet(folder / f"part{i}.parquet", coerce_timestamps="us", allow_truncated_timestamps=True)
    return str(folder)


def drain(df, name, mode):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination(180)
    return df.sparkSession.table(name)


def test_windows(spark, sf, event_files):
    e = spark.read.parquet(f"{sf}/events.parquet")
    got = drain(positions.windowed_counts(positions.read_events(spark, event_files), length="1 day"), "daily", "complete")
    want = e.groupBy(F.date_trunc("day", "ts").alias("start"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    assert got.agg(F.sum("n")).first()[0] == e.count() and got.count() == want.count()
    slid = drain(positions.windowed_counts(positions.read_events(spark, event_files), length="1 day", slide="12 hours"), "slid", "complete")
    assert slid.agg(F.sum("n")).first()[0] == 2 * e.count()
    runs = drain(positions.session_counts(positions.read_events(spark, event_files)), "runs", "complete")
    assert runs.agg(F.sum("n")).first()[0] == e.count()


def test_tracking_and_closest(spark, sf, event_files, tmp_path):
    net = workloads.prepared_network(spark, sf, "urban")
    n = net.vertices.count()
    e = spark.read.parquet(f"{sf}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    last = objects.latest_positions(positions.positions_of(e, net.edges, n))
    want = {r["oid"]: (r["eid"], r["off"]) for r in last.collect()}
    moves = drain(positions.tracked_positions(positions.positions_of(positions.read_events(spark, event_files), net.edges, n), silent="4000 days"), "moves", "update")
    got = {r["oid"]: (r["m"]["eid"], r["m"]["off"]) for r in moves.groupBy("oid").agg(F.max(F.struct("micros", "eid", "off")).alias("m")).collect()}
    assert set(got) == set(want)
    seen = {}
    q = positions.stream_closest_objects(positions.read_events(spark, event_files), net, n, 10, 1500, str(tmp_path / "store"), lambda df, epoch: seen.__setitem__(epoch, rows(df)), checkpoint=str(tmp_path / "checkpoint"))
    q.awaitTermination(300)
    assert q.exception() is None and len(seen) >= 3
    assert seen[max(seen)] == rows(objects.closest_objects(net, last.where("kind = 'r'"), last.where("kind = 's'"), 10, 1500))


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    """A batch far behind the watermark: its rows are dropped, and Spark's count says how many."""
    schema = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
    for i, (day, n) in enumerate(((20, 5), (20, 1), (1, 3))):
        spark.createDataFrame([(100 * i + j, dt.datetime(2024, 1, day, j), 1, "view", 0.0, "{}") for j in range(n)], schema).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    counts = positions.windowed_counts(positions.read_events(spark, str(tmp_path / "in")), length="1 hour")
    q = counts.writeStream.format("memory").queryName("late").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination(180)
    assert positions.late_rows(q) == 3


def test_stateful_processor(spark, sf, event_files):
    """The value-state processor ends at the positions that the batch has."""
    net = workloads.prepared_network(spark, sf, "urban")
    n = net.vertices.count()
    name = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(name)
    spark.conf.set(name, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        moves = drain(positions.positions_by_processor(positions.positions_of(positions.read_events(spark, event_files), net.edges, n)), "processed", "update")
        got = {r["oid"]: r["m"]["eid"] for r in moves.groupBy("oid").agg(F.max(F.struct("micros", "eid")).alias("m")).collect()}
    finally:
        spark.conf.set(name, before)
    e = spark.read.parquet(f"{sf}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    assert set(got) == {r["oid"] for r in objects.latest_positions(positions.positions_of(e, net.edges, n)).collect()}


def test_generated_events(spark):
    rate = positions.rate_events(spark, 100, users=7)
    assert rate.isStreaming and rate.columns == ["event_id", "ts", "user_id", "event_type"]


def test_stream_join(spark, event_files):
    both = positions.meetings_stream(positions.read_events(spark, event_files).where("event_type = 'view'"), positions.read_events(spark, event_files).where("event_type = 'purchase'"), 600)
    e = spark.read.parquet(event_files).withColumn("ts", F.col("ts").cast("timestamp"))
    a, b = e.where("event_type = 'view'").alias("a"), e.where("event_type = 'purchase'").alias("b")
    want = a.join(b, F.expr("a.user_id = b.user_id AND b.ts BETWEEN a.ts - INTERVAL 600 MINUTES AND a.ts + INTERVAL 600 MINUTES")).count()
    assert drain(both, "met", "append").count() == want
