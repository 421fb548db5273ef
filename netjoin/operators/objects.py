"""Objects on edges: positions as distances from the edge's ends, joined without or with being built into the graph."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from netjoin.functions.workspace import materialise
from netjoin.operators.network import Network
from netjoin.operators.relax import relax


def latest_positions(positions: DataFrame) -> DataFrame:
    """The last position (by ts, then event_id) of every object: oid, eid, off, kind."""
    return positions.groupBy("oid").agg(F.max(F.struct("ts", "event_id", "eid", "off", "kind")).alias("m")).select("oid", "m.eid", "m.off", "m.kind")


def _ends(net: Network, objects: DataFrame, cost: str) -> DataFrame:
    """oid, node, cost: reaching either end of the object's edge."""
    on = objects.join(net.edges, "eid")
    return on.select("oid", F.explode(F.array(F.struct(F.col("src").alias("node"), F.col("off").alias(cost)), F.struct(F.col("dst").alias("node"), (F.col("w") - F.col("off")).alias(cost)))).alias("e")).select("oid", "e.node", f"e.{cost}")


def closest_objects(net: Network, r: DataFrame, s: DataFrame, k: int | None, theta: int) -> DataFrame:
    """(u, v, d) of objects (oid, eid, off) kept beside the undirected graph: two seeds for each object of R, two finishes for each of S,
    and the direct way for objects on one edge."""
    seeds = _ends(net, r, "d").select(F.col("oid").alias("src"), "node", "d")
    reached = relax(net.arcs, seeds, theta)
    over = reached.join(_ends(net, s, "d2"), "node").select(F.col("src").alias("u"), F.col("oid").alias("v"), (F.col("d") + F.col("d2")).alias("d"))
    same = r.select(F.col("oid").alias("u"), "eid", F.col("off").alias("o1")).join(s.select(F.col("oid").alias("v"), "eid", F.col("off").alias("o2")), "eid").select("u", "v", F.abs(F.col("o1") - F.col("o2")).alias("d"))
    best = over.unionByName(same).where(F.col("d") <= theta).groupBy("u", "v").agg(F.min("d").alias("d"))
    return best.orderBy("d", "u", "v").limit(k) if k is not None else best


def embed_objects(net: Network, objects: DataFrame, *, offset: int = -(10**12)) -> tuple[Network, DataFrame]:
    """The network with edges split at objects, and (oid, id, src) of each object: its vertex, and the first end of its edge. Objects at one place share a vertex; at an end they are the end."""
    on = objects.join(net.edges, "eid")
    place = on.groupBy("eid", "off").agg(F.min("oid").alias("first"))
    at = on.join(place, ["eid", "off"]).withColumn("id", F.when(F.col("off") == 0, F.col("src")).when(F.col("off") == F.col("w"), F.col("dst")).otherwise(F.lit(offset) - F.col("first")))
    where = materialise(at.select("oid", "id", "eid", "off", "src", "dst", "w"), "embedded")
    inner = where.where("off > 0 AND off < w").select("eid", "off", "id").distinct()
    split = inner.select("eid").distinct()
    ends = net.edges.join(split, "eid", "left_semi")
    points = inner.unionByName(ends.select("eid", F.lit(0).cast("long").alias("off"), F.col("src").alias("id"))).unionByName(ends.select("eid", F.col("w").alias("off"), F.col("dst").alias("id")))
    order = Window.partitionBy("eid").orderBy("off")
    pieces = points.withColumn("next", F.lead("id").over(order)).withColumn("w", F.lead("off").over(order) - F.col("off")).where("next IS NOT NULL")
    edges = net.edges.join(split, "eid", "left_anti").unionByName(pieces.select(F.xxhash64("eid", "id", "next").alias("eid"), F.col("id").alias("src"), F.col("next").alias("dst"), "w"))
    return Network(net.vertices.unionByName(inner.select("id").distinct()), materialise(edges, "embedded-edges"), net.directed), where.select("oid", "id", "src")


def closest_embedded(net: Network, r: DataFrame, s: DataFrame, k: int | None, theta: int) -> DataFrame:
    """The same answer as ``closest_objects``, with the objects built into the graph."""
    built, where = embed_objects(net, r.select("oid", "eid", "off").unionByName(s.select("oid", "eid", "off")).distinct())
    at_r, at_s = r.select("oid").join(where, "oid"), s.select("oid").join(where, "oid")
    reached = relax(built.arcs, at_r.select(F.col("oid").alias("src"), F.col("id").alias("node"), F.lit(0).cast("long").alias("d")), theta)
    best = reached.join(at_s.select(F.col("oid").alias("v"), F.col("id").alias("node")), "node").groupBy(F.col("src").alias("u"), "v").agg(F.min("d").alias("d"))
    return best.orderBy("d", "u", "v").limit(k) if k is not None else best
