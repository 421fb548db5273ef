"""Objects on edges through the partitioned joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from netjoin.operators.network import Network
from netjoin.operators.objects import embed_objects
from netjoin.operators.partition import Hierarchy, from_assignment
from netjoin.plans.joins import closest_at, kth_distance, within_at


def embedded_hierarchy(built: Network, where: DataFrame, tree: Hierarchy) -> Hierarchy:
    """The hierarchy with objects' vertices (oid, id, src) built in: each joins the leaf of its edge's first end."""
    at = tree.assign.select("id", "gp")
    added = where.select("id", "src").distinct().join(at.select("id"), "id", "left_anti").groupBy("id").agg(F.min("src").alias("src"))
    return from_assignment(built, at.unionByName(added.join(at.select(F.col("id").alias("src"), "gp"), "src").select("id", "gp")))


def closest_objects_by_parts(net: Network, r: DataFrame, s: DataFrame, k: int | None, theta: int, hierarchy: Hierarchy, **options) -> DataFrame:
    """The answer of ``closest_objects`` (operators), searched part by part: objects (oid, eid, off) are built into the network and its hierarchy.

    With k, the k closest pairs of places give the radius in which pairs of objects are counted. Options as in ``distance_join``.
    """
    built, where = embed_objects(net, r.select("oid", "eid", "off").unionByName(s.select("oid", "eid", "off")).distinct())
    tree = embedded_hierarchy(built, where, hierarchy)
    at_r, at_s = (x.select("oid").join(where.select("oid", "id"), "oid") for x in (r, s))
    places = [x.select("id").distinct() for x in (at_r, at_s)]
    if k is not None:
        known = kth_distance(closest_at(built, *places, k, theta, hierarchy=tree, **options), k)
        theta = theta if known is None else known
    pairs = within_at(built, *places, theta, hierarchy=tree, **options)
    found = pairs.join(at_r.select(F.col("id").alias("u"), F.col("oid").alias("ou")), "u").join(at_s.select(F.col("id").alias("v"), F.col("oid").alias("ov")), "v")
    best = found.groupBy(F.col("ou").alias("u"), F.col("ov").alias("v")).agg(F.min("d").alias("d"))
    return best.orderBy("d", "u", "v").limit(k) if k is not None else best
