"""Deterministic networks over the given tables, and operand sets on them."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from netjoin.functions.expressions import BUCKETS, bucket, cents, whole_minutes
from netjoin.operators.neighbours import nearest_vectors
from netjoin.operators.network import Network, make_network
from netjoin.sources.tables import load


def urban_grid(spark: SparkSession, sf_dir: str) -> Network:
    """Order keys row by row on a square grid: all neighbours in a row, three tenths of those below; weights from price differences."""
    o = load(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("id"), "o_custkey", cents(F.col("o_totalprice")).alias("c"))
    width = math.isqrt(o.count())
    right, below = F.when(F.col("id") % width != width - 1, F.col("id") + 1), F.when(F.pmod(F.col("id") * 7919 + F.col("o_custkey"), F.lit(100)) < 30, F.col("id") + width)
    here = o.select(F.col("id").alias("src"), "c", F.explode(F.array(right, below)).alias("dst")).where("dst IS NOT NULL")
    there = o.select(F.col("id").alias("dst"), F.col("c").alias("c2"))
    return make_network(here.join(there, "dst").select("src", "dst", (1 + F.abs(F.col("c") - F.col("c2")) % 1000).alias("w")), o.select("id"))


def interstate_chains(spark: SparkSession, sf_dir: str) -> Network:
    """Orders of a customer in a chain, chains hung on nation hubs, hubs in a ring."""
    o = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    c = load(spark, sf_dir, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_nationkey", F.round(F.abs("c_acctbal")).cast("long").alias("bal"), "c_mktsegment")
    n = load(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("k"))
    by = Window.partitionBy("o_custkey")
    order = by.orderBy("o_orderdate", "o_orderkey")
    chain = o.withColumn("next", F.lead("o_orderkey").over(order)).withColumn("date2", F.lead("o_orderdate").over(order)).withColumn("i", F.row_number().over(order)).withColumn("n", F.count(F.lit(1)).over(by))
    steps = chain.where("next IS NOT NULL").select(F.col("o_orderkey").alias("src"), F.col("next").alias("dst"), (1 + F.datediff("date2", "o_orderdate")).cast("long").alias("w"))
    hub = lambda k: -1 - k
    ends = chain.join(c, "o_custkey")
    ramps = ends.where("i = 1").select(F.col("o_orderkey").alias("src"), hub(F.col("c_nationkey").cast("long")).alias("dst"), (1 + F.col("bal") % 500).alias("w"))
    bridges = ends.where("i = n AND n > 1 AND c_mktsegment = 'BUILDING'").select(F.col("o_orderkey").alias("src"), hub(((F.col("c_nationkey") + 1) % 25).cast("long")).alias("dst"), (1 + F.col("bal") % 700).alias("w"))
    ring = n.select(hub(F.col("k")).alias("src"), hub((F.col("k") + 1) % 25).alias("dst"), (1000 + 37 * F.col("k")).alias("w"))
    return make_network(steps.unionByName(ramps).unionByName(bridges).unionByName(ring), o.select(F.col("o_orderkey").alias("id")).unionByName(n.select(hub(F.col("k")).alias("id"))))


def trade_bipartite(spark: SparkSession, sf_dir: str) -> Network:
    """Parts and suppliers, one edge for each pair that trades; a badly separable graph."""
    li = load(spark, sf_dir, "lineitem").groupBy("l_partkey", "l_suppkey").agg(F.min(F.col("l_quantity").cast("long")).alias("w"))
    ids = load(spark, sf_dir, "part").select(F.col("p_partkey").alias("id")).unionByName(load(spark, sf_dir, "supplier").select((-1 - F.col("s_suppkey")).alias("id")))
    return make_network(li.select((-1 - F.col("l_suppkey")).alias("src"), F.col("l_partkey").alias("dst"), F.greatest("w", F.lit(1)).alias("w")), ids)


def event_lines(spark: SparkSession, sf_dir: str, *, directed: bool = False) -> Network:
    """Events of a user in a line by time; every fourth event transfers to the next event of its type."""
    e = load(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type")

    def follow(key: str, least: int) -> DataFrame:
        order = Window.partitionBy(key).orderBy("ts", "event_id")
        step = e.withColumn("next", F.lead("event_id").over(order)).withColumn("ts2", F.lead("ts").over(order)).where("next IS NOT NULL")
        return step.select(F.col("event_id").alias("src"), F.col("next").alias("dst"), (least + whole_minutes(F.col("ts"), F.col("ts2"))).alias("w"))

    links = follow("user_id", 1).unionByName(follow("event_type", 30).where("src % 4 = 0"))
    return make_network(links, e.select(F.col("event_id").alias("id")), directed=directed)


def embedding_mesh(spark: SparkSession, sf_dir: str, *, neighbours: int = 3) -> Network:
    """Each vector with its nearest others, by distance, then id: exact, block against block."""
    v = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("e"))
    top = nearest_vectors(v, neighbours)
    return make_network(top.select(F.col("id").alias("src"), F.col("id2").alias("dst"), (1 + F.floor(1000 * F.col("dist"))).alias("w")), v.select("id"))


NETWORKS = {"urban": urban_grid, "interstate": interstate_chains, "trade": trade_bipartite, "lines": event_lines, "mesh": embedding_mesh}


def hash_sets(net: Network, r_percent: float, s_percent: float) -> tuple[DataFrame, DataFrame]:
    """R and S of so many percent of the non-negative vertices; disjoint up to 50, and nested as a percentage grows."""
    ids = net.vertices.where("id >= 0").withColumn("h", bucket(F.col("id")))
    cut = BUCKETS / 100
    return ids.where(F.col("h") < r_percent * cut).select("id"), ids.where(F.col("h") >= BUCKETS - s_percent * cut).select("id")


def attribute_sets(spark: SparkSession, sf_dir: str, network: str) -> tuple[DataFrame, DataFrame]:
    """R and S by an attribute: urgent and low orders, views and purchases, or two labels."""
    table, key, column, a, b = {"urban": ("orders", "o_orderkey", "o_orderpriority", "1-URGENT", "5-LOW"), "interstate": ("orders", "o_orderkey", "o_orderpriority", "1-URGENT", "5-LOW"),
                                "lines": ("events", "event_id", "event_type", "view", "purchase"), "mesh": ("embeddings", "vec_id", "label", 0, 1)}[network]
    t = load(spark, sf_dir, table).select(F.col(key).alias("id"), F.col(column).alias("x"))
    return t.where(F.col("x") == a).select("id"), t.where(F.col("x") == b).select("id")


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """page_id, href, n: how often a page links to a target."""
    p = load(spark, sf_dir, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), F.lit(1))).alias("href"))
    return p.groupBy("page_id", "href").agg(F.count(F.lit(1)).alias("n"))
