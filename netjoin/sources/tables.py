"""Reading and writing: given tables, edge lists in several formats, stored networks, results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from netjoin.operators.network import EDGE, VERTEX, Network
from netjoin.operators.partition import Hierarchy, border_of


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", schema: str = "src long, dst long, w long", **options) -> DataFrame:
    """An edge list as parquet, orc, csv, json or text (three numbers in a line, by spaces); malformed rows fail the read."""
    if fmt == "text":
        parts = spark.read.text(path).selectExpr("split(trim(value), '[ \\t]+') AS p").where("size(p) >= 3")
        return parts.selectExpr("cast(p[0] AS bigint) AS src", "cast(p[1] AS bigint) AS dst", "cast(p[2] AS bigint) AS w")
    reader = spark.read.format(fmt).schema(schema).options(**options)
    return (reader.option("mode", "FAILFAST") if fmt in ("csv", "json") else reader).load(path)


def save_network(net: Network, path: str, *, buckets: int | None = None, table: str | None = None) -> None:
    """Parquet under ``path``; with ``buckets`` and ``table`` the arcs also as a bucketed table, so frontier joins need no shuffle of them."""
    net.vertices.write.mode("overwrite").parquet(f"{path}/vertices")
    net.edges.write.mode("overwrite").parquet(f"{path}/edges")
    if buckets and table:
        net.arcs.write.mode("overwrite").bucketBy(buckets, "a").sortBy("a").saveAsTable(table)


def load_network(spark: SparkSession, path: str, *, directed: bool = False) -> Network:
    return Network(spark.read.schema(VERTEX).parquet(f"{path}/vertices"), spark.read.schema(EDGE).parquet(f"{path}/edges"), directed)


def save_hierarchy(tree: Hierarchy, path: str) -> None:
    """The parts of a network under ``path``, arcs in a folder for each leaf, so that a search of some leaves reads nothing else."""
    for name in ("nodes", "assign", "cross"):
        getattr(tree, name).write.mode("overwrite").parquet(f"{path}/{name}")
    tree.arcs.hint("rebalance", "gp").write.mode("overwrite").partitionBy("gp").parquet(f"{path}/arcs")


def load_hierarchy(spark: SparkSession, path: str) -> Hierarchy:
    nodes, assign, cross = (spark.read.parquet(f"{path}/{name}") for name in ("nodes", "assign", "cross"))
    arcs = spark.read.schema("a long, b long, w long, gp long").parquet(f"{path}/arcs").select("gp", "a", "b", "w")
    return Hierarchy(nodes, assign, cross, border_of(cross), arcs)


def write_pairs(df: DataFrame, path: str | None = None, fmt: str = "parquet") -> None:
    """Write a result; ``noop`` runs the plan without keeping rows."""
    writer = df.write.format(fmt).mode("overwrite")
    writer.save(path) if path else writer.save()


def register_views(net: Network, r: DataFrame, s: DataFrame) -> None:
    """Temp views net_edges, net_vertices, net_r, net_s for SQL."""
    for name, df in (("net_edges", net.edges), ("net_vertices", net.vertices), ("net_r", r), ("net_s", s)):
        df.createOrReplaceTempView(name)
