"""The network type: vertices, weighted edges, and operand sets."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

VERTEX = T.StructType([T.StructField("id", T.LongType())])
EDGE = T.StructType([T.StructField(c, T.LongType()) for c in ("eid", "src", "dst", "w")])
PAIR = T.StructType([T.StructField(c, T.LongType()) for c in ("u", "v", "d")])


@dataclass(frozen=True)
class Network:
    """``vertices(id)`` and ``edges(eid, src, dst, w)``; an undirected edge is stored once."""

    vertices: DataFrame
    edges: DataFrame
    directed: bool = False

    @property
    def arcs(self) -> DataFrame:
        """arcs (eid, a, b, w): both directions of an undirected edge."""
        out = self.edges.select("eid", F.col("src").alias("a"), F.col("dst").alias("b"), "w")
        return out if self.directed else out.unionByName(self.edges.select("eid", F.col("dst").alias("a"), F.col("src").alias("b"), "w"))

    def reversed(self) -> Network:
        """The network with every edge turned round (the same one if undirected)."""
        if not self.directed:
            return self
        return replace(self, edges=self.edges.select("eid", F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))


def make_network(links: DataFrame, vertices: DataFrame | None = None, *, directed: bool = False) -> Network:
    """A network from links (src, dst, w): self-loops go, parallel edges collapse to the lightest, weights below 1 or null are refused.

    Edge ids are a hash of the ends, the same for every run and engine. Vertices default to the ends of links.
    """
    ends = links if directed else links.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "w")
    checked = ends.where("src <> dst").select("src", "dst", F.when(F.col("w") >= 1, F.col("w")).otherwise(F.raise_error(F.lit("edge weights must be at least 1"))).cast("long").alias("w"))
    edges = checked.groupBy("src", "dst").agg(F.min("w").alias("w")).select(F.xxhash64("src", "dst").alias("eid"), "src", "dst", "w")
    if vertices is None:
        vertices = links.select(F.explode(F.array("src", "dst")).alias("id")).distinct()
    return Network(vertices, edges, directed)


def scale_weight(links: DataFrame, factor: float) -> DataFrame:
    """Links whose fractional weights are scaled to whole numbers of at least 1."""
    return links.withColumn("w", F.greatest(F.lit(1), F.round(F.col("w") * factor)).cast("long"))


def assert_disjoint(r: DataFrame, s: DataFrame) -> None:
    """Refuse operand sets that share a vertex."""
    if not r.select("id").join(s.select("id"), "id", "left_semi").isEmpty():
        raise ValueError("the operand sets share vertices")


def swap_operands(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.col("v").alias("u"), F.col("u").alias("v"), "d")
