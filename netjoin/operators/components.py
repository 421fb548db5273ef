"""Connected components by alternating star contractions over an edge table.

Each round is a few shuffles of the edges; labels never visit the driver. Large stars hang every larger
neighbour of a vertex on its smallest neighbour, small stars do the same with the smaller ones; at the fixed point
every component is one star around its smallest id.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from netjoin.functions.workspace import drop_tables, materialise


def _star(edges: DataFrame, large: bool, tables: list[DataFrame]) -> DataFrame:
    """edges (a > b): one large-star or small-star contraction; what it writes is added to ``tables``."""
    both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))) if large else edges
    # written first: then both sides of the join on a hub are plain exchanges, which AQE can split
    least = materialise(both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m")), "cc-least")
    tables.append(least)
    hung = both.join(least.hint("merge"), "a")
    if large:
        out = hung.where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"))
    else:
        out = hung.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(hung.select("a", F.col("m").alias("b")))
    return out.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()


def connected_components(edges: DataFrame, *, max_rounds: int = 60) -> DataFrame:
    """(id, component) for every vertex that has an edge; component is the smallest id reachable.

    ``edges`` has columns a, b (any order, repeats and self-loops allowed, null ends dropped). A vertex
    whose only edges are self-loops does not appear.
    """
    now = materialise(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "cc-edges")
    seen = None
    for _ in range(max_rounds):
        state = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")), F.sum(F.col("b").cast("decimal(38,0)"))).first()
        if tuple(state) == seen or not state[0]:
            break
        seen = tuple(state)
        tables = [now]
        now = materialise(_star(_star(now, True, tables), False, tables), "cc-edges")
        drop_tables(*tables)
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return now.groupBy("a").agg(F.min("b").alias("b")).select(F.col("a").alias("id"), F.col("b").alias("component")).unionByName(now.select(F.col("b").alias("id"), F.col("b").alias("component")).distinct())
