"""What the joins are compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from netjoin.functions.workspace import counted, drop_tables
from netjoin.operators.neighbours import vector_pairs
from netjoin.operators.network import Network
from netjoin.operators.relax import distances_from


def euclid_pairs(points: DataFrame, r: DataFrame, s: DataFrame, k: int | None, theta: int) -> DataFrame:
    """(u, v, d) by straight-line distance, d = floor(1000 * L2): points(id, e array of numbers). R meets S block against block; no network is used. Null vectors pair with nothing."""
    whole = points.where("e IS NOT NULL")
    return vector_pairs(whole.join(r, "id", "left_semi"), whole.join(s, "id", "left_semi"), k, theta)


def all_pairs(net: Network, theta: int) -> DataFrame:
    """(u, v, d) of every two different vertices within theta."""
    return distances_from(net.arcs, net.vertices, theta).where("src <> node").select(F.col("src").alias("u"), F.col("node").alias("v"), "d")


def all_pairs_recursive(net: Network, theta: int) -> DataFrame:
    """The same by SQL statements that recur by rounds: a round extends the pairs that the last one improved by an arc, and keeps the least distance of a pair.

    Spark's recursive queries keep every path as a row, which light edges passed to and fro multiply without end; here a pair is one row however many paths join it.
    """
    spark = net.vertices.sparkSession
    sql = lambda text, name, **tables: counted(spark.sql(text, **tables), name)
    arcs, _ = sql("SELECT a, b, min(w) AS w FROM {arcs} WHERE w <= {theta} GROUP BY a, b", "recursive-arcs", arcs=net.arcs, theta=int(theta))
    known, n = sql("SELECT id AS u, id AS v, 0L AS d FROM {vertices}", "recursive-known", vertices=net.vertices.distinct())
    front, n = known, n["n"]
    while n:
        better, seen = sql("""
            SELECT r.u, r.v, r.d FROM (SELECT q.u, a.b AS v, min(q.d + a.w) AS d FROM {front} q JOIN {arcs} a ON a.a = q.v WHERE q.d + a.w <= {theta} GROUP BY q.u, a.b) r
            LEFT JOIN {known} o ON o.u = r.u AND o.v = r.v WHERE o.d IS NULL OR r.d < o.d""", "recursive-front", front=front, arcs=arcs, known=known, theta=int(theta))
        done, n = {id(known): known, id(front): front}, seen["n"]
        known, _ = sql("SELECT u, v, min(d) AS d FROM (SELECT * FROM {known} UNION ALL SELECT * FROM {better}) GROUP BY u, v", "recursive-known", known=known, better=better)
        front = better
        drop_tables(*done.values())
    drop_tables(arcs, *([] if front is known else [front]))
    return known.where("u <> v")
