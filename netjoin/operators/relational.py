"""Relational helpers around the joins: roll-ups, nearest per vertex, as-of and interval joins, sessions, JSON."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def rollup_pairs(pairs: DataFrame, labels: DataFrame, *keys: str) -> DataFrame:
    """Pair counts and least distance by a roll-up of labels(id, *keys) of u."""
    return pairs.join(labels.withColumnRenamed("id", "u"), "u").rollup(*keys).agg(F.count(F.lit(1)).alias("n"), F.min("d").alias("least"))


def cube_pairs(pairs: DataFrame, assign: DataFrame) -> DataFrame:
    """Pair counts by every combination of the parts of u and v."""
    at = assign.select("id", "gp")
    return pairs.join(at.toDF("u", "gp_u"), "u").join(at.toDF("v", "gp_v"), "v").cube("gp_u", "gp_v").agg(F.count(F.lit(1)).alias("n"))


def nearest_per_source(pairs: DataFrame, k: int) -> DataFrame:
    """The k nearest partners of every u, with their rank."""
    return pairs.withColumn("rank", F.row_number().over(Window.partitionBy("u").orderBy("d", "v"))).where(F.col("rank") <= k)


def nearest_lateral(sources: DataFrame, pairs: DataFrame, k: int) -> DataFrame:
    """The same for every id of ``sources`` by a lateral join, as SQL users write it."""
    spark = sources.sparkSession
    sources.select(F.col("id").alias("u")).createOrReplaceTempView("lateral_sources")
    pairs.createOrReplaceTempView("lateral_pairs")
    return spark.sql(f"SELECT s.u, p.v, p.d FROM lateral_sources s, LATERAL (SELECT v, d FROM lateral_pairs q WHERE q.u = s.u ORDER BY d, v LIMIT {int(k)}) p")


def as_of(queries: DataFrame, facts: DataFrame, key: str, value: str) -> DataFrame:
    """Each query (key, ts, …) with the value of the last fact of its key at or before ts: one union and one window, no range join."""
    q = queries.select(key, "ts", F.lit(1).alias("side"), F.struct(*queries.columns).alias("q"), F.lit(None).cast(facts.schema[value].dataType).alias(value))
    f = facts.select(key, "ts", F.lit(0).alias("side"), F.lit(None).cast(q.schema["q"].dataType).alias("q"), value)
    order = Window.partitionBy(key).orderBy("ts", "side").rowsBetween(Window.unboundedPreceding, 0)
    return q.unionByName(f).withColumn("found", F.last(value, ignorenulls=True).over(order)).where("side = 1").select("q.*", F.col("found").alias(value))


def meetings(left: DataFrame, right: DataFrame, minutes: int) -> DataFrame:
    """Pairs of events (event_id, user_id, ts) of different users within so many minutes: equi-join on time cells, then the exact test."""
    cell = lambda c: F.floor(F.unix_micros(F.col(c).cast("timestamp")) / F.lit(minutes * 60_000_000)).cast("long")
    a = left.select(F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("ts").alias("ta")).withColumn("cell", F.explode(F.array(cell("ta") - 1, cell("ta"), cell("ta") + 1)))
    b = right.select(F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("ts").alias("tb")).withColumn("cell", cell("tb"))
    gap = F.abs(F.unix_micros(F.col("ta").cast("timestamp")) - F.unix_micros(F.col("tb").cast("timestamp")))
    return a.join(b, "cell").where("ua <> ub").where(gap <= minutes * 60_000_000).select("a", "b")


def sessions(events: DataFrame, minutes: int) -> DataFrame:
    """user_id, session, n_events: runs of a user's events without a gap above so many minutes."""
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    micros = F.unix_micros(F.col("ts").cast("timestamp"))
    fresh = F.when(micros - F.lag(micros).over(order) > minutes * 60_000_000, 1).otherwise(0)
    return events.withColumn("fresh", fresh).withColumn("session", F.sum("fresh").over(order.rowsBetween(Window.unboundedPreceding, 0))).groupBy("user_id", "session").agg(F.count(F.lit(1)).alias("n_events"))


def ranked_pairs(pairs: DataFrame) -> DataFrame:
    """u, v, d with the rank, dense rank and quartile of d among the pairs of u."""
    order = Window.partitionBy("u").orderBy("d")
    quartile = F.ntile(4).over(Window.partitionBy("u").orderBy("d", "v"))
    return pairs.select("u", "v", "d", F.rank().over(order).cast("long").alias("rank"), F.dense_rank().over(order).cast("long").alias("dense_rank"), quartile.cast("long").alias("quartile"))


def pairs_nearby(pairs: DataFrame, width: int) -> DataFrame:
    """u, v, d, n: pairs of u whose distance is within ``width`` of this one's, by a range frame."""
    return pairs.withColumn("n", F.count(F.lit(1)).over(Window.partitionBy("u").orderBy("d").rangeBetween(-width, width)))


def chain_lengths(steps: DataFrame) -> DataFrame:
    """chain, pos, upto: running length of steps (chain, pos, w)."""
    return steps.select("chain", "pos", F.sum("w").over(Window.partitionBy("chain").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)).alias("upto"))


def pivot_counts(rows: DataFrame, down: str, across: str, values: list[str]) -> DataFrame:
    """A row for each value of ``down`` and a column for each value of ``across``, with counts."""
    return rows.groupBy(down).pivot(across, values).agg(F.count(F.lit(1))).select(down, *(F.coalesce(F.col(v), F.lit(0)).alias(v) for v in values))


def page_of(pairs: DataFrame, number: int, size: int) -> DataFrame:
    """A page of the pairs in their total order, from number 0."""
    return pairs.orderBy("d", "u", "v").offset(number * size).limit(size)
