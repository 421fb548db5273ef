"""Measures of partitions and answers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from netjoin.operators.partition import Hierarchy


def separation(tree: Hierarchy) -> DataFrame:
    """gp, sep: the lightest cross-edge of every inner part."""
    return tree.cross.groupBy("gp").agg(F.min("w").alias("sep"))


def imbalance(tree: Hierarchy) -> DataFrame:
    """leaves, largest, smallest, ratio: the largest leaf over the mean."""
    leaf = tree.nodes.where("leaf")
    return leaf.agg(F.count(F.lit(1)).alias("leaves"), F.max("n_vertices").alias("largest"), F.min("n_vertices").alias("smallest"), (F.max("n_vertices") / F.avg("n_vertices")).alias("ratio"))


def split_balance(tree: Hierarchy) -> DataFrame:
    """gp, n_left, n_right of every inner part."""
    kids = tree.nodes.where("gp > 1").groupBy(F.col("parent").alias("gp")).agg(F.sum(F.when(F.col("side") == 0, F.col("n_vertices"))).alias("n_left"), F.sum(F.when(F.col("side") == 1, F.col("n_vertices"))).alias("n_right"))
    return kids


def border_profile(tree: Hierarchy) -> DataFrame:
    """gp, n_cross (edges), cut_weight, n_border of every inner part."""
    cross = tree.cross.groupBy("gp").agg(F.count_distinct("eid").alias("n_cross"), (F.sum("w") / 2).cast("long").alias("cut_weight"))
    return cross.join(tree.border.groupBy("gp").agg(F.count(F.lit(1)).alias("n_border")), "gp")


def recall_report(answer: DataFrame, exact: DataFrame) -> DataFrame:
    """n_exact, n_found, n_equal (same distance), recall, equal_share, mean_stretch of an answer against the exact pairs."""
    both = exact.select("u", "v", F.col("d").alias("e")).join(answer.select("u", "v", "d"), ["u", "v"], "left")
    return both.agg(F.count(F.lit(1)).alias("n_exact"), F.count("d").alias("n_found"), F.count_if(F.col("d") == F.col("e")).alias("n_equal"), (F.count("d") / F.count(F.lit(1))).alias("recall"),
                    (F.count_if(F.col("d") == F.col("e")) / F.count(F.lit(1))).alias("equal_share"), F.avg(F.col("d") / F.col("e")).alias("mean_stretch"))


def idle_share(plan: DataFrame, costs: DataFrame, parallelism: int) -> DataFrame:
    """Idle slot share of a schedule (wave, gp, slot) when every part costs what ``costs`` (gp, cost) says: waves wait for their slowest slot."""
    slots = plan.join(costs, "gp").groupBy("wave", "slot").agg(F.sum("cost").alias("busy"))
    waves = slots.groupBy("wave").agg(F.max("busy").alias("span"), F.sum("busy").alias("work"))
    return waves.agg((1 - F.sum("work") / (F.sum("span") * parallelism)).alias("idle"))


def shuffle_totals(spark: SparkSession, since: int = 0) -> dict[str, int]:
    """Stages started by this application so far, and what those numbered ``since`` or later shuffled and spilled, in bytes.

    For one action, pass the ``stages`` of a call before it. Spark's status store keeps only the latest ``spark.ui.retainedStages`` stages.
    """
    listed = spark.sparkContext._jsc.sc().statusStore().stageList(None, False, False, spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0), None)
    out = {"shuffle_write": 0, "spilled": 0, "stages": since}
    for i in range(listed.size()):
        stage = listed.apply(i)
        if stage.stageId() >= since:
            out["shuffle_write"] += stage.shuffleWriteBytes()
            out["spilled"] += stage.diskBytesSpilled()
            out["stages"] = max(out["stages"], stage.stageId() + 1)
    return out
