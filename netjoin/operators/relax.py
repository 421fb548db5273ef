"""The frontier engine: shortest distances by iterated joins, for networks of any size.

Each round joins the states improved last round with the arcs, drops what exceeds the bound before the shuffle, and appends the states that
improve. Known states are not rewritten: a round reads them to compare, and while the front is small beside them they are not shuffled
either. Every few rounds what has been superseded is merged away. Rounds are written to the shared folder, so lineage stays short and lost executors cost one round.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from netjoin.functions.workspace import counted, drop_path, scratch_path

#: Rounds between merges of the written states.
MERGE_ROUNDS = 8
#: Up to so many known states a round is one job that shuffles them; beyond, a front of at most FRONT_ROWS rows is broadcast to them instead.
FEW_STATES, FRONT_ROWS = 2_000_000, 500_000


def relax(arcs: DataFrame, seeds: DataFrame, bound: int | None, *, max_rounds: int = 100_000, report: dict | None = None, early_stop: bool = True) -> DataFrame:
    """(src, node, d): least cost of each node from each source, d <= bound, starting from seeds (src, node, d).

    ``arcs`` has a, b, w (w >= 1). Without a bound it runs until nothing improves; it raises if that takes more than ``max_rounds``. ``report`` receives the
    rounds and the states written (``settled``: each as often as it improved). ``early_stop=False`` keeps arcs heavier than the bound in the joins.
    """
    spark = seeds.sparkSession
    within = (lambda df: df) if bound is None else (lambda df: df.where(F.col("d") <= bound))
    steps = arcs.select(F.col("a").alias("node"), "b", "w")
    if bound is not None and early_stop:
        steps = steps.where(F.col("w") <= bound)
    keys, root = ["src", "node"], scratch_path(spark, "relax")
    shortest = lambda df: df.groupBy(*keys).agg(F.min("d").alias("d"))
    front, n = _write(shortest(within(seeds.select(*keys, "d"))), f"{root}/0")
    files, total, rounds, written = [f"{root}/0"], n, 0, n
    while n:
        if rounds == max_rounds:
            raise RuntimeError(f"distances did not settle in {max_rounds} rounds")
        rounds += 1
        state = spark.read.schema(front.schema).parquet(*files)
        reached = shortest(within(front.join(steps, "node").select("src", F.col("b").alias("node"), (F.col("d") + F.col("w")).alias("d"))))
        known = state
        if total > FEW_STATES:
            reached, m = _write(reached, f"{root}/reached-{rounds}")
            if m <= FRONT_ROWS:
                known = state.join(F.broadcast(reached.select(*keys)), keys, "left_semi")
        known = known.groupBy(*keys).agg(F.min("d").alias("old"))
        better = reached.join(known, keys, "left").where("old IS NULL OR d < old").select(*keys, "d")
        front, n = _write(better, f"{root}/{rounds}")
        if total > FEW_STATES:
            drop_path(spark, f"{root}/reached-{rounds}")
        files, total, improved_rows = files + [f"{root}/{rounds}"], total + n, written + n
        if rounds % MERGE_ROUNDS == 0 and n:
            _, total = _write(shortest(spark.read.schema(front.schema).parquet(*files)), f"{root}/merged-{rounds}")
            for old in files[:-1]:  # the last one is the front
                drop_path(spark, old)
            files = [f"{root}/merged-{rounds}", files[-1]]
    if report is not None:
        report["rounds"] = report.get("rounds", 0) + rounds
        report["settled"] = report.get("settled", 0) + written
    return shortest(spark.read.schema(front.schema).parquet(*files))


def _write(df: DataFrame, path: str) -> tuple[DataFrame, int]:
    out, seen = counted(df, "relax", path=path)
    return out, seen["n"]


def distances_from(arcs: DataFrame, sources: DataFrame, bound: int | None = None) -> DataFrame:
    """(src, node, d) from every id of ``sources``."""
    return relax(arcs, sources.select(F.col("id").alias("src"), F.col("id").alias("node"), F.lit(0).cast("long").alias("d")), bound)


def double_sweep(arcs: DataFrame, vertices: DataFrame) -> tuple[int, int]:
    """Two far vertices: the farthest from the lowest id, then the farthest from that; two searches, one row each to the driver."""
    start = vertices.agg(F.min("id")).first()[0]
    ends = []
    for _ in range(2):
        far = distances_from(arcs, vertices.where(F.col("id") == start).limit(1))
        start = far.agg(F.max(F.struct("d", (-F.col("node")).alias("n")))).first()[0]["n"] * -1
        ends.append(start)
    return ends[0], ends[1]
