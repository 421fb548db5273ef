"""Python table functions for SQL users."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import LongType, StructField, StructType
from pyspark.sql.udtf import AnalyzeArgument, AnalyzeResult

from netjoin.operators import kernels


@udtf
class LeafPairs:
    """``leaf_pairs(TABLE(rows) PARTITION BY gp, theta)`` over rows (gp, role, a, b, w): arcs, and operands r and s with their id in ``a``.

    Polymorphic: ids come back in the type of column ``a``.
    """

    @staticmethod
    def analyze(rows: AnalyzeArgument, theta: AnalyzeArgument) -> AnalyzeResult:
        if not rows.isTable or not {"role", "a", "b", "w"} <= set(rows.dataType.names):
            raise ValueError("leaf_pairs needs a table with the columns gp, role, a, b and w")
        kind = rows.dataType["a"].dataType
        return AnalyzeResult(StructType([StructField("u", kind), StructField("v", kind), StructField("d", LongType())]))

    def __init__(self):
        self.rows: list[Row] = []
        self.theta = 0

    def eval(self, row: Row, theta: int) -> None:
        self.rows.append((row["role"], row["a"], row["b"], row["w"]))
        self.theta = theta

    def terminate(self) -> Iterator[tuple[int, int, int]]:
        arcs = np.array([r[1:] for r in self.rows if r[0] == "arc"], np.int64).reshape(-1, 3)
        of = {n: np.array([r[1] for r in self.rows if r[0] == n], np.int64) for n in ("r", "s")}
        g = kernels.LocalGraph(*arcs.T, of["r"])
        start = g.local(of["r"])
        x, y, d = kernels.reach(g, start, np.zeros(len(start), np.int64), {"pair": g.mask(of["s"])}, kernels.BestPairs(None, self.theta))["pair"]
        yield from zip(g.ids[x].tolist(), g.ids[y].tolist(), d.tolist())


def register(spark: SparkSession) -> None:
    spark.udtf.register("leaf_pairs", LeafPairs)


def kth_distance_udaf(k: int):
    """A grouped aggregate in Python: the k-th least distinct distance of a group, null if there are fewer. ``kth_distance_native`` is the same in SQL expressions."""

    @pandas_udf("long")
    def kth(d: pd.Series) -> int:
        least = sorted(set(d.dropna()))
        return int(least[k - 1]) if len(least) >= k else None

    return kth


def kth_distance_native(column: str, k: int) -> Column:
    return F.try_element_at(F.array_sort(F.collect_set(column)), F.lit(k))
