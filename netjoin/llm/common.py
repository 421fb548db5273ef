"""Helpers that the text operators share."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from netjoin.functions.workspace import materialise, scratch_path

__all__ = ["BROADCAST_ROWS", "SPACE", "WORD", "join_small", "slices", "materialise", "scratch_path", "table", "text_or_empty"]

# The white space of the contracts, and words as what lies between.
SPACE = " \t\n\x0b\x0c\r"
WORD = "[^\\x20\\x09-\\x0D]+"

#: Most rows of (id, few numbers) that a join side may hold to be broadcast: about 32 MB.
BROADCAST_ROWS = 500_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_or_empty(name: str) -> Column:
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def join_small(big: DataFrame, small: DataFrame, on: list[str], how: str, *, rows: int | None = None) -> DataFrame:
    """Join with a written side: broadcast when its counted rows are within BROADCAST_ROWS, else shuffle both."""
    rows = small.count() if rows is None else rows
    return big.join(F.broadcast(small) if rows <= BROADCAST_ROWS else small.hint("merge"), on, how)


#: Rows that a Python worker holds as objects at once.
SLICE_ROWS = 512


def slices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Arrow batches cut into small ones, so that texts and results of few rows are in memory together."""
    for batch in batches:
        for at in range(0, batch.num_rows, SLICE_ROWS):
            yield batch.slice(at, SLICE_ROWS)
