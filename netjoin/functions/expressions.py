"""Column expressions that the builders and joins share; each has the same value in DuckDB."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Prime modulus of the operand buckets.
BUCKETS = 10007


def bucket(id_column: Column) -> Column:
    """h(id) = ((id + 17) mod p)^3 mod p, reduced after every product; a bijection of residues that no grid neighbour shares."""
    x = F.pmod(id_column + 17, F.lit(BUCKETS))
    return F.pmod(F.pmod(x * x, F.lit(BUCKETS)) * x, F.lit(BUCKETS))


def whole_minutes(earlier: Column, later: Column) -> Column:
    """Whole minutes between two timestamps, rounded down."""
    return F.floor((F.unix_micros(later.cast("timestamp")) - F.unix_micros(earlier.cast("timestamp"))) / F.lit(60_000_000)).cast("long")


def smoothed(w: Column, own: Column, other: Column, alpha: float) -> Column:
    """An edge weight scaled by the relative population of its cluster: alpha 0 leaves it, alpha 1 multiplies by the own share."""
    return w * own / (own + alpha * other)


def cents(price: Column) -> Column:
    return F.round(price * 100).cast("long")
