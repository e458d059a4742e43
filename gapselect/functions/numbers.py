"""Small numeric expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def clogc(c: Column, log_base: str = "2") -> Column:
    """c log c, 0 at 0."""
    log = F.log2(c) if log_base == "2" else F.log(c)
    return F.when(c > 0, c * log).otherwise(F.lit(0.0))


def r6(x: Column) -> Column:
    """Six decimals, no negative zero."""
    return F.round(x, 6) + F.lit(0.0)
