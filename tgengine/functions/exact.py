"""Exact integer building blocks shared with SQL oracles."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

PRIME = 1_000_003
#: Node ids are below this number, so that an edge id fits a BIGINT.
MAX_NODES = 1 << 31


def arithmetic_hash(a, b, c=0, seed=42) -> Column:
    """A value in [0, PRIME) from three integers; the same in any SQL engine."""
    lit = lambda x: (x if isinstance(x, Column) else F.lit(x)).cast("long")
    return F.pmod(lit(a) * 7919 + lit(b) * 104_729 + lit(c) * 1_299_709 + F.lit(seed), F.lit(PRIME))


def cents(col: str) -> Column:
    return F.round(F.col(col) * 100).cast("long")


def month(col: str) -> Column:
    return (F.year(col) - 1995) * 12 + F.month(col) - 1


def edge_id(src: str = "src", dst: str = "dst") -> Column:
    return F.col(src).cast("long") * MAX_NODES + F.col(dst).cast("long")


def sigmoid(x: Column) -> Column:
    return 1 / (1 + F.exp(-x))
