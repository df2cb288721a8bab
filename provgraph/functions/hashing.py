"""Hashes of multisets that do not depend on the order of their items."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def item_hashes(*cols: Column) -> list[Column]:
    """Two independent 64-bit hashes of an item, as decimals: their sums can't overflow under ANSI rules."""
    return [F.xxhash64(F.lit(seed), *cols).cast("decimal(20,0)") for seed in (1, 2)]


def multiset(*cols: Column) -> list[Column]:
    """Aggregates (m_count, m_sum1, m_sum2) of a multiset of items; with distinct items first it is a set's."""
    a, b = item_hashes(*cols)
    return [F.count(F.lit(1)).alias("m_count"), F.sum(a).alias("m_sum1"), F.sum(b).alias("m_sum2")]


def colour(*cols: Column) -> list[Column]:
    """A 128-bit colour (c1, c2) of the values."""
    return [F.xxhash64(F.lit(seed), *cols).alias(name) for seed, name in ((3, "c1"), (4, "c2"))]
