"""Choice of physical strategy from statistics, never from all rows at the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provgraph.schema import ProvGraph


def choose(g: ProvGraph, local_edge_limit: int = 1_000_000) -> str:
    """'run-parallel' if every run's edges fit a task, else 'giant-graph'. One aggregation, one number back."""
    most = g.edges.groupBy("run_id").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0]
    return "run-parallel" if (most or 0) <= local_edge_limit else "giant-graph"


def broadcast_if_small(df: DataFrame, most: int = 1_000_000) -> DataFrame:
    """``df`` with a broadcast hint if it has at most ``most`` rows, checked; else as it is, for a sorted or hashed join."""
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df


def salted_counts(df: DataFrame, keys: list[str], salts: int = 32) -> DataFrame:
    """Counts by keys in two stages, so that one hot key is added up by many tasks first."""
    first = df.withColumn("_salt", F.pmod(F.xxhash64(*df.columns), F.lit(salts))).groupBy(*keys, "_salt").agg(F.count(F.lit(1)).alias("n"))
    return first.groupBy(*keys).agg(F.sum("n").alias("n"))
