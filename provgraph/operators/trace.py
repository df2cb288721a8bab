"""Traces from audit logs: typed edges with intervals, at a chosen granularity."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from provgraph.functions.paths import prov_label
from provgraph.schema import ACTIVITY, ENTITY, GENERATED, INFORMED, USED, ProvGraph, edges_of, nodes_of


def end_of(ts: Column, dur_us: Column) -> Column:
    """``ts`` plus microseconds, as timestamp_ntz."""
    return F.timestamp_add("MICROSECOND", F.coalesce(dur_us, F.lit(0)), ts)


def coarsen(access: DataFrame, level: str = "access", gap_us: int = 3_600_000_000) -> DataFrame:
    """ACCESS rows as intervals (run_id, actor, op, object, t_begin, t_end, n).

    'access': one per row; 'session': those of one actor, operation and object with less than ``gap_us`` between begins are one;
    'lifetime': one per actor, operation and object. Failed operations stay, as operations of their own kind.
    """
    a = access.select("run_id", "actor", "op", "object", F.col("ts").alias("t_begin"), end_of(F.col("ts"), F.col("dur_us")).alias("t_end"))
    keys = ["run_id", "actor", "op", "object"]
    if level == "access":
        return a.withColumn("n", F.lit(1).cast("long"))
    if level == "session":
        w = Window.partitionBy(*keys).orderBy("t_begin", "t_end")
        far = F.timestamp_diff("MICROSECOND", F.lag("t_begin").over(w), F.col("t_begin")) > gap_us
        a = a.withColumn("new", F.coalesce(far, F.lit(True)).cast("int")).withColumn("part", F.sum("new").over(w.rowsBetween(Window.unboundedPreceding, 0)))
        keys = [*keys, "part"]
    out = a.groupBy(*keys).agg(F.min("t_begin").alias("t_begin"), F.max("t_end").alias("t_end"), F.count(F.lit(1)).alias("n"))
    return out.select("run_id", "actor", "op", "object", "t_begin", "t_end", "n")


def from_intervals(intervals: DataFrame) -> ProvGraph:
    """A graph of intervals, one edge each. A daily process ``d:user:day`` is spawned by the root ``u:user``."""
    made = intervals.withColumn("label", prov_label(F.col("op"))).filter("label is not null")
    back = F.col("label").isin(GENERATED, INFORMED)
    edges = made.select("run_id", F.when(back, F.col("object")).otherwise(F.col("actor")).alias("src"), F.when(back, F.col("actor")).otherwise(F.col("object")).alias("dst"), "label", "t_begin", "t_end", "n")
    actors = intervals.filter("actor is not null").groupBy("run_id", "actor").agg(F.min("t_begin").alias("t_begin"), F.max("t_end").alias("t_end"))
    root = F.concat(F.lit("u:"), F.split("actor", ":")[1])
    daily = F.col("actor").startswith("d:")
    spawned = actors.filter(daily).select("run_id", F.col("actor").alias("src"), root.alias("dst"), F.lit(INFORMED).alias("label"), "t_begin", F.col("t_begin").alias("t_end"), F.lit(1).alias("n"))
    nodes = nodes_of(actors.select("run_id", F.col("actor").alias("node_id"), F.lit(ACTIVITY).alias("node_type"), F.lit("process").alias("kind"), "t_begin", "t_end"))
    nodes = nodes.unionByName(nodes_of(actors.filter(daily).groupBy("run_id", root.alias("node_id")).agg(F.min("t_begin").alias("t_begin"), F.max("t_end").alias("t_end")).withColumns({"node_type": F.lit(ACTIVITY), "kind": F.lit("root")})))
    objects = made.select("run_id", F.col("object").alias("node_id"), F.when(F.col("label") == INFORMED, ACTIVITY).otherwise(ENTITY).alias("node_type"), F.when(F.col("label") == INFORMED, "task").otherwise("file").alias("kind")).distinct()
    return ProvGraph(nodes.unionByName(nodes_of(objects)), edges_of(edges).unionByName(edges_of(spawned)))


def from_accesses(access: DataFrame, level: str = "lifetime") -> ProvGraph:
    """The trace of an audit log; operations outside the labels make no edge."""
    return from_intervals(coarsen(access, level))


def to_trace(edges: DataFrame) -> DataFrame:
    """Stored edges as audited ones: (run_id, start, end, label), information flowing from start to end."""
    label = F.when(F.col("label") == USED, "read").when(F.col("label") == GENERATED, "written").when(F.col("label") == INFORMED, "spawned")
    return edges.select("run_id", F.col("dst").alias("start"), F.col("src").alias("end"), label.alias("label"), "t_begin", "t_end")
