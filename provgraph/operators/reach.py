"""Reachability: closures by frontier, acyclicity by peeling, cyclic cores by forward and backward colours."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provgraph.plans.iterate import materialize
from provgraph.schema import GENERATED, INFORMED, USED, ProvGraph

FLOW = (USED, GENERATED, INFORMED)


def flow(g: ProvGraph, labels: tuple[str, ...] = FLOW) -> DataFrame:
    """(run_id, src, dst, label, t_begin, t_end) in the direction of information: dependee to dependent."""
    return g.edges.filter(F.col("label").isin(*labels)).select("run_id", F.col("dst").alias("src"), F.col("src").alias("dst"), "label", "t_begin", "t_end")


def closure(edges: DataFrame, seeds: DataFrame, max_hops: int | None = None, keys: tuple[str, ...] = ()) -> DataFrame:
    """(run_id, *keys, node_id, hops) of what ``edges`` (run_id, src, dst) reach from ``seeds`` (run_id, *keys, node_id), seeds at 0.

    A driver loop on the frontier alone; visited nodes leave it by an anti join, so cycles end. One number a round comes back.
    """
    cols = ["run_id", *keys, "node_id"]
    frontier = materialize(seeds.select(*cols).distinct().withColumn("hops", F.lit(0)), "frontier")
    visited, e = frontier, materialize(edges.select("run_id", "src", "dst").distinct(), "flow")
    hops = 0
    while max_hops is None or hops < max_hops:
        hops += 1
        step = frontier.select("run_id", *keys, F.col("node_id").alias("src")).join(e, ["run_id", "src"]).select("run_id", *keys, F.col("dst").alias("node_id")).distinct()
        frontier = materialize(step.join(visited, cols, "left_anti").withColumn("hops", F.lit(hops)), "frontier")
        if frontier.isEmpty():
            break
        visited = visited.unionByName(frontier)
    return visited


def _peel(edges: DataFrame, side: str) -> DataFrame:
    """Edges left when nodes without edges on ``side`` have been taken away again and again."""
    far = "dst" if side == "src" else "src"
    edges = materialize(edges, "peel")
    n = edges.count()
    while n:
        alive = edges.select("run_id", F.col(side).alias(far)).distinct()
        edges = materialize(edges.join(alive, ["run_id", far], "left_semi").select("run_id", "src", "dst"), "peel")
        m = edges.count()
        if m == n:
            break
        n = m
    return edges


def on_cycles(g: ProvGraph) -> DataFrame:
    """(run_id, src, dst): edges on or between cycles."""
    e = g.edges.select("run_id", "src", "dst").distinct()
    return _peel(_peel(e, "src"), "dst")


def acyclicity(g: ProvGraph) -> DataFrame:
    """(run_id, acyclic, residual_nodes) of each run."""
    rest = on_cycles(g)
    n = rest.select("run_id", F.explode(F.array("src", "dst")).alias("x")).groupBy("run_id").agg(F.count_distinct("x").alias("residual_nodes"))
    return g.nodes.select("run_id").distinct().join(n, "run_id", "left").select("run_id", F.col("residual_nodes").isNull().alias("acyclic"), F.coalesce("residual_nodes", F.lit(0)).alias("residual_nodes"))


def cyclic_cores(g: ProvGraph) -> DataFrame:
    """(run_id, node_id, core): strongly connected sets of two or more nodes; ``core`` is the least of them.

    The least identifier that reaches a node spreads forwards; the nodes of that colour that the least one is reached from are
    its core. Settled cores leave, and the rest starts again.
    """
    edges, out = on_cycles(g), None
    while not edges.isEmpty():
        nodes = edges.select("run_id", F.explode(F.array("src", "dst")).alias("node_id")).distinct()
        state = materialize(nodes.withColumn("colour", F.col("node_id")), "colour")
        while True:
            heard = edges.join(state.withColumnRenamed("node_id", "src"), ["run_id", "src"]).groupBy("run_id", F.col("dst").alias("node_id")).agg(F.min("colour").alias("c"))
            new = materialize(state.join(heard, ["run_id", "node_id"], "left").select("run_id", "node_id", F.least("colour", F.coalesce("c", "colour")).alias("colour"), (F.col("c") < F.col("colour")).alias("moved")), "colour")
            state = new.select("run_id", "node_id", "colour")
            if new.filter("moved").isEmpty():
                break
        s, d = state.withColumnRenamed("node_id", "src"), state.withColumnRenamed("node_id", "dst").withColumnRenamed("colour", "colour2")
        inside = edges.join(s, ["run_id", "src"]).join(d, ["run_id", "dst"]).filter("colour = colour2").select("run_id", F.col("dst").alias("src"), F.col("src").alias("dst"))
        core = closure(inside, state.filter("node_id = colour").select("run_id", "node_id")).select("run_id", "node_id").join(state, ["run_id", "node_id"]).select("run_id", "node_id", F.col("colour").alias("core"))
        core = materialize(core, "cores")
        out = core if out is None else out.unionByName(core)
        gone = core.select("run_id", "node_id")
        edges = materialize(edges.join(gone.withColumnRenamed("node_id", "src"), ["run_id", "src"], "left_anti").join(gone.withColumnRenamed("node_id", "dst"), ["run_id", "dst"], "left_anti").select("run_id", "src", "dst"), "flow")
        edges = _peel(_peel(edges, "src"), "dst")
    if out is None:
        return g.nodes.select("run_id", "node_id", F.col("node_id").alias("core")).limit(0)
    size = out.groupBy("run_id", "core").agg(F.count(F.lit(1)).alias("k")).filter("k > 1").select("run_id", "core")
    return out.join(size, ["run_id", "core"], "left_semi").select("run_id", "node_id", "core")
