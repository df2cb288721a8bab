"""Partial and modified repeats: what to take along, what must run again, what is reused."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provgraph.functions.paths import short_path
from provgraph.operators import isomorph, reach, temporal
from provgraph.operators import content as store
from provgraph.plans.choose import broadcast_if_small
from provgraph.plans.iterate import materialize
from provgraph.schema import ACTIVITY, GENERATED, INFORMED, USED, ProvGraph, edges_of


def select(g: ProvGraph, pids: list[int] | None = None, paths: list[str] | None = None, ids: list[str] | None = None) -> DataFrame:
    """(run_id, node_id) of the activities with one of the pids, short paths or identifiers."""
    cond = F.lit(False)
    if pids:
        cond = cond | F.col("pid").isin(pids)
    if paths:
        cond = cond | F.col("label").isin(paths) | short_path(F.col("label")).isin(paths)
    if ids:
        cond = cond | F.col("node_id").isin(ids)
    return g.nodes.filter((F.col("node_type") == ACTIVITY) & cond).select("run_id", "node_id")


def spawn(g: ProvGraph) -> DataFrame:
    """(run_id, src = parent, dst = child)."""
    return g.edges.filter(F.col("label") == INFORMED).select("run_id", F.col("dst").alias("src"), F.col("src").alias("dst"))


def required(g: ProvGraph, sel: DataFrame, closure: str = "direct") -> DataFrame:
    """(run_id, node_id) of the processes that a partial repeat runs.

    'direct': the selected and the ones they spawn; 'descendants': all below; 'lineage': these and all that they depend on.
    """
    sel = sel.select("run_id", "node_id").distinct()
    if closure == "lineage":
        down = reach.closure(spawn(g), sel).select("run_id", "node_id")
        up = reach.closure(g.edges.select("run_id", "src", "dst"), down).select("run_id", "node_id")
        return up.join(g.nodes.filter(F.col("node_type") == ACTIVITY).select("run_id", "node_id"), ["run_id", "node_id"], "left_semi")
    return reach.closure(spawn(g), sel, 1 if closure == "direct" else None).select("run_id", "node_id")


def touched(g: ProvGraph, procs: DataFrame) -> DataFrame:
    """(run_id, node_id) of the files that these processes used or generated."""
    f = g.edges.filter(F.col("label").isin(USED, GENERATED))
    file = F.when(F.col("label") == USED, F.col("dst")).otherwise(F.col("src"))
    proc = F.when(F.col("label") == USED, F.col("src")).otherwise(F.col("dst"))
    pairs = f.select("run_id", file.alias("file"), proc.alias("node_id"))
    own = broadcast_if_small(procs.select("run_id", "node_id"))  # a few selected processes leave all edges where they are
    return pairs.join(own, ["run_id", "node_id"], "left_semi").select("run_id", F.col("file").alias("node_id")).distinct()


def sub_container(g: ProvGraph, sel: DataFrame, closure: str = "direct") -> ProvGraph:
    """The processes of ``required``, the files they touch, and the edges between these."""
    procs = required(g, sel, closure)
    keep = broadcast_if_small(materialize(procs.union(touched(g, procs)).distinct(), "kept"))
    e = g.edges
    for side in ("src", "dst"):
        e = e.join(keep.withColumnRenamed("node_id", side), ["run_id", side], "left_semi")
    return ProvGraph(g.nodes.join(keep, ["run_id", "node_id"], "left_semi"), edges_of(e))


def intermediates(sub: ProvGraph, g: ProvGraph) -> DataFrame:
    """(run_id, node_id): files read inside that only processes outside generate; kept from the earlier run."""
    read = sub.edges.filter(F.col("label") == USED).select("run_id", F.col("dst").alias("node_id")).distinct()
    made = g.edges.filter(F.col("label") == GENERATED).select("run_id", F.col("src").alias("node_id")).distinct()
    inside = sub.edges.filter(F.col("label") == GENERATED).select("run_id", F.col("src").alias("node_id")).distinct()
    return read.join(made, ["run_id", "node_id"], "left_semi").join(inside, ["run_id", "node_id"], "left_anti")


def unused(shipped: DataFrame, rep: ProvGraph) -> DataFrame:
    """(run_id, node_id) of shipped files that no process of the repeat touched."""
    acts = rep.nodes.filter(F.col("node_type") == ACTIVITY).select("run_id", "node_id")
    return shipped.select("run_id", "node_id").join(touched(rep, acts), ["run_id", "node_id"], "left_anti")


def executable(sub: ProvGraph, g: ProvGraph) -> DataFrame:
    """(run_id, executable): every file that a process of ``sub`` used in ``g`` is there."""
    acts = sub.nodes.filter(F.col("node_type") == ACTIVITY).select("run_id", F.col("node_id").alias("src"))
    want = g.edges.filter(F.col("label") == USED).join(acts, ["run_id", "src"], "left_semi").select("run_id", F.col("dst").alias("node_id")).distinct()
    gone = want.join(sub.nodes.select("run_id", "node_id"), ["run_id", "node_id"], "left_anti").groupBy("run_id").agg(F.count(F.lit(1)).alias("missing"))
    return sub.nodes.select("run_id").distinct().join(gone, "run_id", "left").select("run_id", F.col("missing").isNull().alias("executable"))


def modified_many(g: ProvGraph, changes: DataFrame, closure: str = "dataflow", as_of: str | None = None) -> DataFrame:
    """(run_id, change_id, node_id, node_type): what must run or be made again, for many changes (run_id, change_id, node_id) at once.

    'direct': the processes that use a changed file and those that they spawn. 'dataflow': everything downstream over use,
    generation and spawning. 'temporal': that part of it which information can reach in time. Changed files themselves
    are not listed.
    """
    changes = changes.select("run_id", "change_id", "node_id").distinct()
    types = g.nodes.select("run_id", "node_id", "node_type")
    if closure == "direct":
        users = g.edges.filter(F.col("label") == USED).select("run_id", F.col("dst").alias("node_id"), F.col("src").alias("p")).join(changes, ["run_id", "node_id"]).select("run_id", "change_id", F.col("p").alias("node_id")).distinct()
        hit = reach.closure(spawn(g), users, 1, ("change_id",)).select("run_id", "change_id", "node_id")
    elif closure == "dataflow":
        hit = reach.closure(reach.flow(g), changes, None, ("change_id",)).filter("hops > 0").select("run_id", "change_id", "node_id")
    else:
        seeds = changes.select("run_id", "node_id").distinct()
        arr = temporal.depends(g, seeds, as_of)
        hit = arr.join(changes.withColumnRenamed("node_id", "source"), ["run_id", "source"]).select("run_id", "change_id", "node_id").distinct()
    return hit.join(changes, ["run_id", "change_id", "node_id"], "left_anti").join(types, ["run_id", "node_id"]).select("run_id", "change_id", "node_id", "node_type")


def modified(g: ProvGraph, changed: DataFrame, closure: str = "dataflow", as_of: str | None = None) -> DataFrame:
    """(run_id, node_id, node_type, action): 'changed', 'rerun' (processes), 'regenerate' (files) or 'reuse', for every node."""
    hit = modified_many(g, changed.select("run_id", F.lit(0).alias("change_id"), "node_id"), closure, as_of).select("run_id", "node_id", F.lit(True).alias("hit"))
    ch = changed.select("run_id", "node_id").distinct().withColumn("ch", F.lit(True))
    n = g.nodes.select("run_id", "node_id", "node_type").join(hit, ["run_id", "node_id"], "left").join(ch, ["run_id", "node_id"], "left")
    if closure == "direct":  # files that a process to run generates are made again
        made = g.edges.filter(F.col("label") == GENERATED).select("run_id", F.col("src").alias("node_id"), F.col("dst").alias("p")).join(hit.select("run_id", F.col("node_id").alias("p")), ["run_id", "p"], "left_semi")
        n = n.join(made.select("run_id", "node_id", F.lit(True).alias("made")).distinct(), ["run_id", "node_id"], "left").withColumn("hit", F.coalesce("hit", "made"))
    action = F.when(F.col("ch"), "changed").when(F.col("hit") & (F.col("node_type") == ACTIVITY), "rerun").when(F.col("hit"), "regenerate").otherwise("reuse")
    return n.select("run_id", "node_id", "node_type", action.alias("action"))


def check_expected(out: DataFrame, expected: DataFrame) -> DataFrame:
    """(key, status): 'pass', 'fail', 'missing' or 'unexpected' of outputs (key, value) against the expected ones."""
    j = out.select("key", F.col("value").alias("got"), F.lit(1).alias("o")).join(expected.select("key", F.col("value").alias("want"), F.lit(1).alias("e")), "key", "full")
    status = F.when(F.col("o").isNull(), "missing").when(F.col("e").isNull(), "unexpected").when(F.col("got").eqNullSafe(F.col("want")), "pass").otherwise("fail")
    return j.select("key", status.alias("status"))


def exact_report(ref: ProvGraph, rep: ProvGraph, ref_files: DataFrame, rep_files: DataFrame, mode: str = "exact") -> DataFrame:
    """(run_id, graph, outputs, repeated): the graph's verdict, whether output contents agree irrespective of names, and both."""
    v = isomorph.verify(ref, rep, mode).select(F.col("run_a").alias("run_id"), F.col("verdict").alias("graph"))
    c = store.validate(ref_files, rep_files).groupBy("run_id").agg(F.bool_and(F.col("status") == "matched").alias("outputs"))
    return v.join(c, "run_id", "left").select("run_id", "graph", F.coalesce("outputs", F.lit(True)).alias("outputs"), ((F.col("graph") == "matched") & F.coalesce("outputs", F.lit(True))).alias("repeated"))
