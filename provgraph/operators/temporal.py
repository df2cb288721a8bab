"""Dependencies that respect time. Information crosses an edge inside its interval, at times that never decrease along a path."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from provgraph.functions.paths import crosses
from provgraph.operators import reach
from provgraph.plans.iterate import materialize
from provgraph.schema import ENTITY, GENERATED, USED, ProvGraph

_FIRST, _LAST = "0001-01-01 00:00:00", "9999-12-31 23:59:59.999999"


def _at(text: str) -> Column:
    return F.lit(text).cast("timestamp_ntz")


def connected(g: ProvGraph, sources: DataFrame, max_hops: int | None = None) -> DataFrame:
    """The baseline without time: (run_id, source, node_id, hops)."""
    seeds = sources.select("run_id", F.col("node_id").alias("source"), "node_id")
    return reach.closure(reach.flow(g), seeds, max_hops, ("source",))


def _tick(c: Column) -> Column:
    return F.timestamp_add("MICROSECOND", F.lit(1), c)


def _spread(edges: DataFrame, seeds: DataFrame, forward: bool, as_of: str | None, strict: bool, max_hops: int | None) -> DataFrame:
    """Best times by rounds over the nodes whose time got better. Forward: earliest arrivals; backward: latest departures."""
    begin, end = F.coalesce("t_begin", _at(_FIRST)), F.coalesce("t_end", _at(_LAST))
    e = edges.select("run_id", "src", "dst", begin.alias("b"), end.alias("e"))
    if as_of is not None:
        e = e.filter(F.col("b") <= _at(as_of)).withColumn("e", F.least("e", _at(as_of)))
    e = materialize(e if forward else e.select("run_id", F.col("dst").alias("src"), F.col("src").alias("dst"), "b", "e"), "flow")
    start = _at(_FIRST if forward else (as_of or _LAST))
    visited = materialize(seeds.select("run_id", "seed", F.col("seed").alias("node_id"), start.alias("t"), F.lit(True).alias("fresh"), F.lit(0).alias("hops")), "arrivals")
    hops, keys = 0, ["run_id", "seed", "node_id"]
    best = F.min if forward else F.max
    while max_hops is None or hops < max_hops:
        hops += 1
        f = visited.filter("fresh").select("run_id", "seed", F.col("node_id").alias("src"), "t", F.col("hops").alias("h"))
        j = f.join(e, ["run_id", "src"])
        if forward:
            t = F.when((F.col("h") > 0) & F.lit(strict), _tick(F.col("t"))).otherwise(F.col("t"))
            j = j.withColumn("t", F.greatest(t, "b")).filter("t <= e")
        else:
            t = F.when((F.col("h") > 0) & F.lit(strict), F.timestamp_add("MICROSECOND", F.lit(-1), F.col("t"))).otherwise(F.col("t"))
            j = j.withColumn("t", F.least(t, "e")).filter("t >= b")
        new = j.groupBy("run_id", "seed", F.col("dst").alias("node_id")).agg(best("t").alias("t2"))
        better = F.col("t").isNull() | (F.col("t2") < F.col("t") if forward else F.col("t2") > F.col("t"))
        both = visited.join(new, keys, "full").select(*keys, F.when(F.col("t2").isNotNull() & better, F.col("t2")).otherwise(F.col("t")).alias("t"), (F.col("t2").isNotNull() & better).alias("fresh"), F.when(F.col("t").isNull(), hops).otherwise(F.greatest("hops", F.when(better & F.col("t2").isNotNull(), hops).otherwise(0))).alias("hops"))
        visited = materialize(both, "arrivals")
        if visited.filter("fresh").isEmpty():
            break
    return visited


def depends(g: ProvGraph, sources: DataFrame, as_of: str | None = None, strict: bool = False, max_hops: int | None = None) -> DataFrame:
    """(run_id, source, node_id, arrival): what depends on each source by ``as_of``, and since when.

    Leaving earlier never hurts, so the earliest arrival at each node is enough; sources themselves are left out. ``strict``: times
    along a path increase. Null interval ends are open.
    """
    v = _spread(reach.flow(g), sources.select("run_id", F.col("node_id").alias("seed")).distinct(), True, as_of, strict, max_hops)
    return v.filter("node_id <> seed").select("run_id", F.col("seed").alias("source"), "node_id", F.col("t").alias("arrival"))


def lineage(g: ProvGraph, targets: DataFrame, as_of: str | None = None, strict: bool = False, max_hops: int | None = None) -> DataFrame:
    """(run_id, target, node_id, departure): what each target may depend on, and until when it may leave."""
    v = _spread(reach.flow(g), targets.select("run_id", F.col("node_id").alias("seed")).distinct(), False, as_of, strict, max_hops)
    return v.filter("node_id <> seed").select("run_id", F.col("seed").alias("target"), "node_id", F.col("t").alias("departure"))


def one_hop(g: ProvGraph, strict: bool = False) -> DataFrame:
    """(run_id, process, in_file, out_file, feasible): pairs of a file read and another written by one process."""
    r = g.edges.filter(F.col("label") == USED).select("run_id", F.col("src").alias("process"), F.col("dst").alias("in_file"), F.col("t_begin").alias("rb"))
    w = g.edges.filter(F.col("label") == GENERATED).select("run_id", F.col("dst").alias("process"), F.col("src").alias("out_file"), F.col("t_end").alias("we"))
    pairs = r.join(w, ["run_id", "process"]).filter("in_file <> out_file")
    return pairs.groupBy("run_id", "process", "in_file", "out_file").agg(F.bool_or(crosses(F.col("rb"), F.col("we"), strict)).alias("feasible"))


def dependency_graph(g: ProvGraph, max_hops: int, as_of: str | None = None) -> DataFrame:
    """(run_id, source, node_id, arrival) among entities, from every entity, over at most ``max_hops`` edges."""
    ents = g.nodes.filter(F.col("node_type") == ENTITY).select("run_id", "node_id")
    return depends(g, ents, as_of, max_hops=max_hops).join(ents, ["run_id", "node_id"], "left_semi").select("run_id", "source", "node_id", "arrival")


def pruning(g: ProvGraph) -> DataFrame:
    """(run_id, pairs, feasible, infeasible_share): how many one-hop dependencies time rules out."""
    p = one_hop(g).groupBy("run_id").agg(F.count(F.lit(1)).alias("pairs"), F.count_if("feasible").alias("feasible"))
    return p.withColumn("infeasible_share", F.round(1 - F.col("feasible") / F.col("pairs"), 6))
