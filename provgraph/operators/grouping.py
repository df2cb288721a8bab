"""Grouping summaries: by attributes, relationship, ancestry and ancestry-degree, and their summary graphs.

All are colour refinements with other signatures. Every round splits all groups against all groups at once, which reaches
the same coarsest stable partition as splitting against one group at a time. Far ends' colours travel to the edges;
a first aggregation by (node, side, label, colour) takes the weight off hubs before rows meet by node.
"""

from __future__ import annotations

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from provgraph.functions.hashing import colour, multiset
from provgraph.operators import runwise
from provgraph.plans.choose import broadcast_if_small, choose
from provgraph.plans.iterate import Rounds, drop, fixpoint, materialize
from provgraph.schema import ProvGraph


def by_attributes(g: ProvGraph, attrs: tuple[str, ...] = ("node_type",)) -> DataFrame:
    """(run_id, node_id, group_id): equal attributes, group_id the least node."""
    least = g.nodes.groupBy("run_id", *attrs).agg(F.min("node_id").alias("group_id"))
    a, b = g.nodes.alias("a"), least.alias("b")
    same = F.col("a.run_id") == F.col("b.run_id")
    for x in attrs:
        same = same & F.col(f"a.{x}").eqNullSafe(F.col(f"b.{x}"))
    return a.join(b, same).select("a.run_id", "a.node_id", "b.group_id")


def views(g: ProvGraph, sides: tuple[str, ...]) -> DataFrame:
    """(run_id, node_id, side, label, far): each edge as its ends see it. 'out' looks at dependees, 'in' at dependents."""
    e, parts = g.edges, []
    if "out" in sides:
        parts.append(e.select("run_id", F.col("src").alias("node_id"), F.lit("out").alias("side"), "label", F.col("dst").alias("far")))
    if "in" in sides:
        parts.append(e.select("run_id", F.col("dst").alias("node_id"), F.lit("in").alias("side"), "label", F.col("src").alias("far")))
    return parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])


def start(g: ProvGraph, attrs: tuple[str, ...] = ("node_type",)) -> DataFrame:
    return g.nodes.select("run_id", "node_id", *colour(*(F.coalesce(F.col(a).cast("string"), F.lit("")) for a in attrs)))


def refine(g: ProvGraph, init: DataFrame, sides: tuple[str, ...], counted: bool, max_rounds: int | None = None, rounds: Rounds | None = None) -> DataFrame:
    """(run_id, node_id, c1, c2) at the fixpoint or after ``max_rounds``.

    ``counted``: a signature counts the edges to each colour; else it is the set of colours. A node without edges has
    the empty signature, which is that of the start. The old colour is part of the new one, so an unchanged number of
    colours means stability.

    Where every run fits a task, all its rounds are made there. Else each round is a plan of its own, in which names meet as numbers.
    """
    if rounds is None and choose(g, runwise.RUN_EDGES) == "run-parallel":
        return materialize(runwise.refine(g, init, sides, counted, max_rounds), "colours")
    seed = _seed(init)
    name = lambda c: _number(seed, c)
    way = F.xxhash64("side", "label")
    # numbers kept by far end, so that a round moves colours alone; what an executor loses of it is read again
    seen = views(g, sides).select(name("far").alias("far"), name("node_id").alias("x"), way.alias("way")).filter("far is not null and x is not null")
    seen = materialize(seen, "views").repartition("far").persist(StorageLevel.MEMORY_AND_DISK)

    def step(state: DataFrame, _: int) -> DataFrame:
        far = state.select(F.col("x").alias("far"), F.col("c1").alias("f1"), F.col("c2").alias("f2"))
        items = seen.join(far, "far").select("x", "way", "f1", "f2")
        sig = (items if counted else items.distinct()).groupBy("x").agg(*multiset(F.col("way"), F.col("f1"), F.col("f2")))
        both = state.join(sig, "x", "left")
        parts = [F.col("c1"), F.col("c2"), F.coalesce("m_count", F.lit(0)), *(F.coalesce(c, F.lit(0)).cast("decimal(38,0)") for c in ("m_sum1", "m_sum2"))]
        return both.select("run_id", "node_id", "x", *colour(*parts))

    def colours(state: DataFrame) -> int:
        return state.select("run_id", "c1", "c2").distinct().count()

    try:
        state = init.select("run_id", "node_id", name("node_id").alias("x"), "c1", "c2")
        return fixpoint(state, step, colours, lambda a, b: a == b, max_rounds, "colours", rounds).drop("x")
    finally:
        seen.unpersist()


def _number(seed: int, c: str) -> Column:
    """A name in its run as a number; a null name meets none."""
    return F.when(F.col("run_id").isNotNull() & F.col(c).isNotNull(), F.xxhash64(F.lit(seed), "run_id", c))


def _seed(nodes: DataFrame) -> int:
    """A seed with which no two names of ``nodes`` get one number."""
    seed, other = 5, F.xxhash64(F.lit(4), "run_id", "node_id")
    while True:
        twice = nodes.select(_number(seed, "node_id").alias("x"), other.alias("y")).filter("x is not null").groupBy("x").agg((F.min("y") < F.max("y")).alias("two"))
        if twice.filter("two").isEmpty():
            return seed
        seed += 1


def canonical(state: DataFrame) -> DataFrame:
    """(run_id, node_id, group_id) with the least node as a group's name."""
    least = state.groupBy("run_id", "c1", "c2").agg(F.min("node_id").alias("group_id"))
    return state.join(least, ["run_id", "c1", "c2"]).select("run_id", "node_id", "group_id")


def _ancestor_side(ancestors: str) -> tuple[str, ...]:
    return ("out",) if ancestors == "dependee" else ("in",)


def ancestry(g: ProvGraph, ancestors: str = "dependee", attrs: tuple[str, ...] = ("node_type",), max_rounds: int | None = None, rounds: Rounds | None = None) -> DataFrame:
    """Equal sets of (label, ancestor group); nodes without ancestors share the start."""
    return canonical(refine(g, start(g, attrs), _ancestor_side(ancestors), False, max_rounds, rounds))


def ancestry_degree(g: ProvGraph, scope: str = "group", ancestors: str = "dependee", attrs: tuple[str, ...] = ("node_type",), max_rounds: int | None = None, rounds: Rounds | None = None) -> DataFrame:
    """Ancestry, with equal degrees: towards each group and label ('group', the default), or per label alone ('label')."""
    if scope == "group":
        return canonical(refine(g, start(g, attrs), ("out", "in"), True, max_rounds, rounds))
    total = views(g, ("out", "in")).groupBy("run_id", "node_id", "side", "label").agg(F.count(F.lit(1)).alias("n"))
    sig = total.groupBy("run_id", "node_id").agg(*multiset(F.col("side"), F.col("label"), F.col("n")))
    parts = [F.col("c1"), F.col("c2"), F.coalesce("m_count", F.lit(0)), *(F.coalesce(c, F.lit(0)).cast("decimal(38,0)") for c in ("m_sum1", "m_sum2"))]
    init = start(g, attrs).join(sig, ["run_id", "node_id"], "left").select("run_id", "node_id", *colour(*parts))
    return canonical(refine(g, init, _ancestor_side(ancestors), False, max_rounds, rounds))


def ancestry_degree_across(g: ProvGraph, rounds: int = 6) -> DataFrame:
    """(node_id, group_id): the groups of ``ancestry_degree`` of all runs taken as one graph; no two runs share a node.

    Where every run fits a task, rounds are made run by run. All runs make the same number, twice as many until a round leaves the
    number of colours of all runs as it was.
    """
    if choose(g) != "run-parallel":
        return ancestry_degree(ProvGraph(*(x.withColumn("run_id", F.lit(0).cast("long")) for x in (g.nodes, g.edges)))).select("node_id", "group_id")
    while True:
        made = materialize(runwise.together(g, rounds), "colours")
        n = {r["round"]: r["n"] for r in made.filter("round is not null").groupBy("round").agg(F.count_distinct("c1", "c2").alias("n")).collect()}
        if n.get(rounds) == n.get(rounds - 1):
            break
        drop(made)
        rounds *= 2
    least = made.filter(F.col("round") == rounds).groupBy("c1", "c2").agg(F.min("node_id").alias("group_id"))
    return made.filter("round is null").join(broadcast_if_small(least), ["c1", "c2"]).select("node_id", "group_id")


def relationship(g: ProvGraph, attrs: tuple[str, ...] = ("node_type",), max_rounds: int | None = None, rounds: Rounds | None = None) -> DataFrame:
    """The baseline: equal sets of (direction, label, neighbour group), both directions."""
    return canonical(refine(g, start(g, attrs), ("out", "in"), False, max_rounds, rounds))


def check(g: ProvGraph, groups: DataFrame) -> DataFrame:
    """(problem, n) of a grouping: nodes in no group, in several, or groups of mixed type; no rows if it is valid."""
    j = g.nodes.select("run_id", "node_id", "node_type").join(groups, ["run_id", "node_id"], "left")
    missing = j.filter("group_id is null").select(F.lit("uncovered").alias("problem"))
    several = groups.groupBy("run_id", "node_id").agg(F.count_distinct("group_id").alias("k")).filter("k > 1").select(F.lit("overlap").alias("problem"))
    mixed = j.filter("group_id is not null").groupBy("run_id", "group_id").agg(F.count_distinct("node_type").alias("k")).filter("k > 1").select(F.lit("mixed").alias("problem"))
    return missing.union(several).union(mixed).groupBy("problem").agg(F.count(F.lit(1)).alias("n"))


def summary_graph(g: ProvGraph, groups: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Nodes (run_id, group_id, node_type, size) and edges (run_id, src, dst, label, n) between groups."""
    nodes = groups.join(g.nodes.select("run_id", "node_id", "node_type"), ["run_id", "node_id"]).groupBy("run_id", "group_id", "node_type").agg(F.count(F.lit(1)).alias("size"))
    e = g.edges.select("run_id", "src", "dst", "label")
    for side in ("src", "dst"):
        e = e.join(groups.select("run_id", F.col("node_id").alias(side), F.col("group_id").alias(f"g_{side}")), ["run_id", side])
    return nodes, e.groupBy("run_id", F.col("g_src").alias("src"), F.col("g_dst").alias("dst"), "label").agg(F.count(F.lit(1)).alias("n"))
