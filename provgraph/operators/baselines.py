"""What the methods are compared with."""

from __future__ import annotations

from collections import Counter, defaultdict
from decimal import Decimal
from itertools import permutations, product
from math import factorial, inf, prod

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provgraph.operators import graph, grouping, isomorph, temporal
from provgraph.schema import ACTIVITY, ProvGraph

relationship_grouping = grouping.relationship
connectivity = temporal.connected


def replete(g: ProvGraph) -> DataFrame:
    """The unsummarised graph's sizes."""
    return graph.stats(g)


def full_rerun(g: ProvGraph) -> DataFrame:
    """(run_id, node_id, action): every process runs again."""
    return g.nodes.filter(F.col("node_type") == ACTIVITY).select("run_id", "node_id", F.lit("rerun").alias("action"))


def drawn_workflow(g: ProvGraph) -> DataFrame:
    """(run_id, src, dst, label): the graph of kinds, as a user would draw the workflow."""
    k = g.nodes.select("run_id", "node_id", "kind")
    e = g.edges.select("run_id", "src", "dst", "label")
    for side in ("src", "dst"):
        e = e.join(k.select("run_id", F.col("node_id").alias(side), F.col("kind").alias(f"k_{side}")), ["run_id", side])
    return e.select("run_id", F.col("k_src").alias("src"), F.col("k_dst").alias("dst"), "label").distinct()


def _per_run(g: ProvGraph, fn, schema: str) -> DataFrame:
    """``fn(run, {node: type}, [(src, dst, label)])`` of each run, which must be small."""
    n = g.nodes.select("run_id", F.lit("n").alias("what"), F.col("node_id").alias("x"), F.col("node_type").alias("y"), F.lit("").alias("label"))
    e = g.edges.select("run_id", F.lit("e").alias("what"), F.col("src").alias("x"), F.col("dst").alias("y"), "label")

    def run(t: pa.Table) -> pa.Table:
        rows = list(zip(*(t.column(c).to_pylist() for c in ("what", "x", "y", "label")), strict=True))
        return fn(t.column("run_id")[0].as_py(), {x: y for w, x, y, _ in rows if w == "n"}, [(x, y, lab) for w, x, y, lab in rows if w == "e"])

    return n.unionByName(e).groupBy("run_id").applyInArrow(run, schema)


def _automorphisms(types: dict[str, str], edges: list[tuple[str, str, str]]) -> int:
    """The number of type- and label-preserving bijections of a run onto itself, without trying each.

    Twins (nodes of one type with the same edges) may be permuted at will and leave one node that bears their number. Of the rest, nodes are
    fixed one after another; the images that a node can take while those before it stay in place are found by search, and their numbers
    multiply to the whole.
    """
    near = {v: Counter() for v in types}
    for x, y, lab in edges:
        near[x]["out", lab, y] += 1
        near[y]["in", lab, x] += 1
    twins = defaultdict(list)
    for v in sorted(types):
        twins[types[v], frozenset(near[v].items())].append(v)
    start = {vs[0]: f"{types[vs[0]]} {len(vs)}" for vs in twins.values()}
    links = [("e", s, x, y, lab) for s in "ab" for x, y, lab in edges if x in start and y in start]
    near = {v: [(k, lab, w, m) for (k, lab, w), m in near[v].items() if w in start] for v in start}

    def refined(c: dict[str, str]) -> dict[str, str]:
        while True:
            seen = {v: (c[v], tuple(sorted((k, lab, c[w], m) for k, lab, w, m in near[v]))) for v in c}
            name = {x: str(i) for i, x in enumerate(sorted(set(seen.values())))}
            new = {v: name[x] for v, x in seen.items()}
            if len(name) == len(set(c.values())):
                return new
            c = new

    n, c = prod(factorial(len(vs)) for vs in twins.values()), refined(start)
    for v in start:
        images = 1
        for w in start:
            if w != v and c[w] == c[v]:
                sides = ("a", c | {v: "chosen"}), ("b", c | {w: "chosen"})
                images += isomorph._search([("n", s, x, k, "") for s, ks in sides for x, k in ks.items()] + links, inf)[0] is not None
        n *= images
        c = refined(c | {v: "chosen"}) if list(c.values()).count(c[v]) > 1 else c
    return n


def all_automorphisms(g: ProvGraph, max_nodes: int = 10) -> DataFrame:
    """(run_id, automorphisms) by trying every type-preserving bijection; runs of more than ``max_nodes`` nodes are counted by refined colours.

    Either count is exact; one of more than 38 digits fails.
    """

    def count(run: int, types: dict[str, str], edges: list[tuple[str, str, str]]) -> pa.Table:
        if len(types) <= max_nodes:
            have, by = sorted(edges), defaultdict(list)
            for v in sorted(types):
                by[types[v]].append(v)
            n = 0
            for choice in product(*(permutations(vs) for vs in by.values())):
                m = {v: w for vs, ws in zip(by.values(), choice, strict=True) for v, w in zip(vs, ws, strict=True)}
                n += sorted((m[x], m[y], lab) for x, y, lab in edges) == have
        else:
            n = _automorphisms(types, edges)
        return pa.table({"run_id": pa.array([run], pa.int64()), "automorphisms": pa.array([Decimal(n)], pa.decimal128(38, 0))})

    return _per_run(g, count, "run_id long, automorphisms decimal(38,0)")


def splitter_queue(g: ProvGraph) -> DataFrame:
    """(run_id, node_id, group_id) of the ancestry-degree grouping, by one splitter at a time; for small runs."""

    def split(run: int, types: dict[str, str], edges: list[tuple[str, str, str]]) -> pa.Table:
        towards = defaultdict(list)
        for x, y, lab in edges:
            towards[y].append((x, "out", lab))
            towards[x].append((y, "in", lab))
        groups: list[set[str]] = []
        for t in sorted(set(types.values())):
            groups.append({v for v in types if types[v] == t})
        queue = list(groups)
        while queue:
            by = queue.pop()
            degree: dict[str, dict[tuple[str, str], int]] = defaultdict(lambda: defaultdict(int))
            for v in by:
                for w, side, lab in towards[v]:
                    degree[w][side, lab] += 1
            after = []
            for part in groups:
                own = defaultdict(set)
                for v in part:
                    own[tuple(sorted(degree[v].items()))].add(v)
                after += own.values()
                if len(own) > 1:
                    queue = [q for q in queue if q != part] + list(own.values())
            groups = after
        rows = sorted((v, min(p)) for p in groups for v in p)
        return pa.table({"run_id": pa.array([run] * len(rows), pa.int64()), "node_id": pa.array([v for v, _ in rows]), "group_id": pa.array([p for _, p in rows])})

    return _per_run(g, split, "run_id long, node_id string, group_id string")
