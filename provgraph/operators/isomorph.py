"""Exact repeat: are two runs the same graph up to names?

Many pairs go through one job. Sizes are screened first, then histograms of node hashes. In 'one_hop' mode that is the verdict. In
'exact' mode colours are refined to a fixpoint over both runs of a pair at once; pairs whose histograms still agree get a bijection: unique
colours by a join, interchangeable twins by rank, and only what is left by a bounded search.
"""

from __future__ import annotations

import math
from collections import Counter, defaultdict

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from provgraph.functions.hashing import colour, multiset
from provgraph.operators import grouping, runwise
from provgraph.plans.choose import choose
from provgraph.plans.iterate import materialize, release
from provgraph.schema import ProvGraph

SHARE = 24_000_000  # edges

MATCHED, UNMATCHED, UNDECIDED = "matched", "unmatched", "undecided"


def node_hashes(g: ProvGraph, rounds: int | None = 1, directed: bool = False, label_cols: tuple[str, ...] = ()) -> DataFrame:
    """(run_id, node_id, node_type, c1, c2), to a fixpoint if ``rounds`` is None: by run in one task where all runs fit one, else by rounds
    over the whole graph. One round without direction: the multiset of (edge label, neighbour's type)
    of each node."""
    attrs = ("node_type", *label_cols)
    if rounds == 1 and not directed:
        seen = grouping.views(g, ("out", "in")).select("run_id", "node_id", "label", "far")
        far = g.nodes.select("run_id", F.col("node_id").alias("far"), *(F.coalesce(F.col(a).cast("string"), F.lit("")).alias(f"far_{a}") for a in attrs))
        sig = seen.join(far, ["run_id", "far"]).groupBy("run_id", "node_id").agg(*multiset(F.col("label"), *(F.col(f"far_{a}") for a in attrs)))
        own = g.nodes.select("run_id", "node_id", "node_type", *(F.coalesce(F.col(a).cast("string"), F.lit("")).alias(f"own_{a}") for a in attrs))
        parts = [*(F.col(f"own_{a}") for a in attrs), F.coalesce("m_count", F.lit(0)), *(F.coalesce(c, F.lit(0)).cast("decimal(38,0)") for c in ("m_sum1", "m_sum2"))]
        return own.join(sig, ["run_id", "node_id"], "left").select("run_id", "node_id", "node_type", *colour(*parts))
    if rounds is None and not label_cols and choose(g) == "run-parallel":
        return runwise.colours(g)
    state = grouping.refine(g, grouping.start(g, attrs), ("out", "in"), True, rounds)
    return state.join(g.nodes.select("run_id", "node_id", "node_type"), ["run_id", "node_id"]).select("run_id", "node_id", "node_type", "c1", "c2")


def fingerprint(g: ProvGraph, hashes: DataFrame | None = None) -> DataFrame:
    """(run_id, nodes, edges, f1, f2): the multiset of a run's node hashes."""
    h = node_hashes(g, None, True) if hashes is None else hashes
    n = h.groupBy("run_id").agg(*multiset(F.col("node_type"), F.col("c1"), F.col("c2")))
    e = g.edges.groupBy("run_id").agg(F.count(F.lit(1)).alias("edges"))
    return n.join(e, "run_id", "left").select("run_id", F.col("m_count").alias("nodes"), F.coalesce("edges", F.lit(0)).alias("edges"), *(c.alias(f) for c, f in zip(colour(F.col("m_sum1").cast("decimal(38,0)"), F.col("m_sum2").cast("decimal(38,0)")), ("f1", "f2"), strict=True)))


def classes(g: ProvGraph, exact: bool = False, max_steps: int = 20_000) -> DataFrame:
    """(run_id, class_id): runs with one fingerprint; class_id is the least of them.

    The fingerprint is of refined colours, which tell all trees and chains apart, but not all regular graphs. With ``exact`` each
    run of a class is verified against the class's least; those that differ form a class of their own and are verified again.
    A search that passes ``max_steps`` leaves its run with those that differ.
    """
    f = fingerprint(g)
    least = f.groupBy("nodes", "edges", "f1", "f2").agg(F.min("run_id").alias("class_id"))
    found = f.join(least, ["nodes", "edges", "f1", "f2"]).select("run_id", "class_id")
    if not exact:
        return found
    left, out = materialize(found, "classes"), None
    while not left.isEmpty():
        pairs = left.filter("run_id <> class_id").select(F.col("class_id").alias("run_a"), F.col("run_id").alias("run_b"))
        verdicts = verify_many(g, g, pairs, max_steps=max_steps).filter(F.col("verdict") == MATCHED).select(F.col("run_b").alias("run_id"))
        same = materialize(left.join(verdicts, "run_id", "left_semi").union(left.filter("run_id = class_id")).select("run_id", "class_id"), "classes")
        out = same if out is None else out.union(same)
        rest = left.join(same.select("run_id"), "run_id", "left_anti")
        heads = rest.groupBy("class_id").agg(F.min("run_id").alias("head"))
        left = materialize(rest.join(heads, "class_id").select("run_id", F.col("head").alias("class_id")), "classes")
    return found.limit(0) if out is None else out


def _sizes(g: ProvGraph) -> DataFrame:
    n = g.nodes.groupBy("run_id").agg(F.count(F.lit(1)).alias("nodes"))
    e = g.edges.groupBy("run_id").agg(F.count(F.lit(1)).alias("edges"))
    return n.join(e, "run_id", "left").select("run_id", "nodes", F.coalesce("edges", F.lit(0)).alias("edges"))


def _histogram_equal(a: DataFrame, b: DataFrame, pairs: DataFrame) -> DataFrame:
    """(pair, same) by comparing the runs' counts per (type, colour)."""
    keys = ["pair", "node_type", "c1", "c2"]

    def count(h: DataFrame, side: str) -> DataFrame:
        return pairs.select("pair", F.col(f"run_{side}").alias("run_id")).join(h, "run_id").groupBy(*keys).agg(F.count(F.lit(1)).alias(f"n_{side}"))

    both = count(a, "a").join(count(b, "b"), keys, "full")
    return both.groupBy("pair").agg(F.bool_and(F.col("n_a").eqNullSafe(F.col("n_b"))).alias("same"))


def verify_many(a: ProvGraph, b: ProvGraph, pairs: DataFrame, mode: str = "exact", empty_matches: bool = False, max_steps: int = 20_000) -> DataFrame:
    """(run_a, run_b, verdict) of pairs (run_a, run_b) of runs of ``a`` and ``b``.

    Two empty runs match only if ``empty_matches``. 'exact' never guesses: a search that passes ``max_steps`` is 'undecided'.
    'one_hop' compares sums over hashes, made run by run where all runs fit a task, else by shares of the names.
    """
    if mode == "one_hop":
        sums = runwise.one_hop if choose(a) == choose(b) == "run-parallel" else one_hop_by_shares
        return _by_sums(pairs.select("run_a", "run_b").distinct(), sums(a), sums(b), empty_matches)
    p = pairs.select("run_a", "run_b").distinct().withColumn("pair", F.concat_ws("|", "run_a", "run_b"))
    p = p.join(_sizes(a).select(F.col("run_id").alias("run_a"), F.col("nodes").alias("na"), F.col("edges").alias("ea")), "run_a", "left").join(_sizes(b).select(F.col("run_id").alias("run_b"), F.col("nodes").alias("nb"), F.col("edges").alias("eb")), "run_b", "left")
    p = materialize(p.fillna(0, ["na", "nb", "ea", "eb"]), "pairs")
    fit = p.filter("na = nb and ea = eb and na > 0")
    one = _histogram_equal(node_hashes(a), node_hashes(b), fit)
    good = materialize(fit.join(one.filter("same").select("pair"), "pair", "left_semi"), "pairs")
    good = good.join(_mappings(a, b, good, max_steps).groupBy("pair").agg(F.min("status").alias("status")), "pair", "left")
    verdict = F.when((F.col("na") == 0) & (F.col("nb") == 0), F.lit(MATCHED if empty_matches else UNMATCHED)).otherwise(F.coalesce("status", F.lit(UNMATCHED)))
    return p.join(good.select("pair", "status"), "pair", "left").select("run_a", "run_b", verdict.alias("verdict"))


def one_hop_by_shares(g: ProvGraph) -> DataFrame:
    """(run_id, nodes, edges, f1, f2) of runs with nodes, as ``runwise.one_hop`` says, for graphs with runs that fit no task.

    Names meet as numbers. One share of them after the other gets the types at its edges' far ends, its hashes, and their sums by run; the
    shuffles of a share go before the next one is made, so that disk follows ``SHARE`` and the nodes, not all edges at once.
    """
    spark = g.nodes.sparkSession
    name = lambda c: F.when(F.col("run_id").isNotNull() & F.col(c).isNotNull(), F.xxhash64("run_id", c))
    word = lambda c: F.xxhash64(F.coalesce(F.col(c), F.lit("")))
    nodes = g.nodes.select("run_id", name("node_id").alias("x"), word("node_type").alias("type"))
    ends = g.edges.select(name("src").alias("s"), name("dst").alias("d"), word("label").alias("label"))
    both = F.explode(F.array(F.struct(F.col("s").alias("x"), F.col("d").alias("far")), F.struct(F.col("d").alias("x"), F.col("s").alias("far"))))
    views = ends.filter("s is not null and d is not null").select("label", both.alias("v")).select("v.x", "v.far", "label")
    sizes = materialize(g.edges.groupBy("run_id").agg(F.count(F.lit(1)).alias("edges")), "sizes")
    total = sizes.agg(F.sum("edges")).first()[0] or 1
    shares = max(math.ceil(total / SHARE), min(4, math.ceil(8 * total / SHARE)))
    made = None
    for k in range(shares):
        share = F.pmod(F.col("x"), F.lit(shares)) == k
        far = nodes.filter("x is not null").select(F.col("x").alias("far"), "type").hint("shuffle_hash")
        items = views.filter(share).join(far, "far").groupBy("x", "label", "type").agg(F.count(F.lit(1)).alias("n"))
        sig = items.groupBy("x").agg(*multiset(F.col("label"), F.col("type"), F.col("n")))
        own = nodes.filter(share | F.col("x").isNull() if k == 0 else share)
        parts = [F.col("type"), F.coalesce("m_count", F.lit(0)), *(F.coalesce(c, F.lit(0)).cast("decimal(38,0)") for c in ("m_sum1", "m_sum2"))]
        sums = own.join(sig, "x", "left").select("run_id", "type", *colour(*parts)).groupBy("run_id").agg(*multiset(F.col("type"), F.col("c1"), F.col("c2")))
        sums = materialize(sums, "sums")
        release(spark)
        made = sums if made is None else made.unionByName(sums)
    made = made.groupBy("run_id").agg(F.sum("m_count").alias("nodes"), F.sum("m_sum1").alias("f1"), F.sum("m_sum2").alias("f2"))
    return made.join(sizes, "run_id", "left").select("run_id", "nodes", F.coalesce("edges", F.lit(0)).alias("edges"), "f1", "f2")


def _by_sums(pairs: DataFrame, a: DataFrame, b: DataFrame, empty_matches: bool) -> DataFrame:
    """(run_a, run_b, verdict) of pairs by the sums of their runs."""
    names = ("nodes", "edges", "f1", "f2")
    x, y = (h.select(F.col("run_id").alias(f"run_{s}"), F.struct(*names).alias(s)) for h, s in ((a, "a"), (b, "b")))
    j = pairs.join(x, "run_a", "left").join(y, "run_b", "left")
    verdict = F.when(F.col("a").isNull() & F.col("b").isNull(), MATCHED if empty_matches else UNMATCHED).when(F.col("a") == F.col("b"), MATCHED).otherwise(UNMATCHED)
    return j.select("run_a", "run_b", verdict.alias("verdict"))


def verify(a: ProvGraph, b: ProvGraph, mode: str = "exact", **how) -> DataFrame:
    """The verdicts of each run against the run with its identifier."""
    runs = a.nodes.select("run_id").union(b.nodes.select("run_id")).distinct()
    return verify_many(a, b, runs.select(F.col("run_id").alias("run_a"), F.col("run_id").alias("run_b")), mode, **how)


def _paired(g: ProvGraph, pairs: DataFrame, side: str) -> ProvGraph:
    """The runs of one side with the pair as run: (run_id = pair)."""
    p = pairs.select("pair", F.col(f"run_{side}").alias("run_id"))
    return ProvGraph(*(x.join(p, "run_id").drop("run_id").withColumnRenamed("pair", "run_id") for x in (g.nodes.select("run_id", "node_id", "node_type"), g.edges.select("run_id", "src", "dst", "label"))))


def _mappings(a: ProvGraph, b: ProvGraph, pairs: DataFrame, max_steps: int) -> DataFrame:
    """(pair, node_a, node_b, status): a verified bijection for every matching pair; a row of nulls for an undecided one."""
    sides = {s: _paired(g, pairs, s) for s, g in (("a", a), ("b", b))}
    tag = lambda df, s, *cols: df.select(*(F.concat(F.lit(f"{s}:"), F.col(c)).alias(c) if c in cols else F.col(c) for c in df.columns))
    both = ProvGraph(*(tag(getattr(sides["a"], x), "a", *cols).unionByName(tag(getattr(sides["b"], x), "b", *cols)) for x, cols in (("nodes", ("node_id",)), ("edges", ("src", "dst")))))
    colours = runwise.colours(both) if choose(both) == "run-parallel" else grouping.refine(both, grouping.start(both), ("out", "in"), True)
    colours = materialize(colours.select("run_id", "node_id", "c1", "c2"), "colours")
    side = colours.select("run_id", F.substring("node_id", 1, 1).alias("s"), F.expr("substring(node_id, 3)").alias("node"), "c1", "c2")
    n = side.groupBy("run_id", "c1", "c2").agg(F.count_if(F.col("s") == "a").alias("ka"), F.count_if(F.col("s") == "b").alias("kb"))
    bad = n.filter("ka <> kb").select("run_id").distinct()
    side, n = side.join(bad, "run_id", "left_anti"), n.join(bad, "run_id", "left_anti")
    # twins: nodes of one colour with the same neighbours, which may be paired in any order
    near = grouping.views(both, ("out", "in")).groupBy("run_id", "node_id").agg(*multiset(F.col("side"), F.col("label"), F.col("far")))
    near = near.select("run_id", F.substring("node_id", 1, 1).alias("s"), F.expr("substring(node_id, 3)").alias("node"), *(c.alias(x) for c, x in zip(colour(F.col("m_count"), F.col("m_sum1").cast("decimal(38,0)"), F.col("m_sum2").cast("decimal(38,0)")), ("t1", "t2"), strict=True)))
    rich = side.join(n.select("run_id", "c1", "c2", F.col("ka").alias("k")), ["run_id", "c1", "c2"]).join(near, ["run_id", "s", "node"], "left")
    sets = rich.groupBy("run_id", "s", "c1", "c2").agg(F.count_distinct(F.struct(F.coalesce("t1", F.lit(0)), F.coalesce("t2", F.lit(0)))).alias("sets"))
    sets = sets.groupBy("run_id", "c1", "c2").agg(F.max("sets").alias("sets"))
    rich = materialize(rich.join(sets, ["run_id", "c1", "c2"]).withColumn("r", F.row_number().over(Window.partitionBy("run_id", "s", "c1", "c2").orderBy("node"))), "ranked")
    open_runs = rich.filter("sets > 1 and k > 1").select("run_id").distinct()
    easy = rich.join(open_runs, "run_id", "left_anti")
    x, y = (easy.filter(F.col("s") == s).select("run_id", "c1", "c2", "r", F.col("node").alias(f"node_{s}")) for s in "ab")
    mapped = x.join(y, ["run_id", "c1", "c2", "r"]).select(F.col("run_id").alias("pair"), "node_a", "node_b", F.lit(MATCHED).alias("status"))
    hard = rich.join(open_runs, "run_id", "left_semi")
    edges = both.edges.join(open_runs, "run_id", "left_semi").select(F.col("run_id").alias("pair"), F.lit("e").alias("what"), F.substring("src", 1, 1).alias("s"), F.expr("substring(src, 3)").alias("x"), F.expr("substring(dst, 3)").alias("y"), "label")
    nodes = hard.select(F.col("run_id").alias("pair"), F.lit("n").alias("what"), "s", F.col("node").alias("x"), F.concat_ws("_", "c1", "c2").alias("y"), F.lit("").alias("label"))

    def search(t: pa.Table) -> pa.Table:
        found, steps = _search(list(zip(*(t.column(c).to_pylist() for c in ("what", "s", "x", "y", "label")), strict=True)), max_steps)
        rows = sorted(found.items()) if found else [(None, None)] if steps > max_steps else []
        status, text = MATCHED if found else UNDECIDED, pa.string()
        return pa.table({"pair": pa.array([t.column("pair")[0].as_py()] * len(rows), text), "node_a": pa.array([p for p, _ in rows], text), "node_b": pa.array([q for _, q in rows], text), "status": pa.array([status] * len(rows), text)})

    searched = nodes.unionByName(edges).groupBy("pair").applyInArrow(search, "pair string, node_a string, node_b string, status string")
    proposed = materialize(mapped.unionByName(searched), "mappings")
    return _preserving(proposed, sides)


def _preserving(proposed: DataFrame, sides: dict[str, ProvGraph]) -> DataFrame:
    """The proposed mappings of pairs whose mapped edges are the other run's, as multisets."""
    m = proposed.filter("status = 'matched'").withColumnRenamed("pair", "run_id")
    e = sides["a"].edges
    for end in ("src", "dst"):
        e = e.join(m.select("run_id", F.col("node_a").alias(end), F.col("node_b").alias(f"m_{end}")), ["run_id", end])
    x = e.groupBy("run_id", F.col("m_src").alias("src"), F.col("m_dst").alias("dst"), "label").agg(F.count(F.lit(1)).alias("p"))
    y = sides["b"].edges.join(m.select("run_id").distinct(), "run_id", "left_semi").groupBy("run_id", "src", "dst", "label").agg(F.count(F.lit(1)).alias("q"))
    wrong = x.join(y, ["run_id", "src", "dst", "label"], "full").filter(~F.col("p").eqNullSafe(F.col("q"))).select(F.col("run_id").alias("pair")).distinct()
    return proposed.join(wrong, "pair", "left_anti")


def _search(rows: list[tuple[str, str, str, str, str]], max_steps: int) -> tuple[dict[str, str] | None, int]:
    """Individualise and refine with backtracking on one pair of runs: a bijection or none, and the steps taken."""
    out = {s: defaultdict(Counter) for s in "ab"}
    colours: dict[str, dict[str, object]] = {"a": {}, "b": {}}
    for what, s, x, y, label in rows:
        if what == "n":
            colours[s][x] = y
        else:
            out[s][x][("out", label, y)] += 1
            out[s][y][("in", label, x)] += 1
    steps = 0

    def stable(c: dict[str, dict[str, object]]) -> dict[str, dict[str, object]] | None:
        nonlocal steps
        while True:
            steps += 1
            new = {s: {v: (c[s][v], tuple(sorted(((d, lab, str(c[s][w])), k) for (d, lab, w), k in out[s][v].items()))) for v in c[s]} for s in "ab"}
            name = {v: i for i, v in enumerate(sorted(set(new["a"].values()) | set(new["b"].values()), key=repr))}
            new = {s: {v: name[x] for v, x in new[s].items()} for s in "ab"}
            if Counter(new["a"].values()) != Counter(new["b"].values()):
                return None
            if len(set(new["a"].values())) == len(set(c["a"].values())):
                return new
            c = new

    def extend(c: dict[str, dict[str, object]]) -> dict[str, str] | None:
        c = stable(c)
        if c is None or steps > max_steps:
            return None
        members = {s: defaultdict(list) for s in "ab"}
        for s in "ab":
            for v in sorted(c[s]):
                members[s][c[s][v]].append(v)
        several = [k for k, v in members["a"].items() if len(v) > 1]
        if not several:
            m = {v[0]: members["b"][k][0] for k, v in members["a"].items()}
            same = all(Counter({(d, lab, m[w]): k for (d, lab, w), k in out["a"][v].items()}) == out["b"][m[v]] for v in m)
            return m if same else None
        k = min(several, key=lambda k: (len(members["a"][k]), str(k)))
        v = members["a"][k][0]
        for w in members["b"][k]:
            trial = {"a": c["a"] | {v: "chosen"}, "b": c["b"] | {w: "chosen"}}
            if (m := extend(trial)) is not None or steps > max_steps:
                return m
        return None

    return extend(colours), steps


def bijection(a: ProvGraph, b: ProvGraph, max_steps: int = 20_000) -> DataFrame:
    """(run_id, node_a, node_b) for runs with the same identifier that match."""
    pairs = a.nodes.select("run_id").intersect(b.nodes.select("run_id"))
    p = materialize(pairs.select(F.col("run_id").alias("run_a"), F.col("run_id").alias("run_b"), F.concat_ws("|", "run_id", "run_id").alias("pair")), "pairs")
    m = _mappings(a, b, p, max_steps).filter("status = 'matched'")
    return m.join(p, "pair").select(F.col("run_a").alias("run_id"), "node_a", "node_b")
