"""Worked micro-examples with exact expectations, and invariants."""

import pytest
from micro import F7, F8, F9, RING, SQUARES, build, groups, ids, names, sec

from provgraph.operators import baselines, collapse, content, graph, grouping, isomorph, reach, replay, runwise, summaries, temporal, versioning
from provgraph.operators.catalog import Catalog
from provgraph.plans.choose import choose, salted_counts
from provgraph.schema import ProvGraph
from provgraph.sources import carriers


def arrivals(df):
    return {r["node_id"]: r["arrival"] for r in df.collect()}


def test_no_dependency(spark):
    g = build(spark, [("P1 U A", 1, 2), ("P2 U B", 1, 3), ("B G P1", 5, 6), ("C G P2", 7, 8)])
    assert names(temporal.connected(g, ids(spark, "A")).filter("hops > 0")) == {"P1", "B", "P2", "C"}
    assert arrivals(temporal.depends(g, ids(spark, "A"))) == {"P1": sec(1), "B": sec(5)}
    assert arrivals(temporal.depends(g, ids(spark, "B"))) == {"P2": sec(1), "C": sec(7)}
    assert set(arrivals(temporal.depends(g, ids(spark, "A"), as_of=str(sec(4))))) == {"P1"}
    later = build(spark, [("P1 U A", 1, 2), ("P2 U B", 1, 5), ("B G P1", 5, 6), ("C G P2", 7, 8)])
    assert arrivals(temporal.depends(later, ids(spark, "A"))) == {"P1": sec(1), "B": sec(5), "P2": sec(5), "C": sec(7)}
    assert set(arrivals(temporal.depends(later, ids(spark, "A"), strict=True))) == {"P1", "B"}


def test_several_intervals_and_lineage(spark):
    g = build(spark, [("P U A", 1, 2), ("P U A", 10, 12), ("P U E", 6, 7), ("D G P", 4, 5), ("H G P", 11, 13)])
    assert arrivals(temporal.depends(g, ids(spark, "A")))["D"] == sec(4)
    assert set(arrivals(temporal.depends(g, ids(spark, "E")))) == {"P", "H"}
    assert names(temporal.lineage(g, ids(spark, "D"))) == {"P", "A"}
    assert names(temporal.lineage(g, ids(spark, "H"))) == {"P", "A", "E"}


def test_hazard_and_versions(spark):
    g = build(spark, [("P1 U F", 1, 2), ("F G P2", 3, 4), ("P3 U F", 5, 6)])
    assert [tuple(r)[1:] for r in versioning.hazards(g).collect()] == [("P1", "F", "P2")]
    assert [r["n"] for r in versioning.hazard_counts(g).collect()] == [1]
    v = versioning.version_files(g)
    assert {(r["src"], r["dst"]) for r in v.edges.collect()} == {("P1", "F#0"), ("F#1", "P2"), ("P3", "F#1")}
    assert versioning.hazards(v).isEmpty()


def test_cycles(spark):
    two = build(spark, [("P1 U F", 1, 2), ("G G P1", 3, 4), ("P2 U G", 5, 6), ("F G P2", 7, 8)])
    assert not reach.acyclicity(two).first()["acyclic"]
    assert names(reach.cyclic_cores(two)) == {"P1", "P2", "F", "G"}
    assert reach.acyclicity(versioning.version_files(two)).first()["acyclic"]
    back = build(spark, [("F G P", 1, 2), ("P U F", 3, 4)])
    v = versioning.version_files(back)
    assert not reach.acyclicity(v).first()["acyclic"]
    assert reach.acyclicity(versioning.version_files(back, drop_readback=True)).first()["acyclic"]
    s = versioning.split_processes(v)
    assert reach.acyclicity(s).first()["acyclic"] and ("P#1", "P#0") in {(r["src"], r["dst"]) for r in s.edges.collect()}
    ways = build(spark, [("G G P", 1, 1), ("F G Q", 1, 1), ("Q U G", 2, 2), ("P U F", 4, 4)])
    assert not reach.acyclicity(versioning.version_files(ways)).first()["acyclic"]
    assert reach.acyclicity(versioning.prepare(ways)).first()["acyclic"]
    with pytest.raises(ValueError):
        versioning.prepare(ways, "raise")


def test_modified_and_partial(spark):
    g = build(spark, ["P U A", "B G P", "Q I P", "Q U B", "Q U C", "D G Q"])

    def again(changed, closure):
        return names(replay.modified(g, ids(spark, *changed), closure).filter("action = 'rerun'"))

    for closure in ("direct", "dataflow", "temporal"):
        assert again(["A"], closure) == again(["A", "C"], closure) == {"P", "Q"}
        assert again(["C"], closure) == {"Q"}
    assert names(replay.modified(g, ids(spark, "C")).filter("action = 'reuse'")) == {"P", "A", "B"}
    f9 = build(spark, F9)
    assert names(replay.modified(f9, ids(spark, "A1"), "direct").filter("action = 'rerun'")) == {"P1"}
    assert names(replay.modified(f9, ids(spark, "A1")).filter("action in ('rerun', 'regenerate')")) == {"P1", "P2", "P3", "F1", "D"}
    assert names(replay.required(f9, ids(spark, "P0"))) == {"P0", "P1", "P2"}
    assert names(replay.required(f9, ids(spark, "P0"), "descendants")) == {"P0", "P1", "P2", "P3"}
    sub = replay.sub_container(f9, ids(spark, "P2"))
    assert names(sub.nodes) == {"P2", "P3", "F1", "L1", "L2", "D"}
    assert names(replay.intermediates(sub, f9)) == {"F1"}
    assert replay.executable(sub, f9).first()["executable"]
    assert replay.unused(sub.nodes.filter("node_type = 'entity'"), sub).isEmpty()
    assert names(replay.required(f9, ids(spark, "P2"), "lineage")) == {"P0", "P1", "P2", "P3"}


def test_isomorphism(spark):
    g = build(spark, F9)
    for mode in ("one_hop", "exact"):
        assert isomorph.verify(g, carriers.rerun(g), mode).first()["verdict"] == "matched"
        for k in range(len(F9)):
            less = build(spark, F9[:k] + F9[k + 1 :])
            if k in (0, 9):  # two of the edges, for time
                assert isomorph.verify(g, less, mode).first()["verdict"] == "unmatched"
    ring, squares = build(spark, RING), build(spark, SQUARES)
    assert isomorph.verify(ring, squares, "one_hop").first()["verdict"] == "matched"
    assert isomorph.verify(ring, squares, "exact").first()["verdict"] == "unmatched"
    assert isomorph.verify(ring, carriers.rerun(ring)).first()["verdict"] == "matched"
    assert isomorph.verify(ring, carriers.rerun(ring), max_steps=0).first()["verdict"] == "undecided"
    assert baselines.all_automorphisms(ring).first()["automorphisms"] == 8
    a, b = build(spark, ["c I b", "b I a"]), build(spark, ["a I b", "c I b"])
    assert isomorph.verify(a, b, "one_hop").first()["verdict"] == "matched"
    assert isomorph.verify(a, b).first()["verdict"] == "unmatched"
    m = {r["node_a"]: r["node_b"] for r in isomorph.bijection(g, carriers.rerun(g)).collect()}
    assert len(m) == len(set(m.values())) == 9


def test_groupings(spark):
    f7, f8 = build(spark, F7), build(spark, F8)
    assert groups(grouping.ancestry(f7)) == {frozenset("A"), frozenset("B"), frozenset({"P1", "P2"})}
    for f in (grouping.relationship, grouping.ancestry_degree):
        assert all(len(x) == 1 for x in groups(f(f7)))
    p, own = frozenset({"P1", "P2", "P3"}), frozenset({"F1", "F2", "F3"})
    assert groups(grouping.ancestry(f8)) == groups(grouping.relationship(f8)) == {p, own | {"F4"}}
    for scope in ("group", "label"):
        assert groups(grouping.ancestry_degree(f8, scope)) == {p, own, frozenset({"F4"})}
    assert groups(baselines.splitter_queue(f8)) == {p, own, frozenset({"F4"})}
    f9 = build(spark, F9)
    fine, coarse = groups(grouping.ancestry_degree(f9)), groups(grouping.ancestry(f9))
    assert all(any(x <= y for y in coarse) for x in fine)
    assert fine == groups(baselines.splitter_queue(f9))
    assert grouping.check(f9, grouping.ancestry(f9)).isEmpty()
    assert not grouping.check(f9, grouping.ancestry(f9).filter("node_id <> 'P0'")).isEmpty()


def test_collapse(spark):
    g = build(spark, F9)
    assert [(r["child"], r["parent"]) for r in collapse.similarity(g).collect()] == [("L2", "L1")]
    q, m = collapse.summarize(g)
    assert names(q.nodes) == {"P0", "P1", "P2", "L1"}
    assert {(r["src"], r["label"], r["dst"]) for r in q.edges.collect()} == {("P1", "wasInformedBy", "P0"), ("P2", "wasInformedBy", "P0"), ("P2", "wasInformedBy", "P1"), ("P1", "used", "L1"), ("P2", "used", "L1")}
    assert tuple(collapse.clicks(m).first()) == (1, 3)
    assert names(collapse.expand(m, "P2"), "child") == {"D", "P3"}
    a, notes = collapse.annotate(q)
    assert (a.nodes.count(), a.edges.count()) == (3, 3) and {r["node_id"]: r["files"] for r in notes.collect()} == {"P1": ["L1"], "P2": ["L1"]}
    same, more = collapse.summarize(q)
    assert more.filter("rule = 'similarity'").isEmpty() and same.nodes.count() <= 4
    chain, log = collapse.summarize(build(spark, ["P1 I P0", "P2 I P1", "P3 I P2"]))
    assert names(chain.nodes) == {"P0"} and chain.edges.isEmpty() and {r["parent"] for r in log.collect()} == {"P0"}
    f8, _ = collapse.summarize(build(spark, F8))
    assert names(f8.nodes) == {"P1", "P2", "P3", "F4"} and f8.edges.count() == 3


def test_invalid_edges(spark):
    g = build(spark, ["P U F", "Q I P"])
    bad = spark.createDataFrame([(0, "F", "P", "used"), (0, "P", "F", "wasGeneratedBy"), (0, "F", "P", "wasInformedBy"), (0, "P", "X", "used"), (0, "P", "F", "odd")], "run_id long, src string, dst string, label string")
    found = graph.violations(ProvGraph(g.nodes, g.edges.unionByName(bad, allowMissingColumns=True)))
    assert sorted(r["problem"] for r in found.collect()) == ["dangling", "label", "type", "type", "type"]


def test_content(spark):
    middle = "".join(chr(97 + i * 7 % 26) + str(i) for i in range(3000))
    rows = [(0, "a", middle), (0, "b", "prefix " + middle), (0, "c", ""), (0, "d", "héllo wörld " * 300), (0, "e", middle)]
    f = spark.createDataFrame(rows, "run_id long, file_id string, content string")
    ch = content.chunk(f)
    assert ch.filter("file_id = 'a'").join(ch.filter("file_id = 'b'"), "chunk_hash", "left_semi").count() > 0
    fixed = content.chunk(f, "fixed")
    assert fixed.filter("file_id = 'a'").join(fixed.filter("file_id = 'b'"), "chunk_hash", "left_semi").isEmpty()
    back = {r["file_id"]: r["content"] for r in content.restore(*content.store(ch)).collect()}
    assert back == {k: t for _, k, t in rows if t}
    lines = content.chunk(f, "line")
    assert {r["file_id"]: r["content"] for r in content.restore(*content.store(lines), sep="\n").collect()} == {k: t for _, k, t in rows}
    assert {r["file_id"]: r["stored_as"] for r in content.dedup_files(f).collect()}["e"] == "a"
    known = content.store(ch.filter("file_id = 'a'"))[0]
    assert content.ingest(known, ch.filter("file_id = 'e'")).isEmpty()


def test_catalog_and_plans(spark, tmp_path):
    cat, g = Catalog(spark, f"file://{tmp_path}/store"), build(spark, F9)
    assert cat.last("lab") == -1
    assert [cat.record("lab", g), cat.record("lab", g), cat.record("other", g)] == [0, 1, 0]
    assert cat.list().count() == 3 and cat.show("lab").edges.count() == 11
    assert names(cat.repeat("lab", given=["A1"]).filter("action = 'rerun'")) == {"P1", "P2", "P3"}
    put = cat.repeat("lab", given={"A1": "mine"})
    assert names(put.filter("action = 'given'")) == {"mine"} and names(put.filter("action = 'changed'")) == {"A1"}
    with pytest.raises(ValueError, match="nowhere"):
        cat.repeat("lab", given=["nowhere"])
    many = ProvGraph(*(x.union(y).union(z) for x, y, z in zip(*((h.nodes, h.edges) for h in (build(spark, F7, run=k) for k in (0, 1, 1500))), strict=True)))
    assert cat.record_all("bulk", many) == 1500 and cat.record("bulk", g) == 1501
    assert cat.show("bulk", 1500).edges.count() == 3 and cat.show("bulk").edges.count() == 11
    token = cat.export("lab", 1, f"file://{tmp_path}/out")
    assert token == cat.token("lab", 0) and Catalog.open(spark, f"file://{tmp_path}/out", token).nodes.count() == 9
    assert choose(g) == "run-parallel" and choose(g, 5) == "giant-graph"
    assert {r["label"]: r["n"] for r in salted_counts(g.edges.select("label", "src"), ["label"]).collect()} == {"used": 6, "wasGeneratedBy": 2, "wasInformedBy": 3}


def test_summaries_by_one_entry(spark):
    g = build(spark, F9)
    q, merges = collapse.summarize(g)
    nodes, edges = summaries.summarize(g)
    assert {r["group_id"] for r in nodes.collect()} == names(q.nodes) and edges.count() == q.edges.count()
    assert sum(r["size"] for r in nodes.collect()) == g.nodes.count()
    for method in summaries.METHODS[1:]:
        n, _ = summaries.summarize(g, method)
        assert sum(r["size"] for r in n.collect()) == g.nodes.count()
    with pytest.raises(ValueError, match="no summarization"):
        summaries.summarize(g, "else")


@pytest.mark.parametrize("edges", [F7, F8, F9, RING, SQUARES, ["P1 I P0", "P1 I P0", "P2 I P0"]])
def test_runwise_colours_equal_those_by_rounds(spark, edges):
    runs = [build(spark, edges, run=k) for k in (3, 8)]
    g = ProvGraph(*(x.union(y) for x, y in zip(*((h.nodes, h.edges) for h in runs), strict=True)))
    state = grouping.refine(g, grouping.start(g), ("out", "in"), True)

    def parts(df):
        by = {}
        for r in df.collect():
            by.setdefault((r["c1"], r["c2"]), set()).add((r["run_id"], r["node_id"]))
        return {frozenset(v) for v in by.values()}

    assert parts(runwise.colours(g)) == parts(state)


def test_classes_are_checked_inside(spark):
    runs = [build(spark, e, run=k) for k, e in enumerate((RING, SQUARES, RING, F8, SQUARES))]
    g = ProvGraph(_union([r.nodes for r in runs]), _union([r.edges for r in runs]))
    rough = {r["run_id"]: r["class_id"] for r in isomorph.classes(g).collect()}
    exact = {r["run_id"]: r["class_id"] for r in isomorph.classes(g, exact=True).collect()}
    assert rough == {0: 0, 1: 0, 2: 0, 3: 3, 4: 0} and exact == {0: 0, 1: 1, 2: 0, 3: 3, 4: 1}


def _union(frames):
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def test_moved_edges_keep_one_hop_hashes(spark):
    g = build(spark, ["A U x", "B U x", "B U y"])
    moved = carriers.rerun(g, perturb="move", every=1)
    assert [r["verdict"] for m in ("one_hop", "exact") for r in isomorph.verify(g, moved, m).collect()] == ["matched", "unmatched"]
    assert g.edges.count() == moved.edges.count()


def test_versions_of_hazard_files_alone(spark):
    g = build(spark, [("P1 U F", 1, 2), ("F G P2", 3, 4), ("H G P2", 5, 6), ("P3 U H", 7, 8)])
    v = names(versioning.version_files(g, "hazard").nodes)
    assert {"F#0", "F#1", "H"} <= v and "F" not in v
