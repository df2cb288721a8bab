"""What larger tables brought up: sums past a long, row limits, work that grew faster than its input."""

from pyspark.sql import functions as F
from micro import build
from test_oracles import SF
from test_sources_streams import _parts

import provgraph.coverage  # noqa: F401  its queries register themselves
from provgraph import queries
from provgraph.operators import grouping, isomorph, measures, versioning
from provgraph.schema import ProvGraph, edges_of
from provgraph.sources import carriers
from provgraph.streaming import live


def test_seconds_past_a_long(spark):
    """Intervals of centuries add up to more microseconds than a long holds."""
    century = 100 * 365 * 86400
    g = build(spark, [(f"P{i % 7} U F{i}", 0, 70 * century) for i in range(70)])
    want = 70.0 * 70 * century
    assert want * 1e6 > 2**63
    assert measures.access_seconds(g).first()["seconds"] == want
    acts = g.nodes.select("run_id", "node_id", "node_type", F.lit("reuse").alias("action"))
    r = measures.rerun_savings(g, acts).first()
    assert (r["processes"], r["reused"], r["seconds"], r["seconds_saved"]) == (7, 7, want, want)


def test_recursion_past_the_row_limit(spark):
    """The spawn tree is whole, however many rows Spark lets a recursion have by default."""
    whole = queries.QUERIES["op_sql_recursive"](spark, SF).count()
    spark.conf.set("spark.sql.cteRecursionRowLimit", "20")
    try:
        assert queries.QUERIES["op_sql_recursive"](spark, SF).count() == whole > 20
    finally:
        spark.conf.unset("spark.sql.cteRecursionRowLimit")


def test_hazards_are_counted_without_pairs(spark, tmp_path, monkeypatch):
    """The number of hazards of a stream is that of its pairs, per file, though no pair is made."""
    def no_pairs(*_):
        raise AssertionError("pairs")

    ev = _parts(spark, tmp_path / "events")
    pairs = live.drain(live.live_hazards(ev, None).select("reader", "file", "writer")).distinct().groupBy("file").agg(F.count(F.lit(1)).alias("n"))
    assert dict(map(tuple, live.count_hazards(ev).collect())) == dict(map(tuple, pairs.collect()))
    monkeypatch.setattr(live, "live_hazards", no_pairs)
    assert queries.QUERIES["stream_hazards"](spark, SF).first()["hazards"] > 0


def test_pairs_of_one_file_are_spread(spark, monkeypatch):
    """The hazards of a single file are made by several tasks, each pair once, whatever groups and arrays its accesses fall into."""
    monkeypatch.setattr(versioning, "GROUP", 8, raising=False)
    monkeypatch.setattr(versioning, "ARRAY", 2, raising=False)
    reads, writes = [(f"P{i}", i * 7 % 30) for i in range(40)], [(f"P{i}", i * 11 % 31) for i in range(20, 70)]  # with equal times and common processes
    rows = [(p, "F", "used", t) for p, t in reads] + [("F", p, "wasGeneratedBy", t) for p, t in writes] + [("P1", None, "used", 0), ("G", "P2", "wasGeneratedBy", 1), ("P3", "G", "used", 1)]
    edges = spark.createDataFrame([(run, *r) for run in (1, 2) for r in rows], "run_id long, src string, dst string, label string, t int")
    g = ProvGraph(None, edges_of(edges.withColumn("t_begin", F.timestamp_seconds("t").cast("timestamp_ntz")).withColumn("n", F.lit(1))))
    got = versioning.hazards(g).withColumn("task", F.spark_partition_id()).collect()
    want = sorted((run, r, "F", w) for run in (1, 2) for r, a in reads for w, b in writes if r != w and b > a)
    assert sorted((x["run_id"], x["reader"], x["file"], x["writer"]) for x in got) == want
    assert len({x["task"] for x in got if x["run_id"] == 1}) > 1


def test_stream_of_a_folder(spark, tmp_path):
    """An event table of several files is streamed whole."""
    spark.read.parquet(f"{SF}/events.parquet").repartition(3).write.parquet(f"{tmp_path}/events.parquet")
    want = queries.QUERIES["stream_hazards"](spark, SF).first()["hazards"]
    assert queries.QUERIES["stream_hazards"](spark, str(tmp_path)).first()["hazards"] == want


def test_reductions_are_made_once(spark):
    """The report and its means read finished rows, not the tables and graphs again."""
    r = queries.QUERIES["reduction_report"](spark, SF)
    assert all("/reductions-" in f for f in r.inputFiles())
    assert r.count() == 20 and r.filter("graph = 'mean'").count() == 4


def _exchanged(df):
    """The keys that rows of a query are dealt out by."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    return {k.split("#")[0] for line in plan.splitlines() if "hashpartitioning(" in line for k in line.split("hashpartitioning(")[1].split(")")[0].split(", ")[:-1]}


def test_one_hop_verdicts_move_runs_alone(spark):
    """No name of a node is dealt out: rows go by run, as numbers, and stay."""
    df = queries.QUERIES["repeat_verdicts_one_hop"](spark, SF)
    assert _exchanged(df) <= {"run_id", "run_a", "run_b"}
    assert df.count() == df.filter("verdict = 'matched'").count() > 0


def test_one_hop_verdicts_by_sums(spark, monkeypatch):
    """Sums made run by run say what histograms of joined hashes do: also with ends that are no node, names of several rows, null names."""
    g = carriers.order_runs(spark, SF)
    g = ProvGraph(*(x.filter("run_id < 60") for x in (g.nodes, g.edges)))
    twice = g.nodes.filter("run_id % 6 = 1 and kind = 'part'").union(g.nodes.filter("run_id % 6 = 2").limit(3).withColumn("node_id", F.lit(None).cast("string")))
    gone = "run_id % 6 = 3 and kind = 'part'"
    others = [carriers.rerun(g), carriers.rerun(g, perturb="flip", every=2), ProvGraph(g.nodes.unionByName(twice), g.edges), ProvGraph(g.nodes.filter(f"not ({gone})"), g.edges), ProvGraph(g.nodes.withColumn("node_type", F.when(F.expr("run_id % 5 = 0"), "entity").otherwise(F.col("node_type"))), g.edges), ProvGraph(g.nodes.filter("run_id > 9"), g.edges)]
    for i, b in enumerate(others):
        got = {}
        for how in ("run-parallel", "giant-graph"):
            monkeypatch.setattr(isomorph, "choose", lambda _, how=how: how)
            got[how] = sorted(map(tuple, isomorph.verify(g, b, "one_hop").collect()))
        assert got["run-parallel"] == got["giant-graph"], i
        monkeypatch.setattr("provgraph.operators.runwise.AT_ONCE", 50)


def test_groups_across_runs(spark, monkeypatch):
    """Rounds made run by run give the groups of all runs as one graph, however few rounds they begin with, and the query makes them so."""
    for g in (carriers.conversation_runs(spark, SF), carriers.order_runs(spark, SF)):
        g = ProvGraph(*(x.filter("run_id < 90") for x in (g.nodes, g.edges)))
        one = ProvGraph(*(x.withColumn("run_id", F.lit(0).cast("long")) for x in (g.nodes, g.edges)))
        want = sorted(map(tuple, grouping.ancestry_degree(one).select("node_id", "group_id").collect()))
        assert sorted(map(tuple, grouping.ancestry_degree_across(g, 1).collect())) == want

    def no_refine(*_):
        raise AssertionError("rounds over the whole graph")

    monkeypatch.setattr(grouping, "refine", no_refine)
    assert queries.QUERIES["orders_degree_groups"](spark, SF).count() > 0


def test_order_workflow_meets_by_numbers(spark, tmp_path):
    """Edges of the order workflow meet by the tables' keys, not by names; lines without a key still make one edge and one node per pair of names."""
    g = carriers.star(spark, SF)
    assert "label" not in _exchanged(g.edges) and "x" not in _exchanged(g.nodes)
    for t in ("region", "nation", "customer", "supplier", "part", "orders"):
        spark.read.parquet(f"{SF}/{t}.parquet").write.parquet(f"{tmp_path}/{t}.parquet")
    li = spark.read.parquet(f"{SF}/lineitem.parquet").limit(300)
    odd = li.withColumn("l_linenumber", F.when(F.expr("l_orderkey % 3 > 0"), F.col("l_linenumber"))).withColumn("l_orderkey", F.when(F.expr("l_suppkey % 4 > 0"), F.col("l_orderkey")))
    odd.union(li).write.parquet(f"{tmp_path}/lineitem.parquet")
    g = carriers.star(spark, str(tmp_path))
    edges = g.edges.filter("label = 'used' and src like 's:%' or label = 'wasGeneratedBy'")
    assert edges.filter("src is null or dst is null").count() > 0
    assert edges.count() == edges.select("src", "dst").distinct().count()
    assert edges.agg(F.sum("n")).first()[0] == 1200
    x = "concat('x:', l_orderkey, '_', l_linenumber)"
    assert g.nodes.filter("kind = 'shipment'").count() == odd.union(li).selectExpr(f"{x} as x", "l_orderkey").distinct().count()


def test_rounds_of_a_run_in_its_task(spark, monkeypatch):
    """A graph that fits a task is refined there, to the groups that rounds over the whole graph give: also with ends that are no node, names of
    several rows or none, parallel edges, and a bound on the rounds."""
    g = carriers.conversation_runs(spark, SF)
    g = ProvGraph(*(x.filter("run_id < 40") for x in (g.nodes, g.edges)))
    one = ProvGraph(*(x.withColumn("run_id", F.lit(0).cast("long")) for x in (g.nodes, g.edges)))
    odd = ProvGraph(g.nodes.filter("run_id % 5 > 0 or kind <> 'user'").union(g.nodes.filter("run_id % 6 = 1")).union(g.nodes.filter("run_id % 6 = 2").limit(3).withColumn("node_id", F.lit(None).cast("string"))), g.edges.union(g.edges.filter("run_id % 7 = 1")))
    how = [lambda g, **k: grouping.ancestry(g, **k), lambda g, **k: grouping.ancestry(g, "incoming", **k), lambda g, **k: grouping.ancestry_degree(g, **k), lambda g, **k: grouping.ancestry_degree(g, "label", **k), lambda g, **k: grouping.relationship(g, **k)]
    cases = [(h, x, k) for h in how for x, k in ((one, {}), (odd, {}))] + [(h, one, {"max_rounds": 1}) for h in (how[0], how[4])]
    rows = lambda df: sorted(map(tuple, df.select("run_id", "node_id", "group_id").collect()), key=repr)
    with monkeypatch.context() as m:
        m.setattr(grouping, "choose", lambda *_: "giant-graph")
        want = [rows(h(x, **k)) for h, x, k in cases]

    def no_rounds(*_, **__):
        raise AssertionError("rounds over the whole graph")

    monkeypatch.setattr(grouping, "fixpoint", no_rounds)
    for i, (h, x, k) in enumerate(cases):
        assert rows(h(x, **k)) == want[i], i


def test_one_hop_verdicts_by_shares(spark, monkeypatch):
    """A graph with a run that fits no task is checked share by share of its names, with the verdicts that run by run gives, and never joined by names."""
    g = carriers.conversation_runs(spark, SF)
    g = ProvGraph(*(x.filter("run_id < 40") for x in (g.nodes, g.edges)))
    odd = ProvGraph(g.nodes.filter("run_id % 5 > 0 or kind <> 'user'").union(g.nodes.filter("run_id % 6 = 1")).union(g.nodes.filter("run_id % 6 = 2").limit(3).withColumn("node_id", F.lit(None).cast("string"))), g.edges.union(g.edges.filter("run_id % 7 = 1")))
    others = [(g, carriers.rerun(g, perturb="flip", every=2)), (g, odd), (odd, carriers.rerun(odd))]
    want = [sorted(map(tuple, isomorph.verify(a, b, "one_hop").collect())) for a, b in others]
    assert {v for w in want for *_, v in w} == {isomorph.MATCHED, isomorph.UNMATCHED}

    def by_names(*_, **__):
        raise AssertionError("joins by names")

    monkeypatch.setattr(isomorph, "choose", lambda _: "giant-graph")
    monkeypatch.setattr(isomorph, "node_hashes", by_names)
    monkeypatch.setattr(isomorph, "SHARE", g.edges.count() // 3, raising=False)
    for (a, b), w in zip(others, want, strict=True):
        assert sorted(map(tuple, isomorph.verify(a, b, "one_hop").collect())) == w
