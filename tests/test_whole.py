"""Queries read all rows of their tables."""

import pytest
from pyspark.sql import functions as F
from micro import F8, RING, SQUARES, build
from test_oracles import SF, duck  # noqa: F401
from test_sources_streams import _parts

import provgraph.coverage  # noqa: F401  its queries register themselves
from provgraph import queries
from provgraph.operators import baselines, trace, versioning
from provgraph.sources import carriers
from provgraph.streaming import live


@pytest.mark.parametrize("name", ["op_join_semi_all", "op_join_anti_all", "op_set_ops_all"])
def test_all_lines_count(spark, duck, name):  # noqa: F811
    """Every part is where all lines put it, not those of some orders."""
    got = {tuple(r) for r in queries.QUERIES[name](spark, SF).collect()}
    used = set(duck.execute("SELECT DISTINCT l_partkey, l_returnflag FROM lineitem").fetchall())
    if name == "op_set_ops_all":
        status = {}
        for p, s in duck.execute("SELECT DISTINCT l_partkey, l_linestatus FROM lineitem").fetchall():
            status.setdefault(p, set()).add(s == "F")
        assert got == {("both" if len(s) == 2 else "first" if True in s else "second", p) for p, s in status.items()}
    elif name == "op_join_semi_all":
        assert got == used
    else:
        every = {(p, f) for (p,) in duck.execute("SELECT p_partkey FROM part").fetchall() for _, f in used}
        assert got == every - used


def test_all_orders_pair(spark, duck):  # noqa: F811
    """The candidates over all pairs of orders, counted pair by pair."""
    rows = duck.execute("SELECT l_orderkey, count(DISTINCT l_partkey) AS k FROM lineitem GROUP BY l_orderkey, l_suppkey").fetchall()
    by = {}
    for run, k in rows:
        by.setdefault(k, {}).setdefault(run, 0)
        by[k][run] += 1
    want = {k: (sum(n.values()) ** 2 - sum(x * x for x in n.values())) // 2 for k, n in by.items()}
    got = dict.fromkeys(want, 0)
    for r in queries.QUERIES["op_join_nested_all"](spark, SF).collect():
        got[r["degree"]] += r["n_a"] * r["n_b"] * int(r["run_pairs"])
    assert got == want


def test_live_hazards_equal_batch(spark, tmp_path):
    a = carriers.audit_accesses(spark, SF)
    want = {tuple(r) for r in versioning.hazards(trace.from_accesses(a, "access")).select("reader", "file", "writer").collect()}
    got = live.drain(live.live_hazards(_parts(spark, tmp_path / "events"), None))
    assert {tuple(r) for r in got.select("reader", "file", "writer").collect()} == want
    assert queries.QUERIES["stream_hazards"](spark, SF).first()["hazards"] == len(want)


def test_live_sessions_equal_batch(spark, tmp_path):
    a = carriers.audit_accesses(spark, SF)
    at = F.col("t_begin").cast("timestamp").alias("t_begin")
    want = trace.coarsen(a, "session").select("actor", "op", "object", at, "n")
    got = live.drain(live.open_close_intervals(_parts(spark, tmp_path / "events"), delay=None), "complete").select(*want.columns)
    assert got.exceptAll(want).isEmpty() and want.exceptAll(got).isEmpty()
    total = want.groupBy("op").agg(F.count(F.lit(1)).alias("sessions"), F.sum("n").alias("accesses"))
    assert {tuple(r) for r in queries.QUERIES["stream_intervals"](spark, SF).collect()} == {tuple(r) for r in total.collect()}
    assert sum(r["accesses"] for r in total.collect()) == a.count()


@pytest.mark.parametrize("edges", [F8, RING, SQUARES, ["P1 I P0", "P2 I P0", "P3 I P0", "P1 U A", "P2 U A", "P3 U B", "D G P3"]])
def test_automorphisms_of_larger_runs(spark, edges):
    """Counting by refined colours, for runs beyond the bound, agrees with trying every bijection."""
    g = build(spark, edges)
    n = baselines.all_automorphisms(g).first()["automorphisms"]
    assert baselines.all_automorphisms(g, 1).first()["automorphisms"] == n > 0


def test_automorphisms_are_never_missing(spark):
    wide = build(spark, [f"P{i} U F{i}" for i in range(7)])  # 14 nodes
    assert baselines.all_automorphisms(wide).first()["automorphisms"] == 5040
    assert baselines.all_automorphisms(build(spark, [f"P U F{i}" for i in range(25)])).first()["automorphisms"] == 15511210043330985984000000
    assert queries.QUERIES["automorphism_baseline"](spark, SF).filter("automorphisms is null").isEmpty()
