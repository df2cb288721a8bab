"""Micro-graphs in shorthand: ``P U F`` used, ``F G P`` generated, ``P I Q`` informed; intervals are seconds."""

from datetime import datetime, timedelta

from pyspark.sql import functions as F

from provgraph.schema import ENDS, GENERATED, INFORMED, USED, ProvGraph, edges_of, nodes_of

LABEL = {"U": USED, "G": GENERATED, "I": INFORMED}
AT = datetime(2024, 1, 1)


def sec(k):
    return AT + timedelta(seconds=k)


def build(spark, edges, run=0):
    """Edges 'A U B' or ('A U B', begin, end)."""
    rows, types = [], {}
    for e in edges:
        text, b, z = e if isinstance(e, tuple) else (e, None, None)
        src, lab, dst = text.split()
        rows.append((run, src, dst, LABEL[lab], None if b is None else sec(b), None if z is None else sec(z)))
        types[src], types[dst] = ENDS[LABEL[lab]]
    e = spark.createDataFrame(rows, "run_id long, src string, dst string, label string, t_begin timestamp_ntz, t_end timestamp_ntz").withColumn("n", F.lit(1))
    n = spark.createDataFrame([(run, k, v) for k, v in types.items()], "run_id long, node_id string, node_type string")
    return ProvGraph(nodes_of(n), edges_of(e))


def ids(spark, *names, run=0):
    return spark.createDataFrame([(run, n) for n in names], "run_id long, node_id string")


def groups(df):
    out = {}
    for r in df.collect():
        out.setdefault(r["group_id"], set()).add(r["node_id"])
    return {frozenset(v) for v in out.values()}


def names(df, col="node_id"):
    return {r[col] for r in df.collect()}


F9 = ["P1 I P0", "P2 I P0", "P3 I P2", "F1 G P1", "P2 U F1", "P1 U L1", "P1 U L2", "P2 U L1", "P2 U L2", "P1 U A1", "D G P2"]
F8 = [f"P{i} U F{i}" for i in (1, 2, 3)] + [f"P{i} U F4" for i in (1, 2, 3)]
F7 = ["P1 U A", "P2 U A", "B G P1"]
RING = [f"P{i} U F{(i + k) % 4}" for i in range(4) for k in (0, 1)]
SQUARES = [f"P{i} U F{j}" for h in (0, 2) for i in (h, h + 1) for j in (h, h + 1)]
